"""Private, mergeable distinct counting on Spark."""
