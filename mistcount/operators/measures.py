"""Accuracy and cost of estimates. Input: a row a trial, with n_hat and the true n."""

from __future__ import annotations

import time

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..layout import Layout


def _error() -> Column:
    return F.col("n_hat") - F.col("n")


def accuracy(df: DataFrame, by: list[str]) -> DataFrame:
    """Trials, failures, bias, variance, mse and relative root mean squared error; trials without an estimate only count as failures."""
    return df.groupBy(*by).agg(
        F.count("*").alias("trials"), F.avg(F.col("n_hat").isNull().cast("int")).alias("failure_rate"), F.avg(_error()).alias("bias"),
        F.var_pop("n_hat").alias("variance"), F.avg(F.pow(_error(), 2)).alias("mse"), (F.sqrt(F.avg(F.pow(_error(), 2))) / F.avg("n")).alias("rrmse"),
    )


def relative_efficiency(scores: DataFrame, by: list[str], against: str, method: str = "method") -> DataFrame:
    """MSE of each method over that of `against`: how much more space it needs for the same error."""
    base = F.max(F.when(F.col(method) == against, F.col("mse"))).over(Window.partitionBy(*by) if by else Window.partitionBy(F.lit(0)))
    return scores.withColumn("relative_efficiency", F.try_divide("mse", base))


def calibration(df: DataFrame, by: list[str]) -> DataFrame:
    """Estimated over empirical error; near 1 if the error formula holds."""
    return df.groupBy(*by).agg((F.sqrt(F.avg(F.pow("stderr", 2))) / F.sqrt(F.avg(F.pow(_error(), 2)))).alias("calibration"))


def coverage(df: DataFrame, by: list[str]) -> DataFrame:
    return df.groupBy(*by).agg(F.avg(((F.col("ci_low") <= F.col("n")) & (F.col("n") <= F.col("ci_high"))).cast("int")).alias("coverage"))


def space_bits(layout: Layout) -> dict[str, int]:
    """Bits of the bitmap sketch, and of registers for the highest level of each bucket."""
    return {"sketch": layout.cells, "registers": layout.buckets * layout.levels.bit_length()}


def timed(df: DataFrame) -> float:
    """Seconds that all rows of df take; nothing is kept."""
    began = time.monotonic()
    df.write.format("noop").mode("overwrite").save()
    return time.monotonic() - began


def empirical_epsilon(pairs: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Greatest log-odds of an output bit between neighbours. pairs: bit (true), noisy."""
    rates = pairs.groupBy(*(by or [])).agg(F.avg(F.when(F.col("bit") == 1, F.col("noisy"))).alias("p"), F.avg(F.when(F.col("bit") == 0, F.col("noisy"))).alias("q"))
    return rates.withColumn("epsilon", F.log(F.greatest(F.col("p") / F.col("q"), (1 - F.col("q")) / (1 - F.col("p")))))


def loglog_slope(df: DataFrame, x: str, y: str, by: list[str]) -> DataFrame:
    return df.groupBy(*by).agg(F.regr_slope(F.log(y), F.log(x)).alias("slope"))
