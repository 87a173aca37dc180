"""SQL functions: plain expressions that Catalyst inlines."""

from __future__ import annotations

from pyspark.sql import SparkSession

from ..layout import Layout

FUNCTIONS = {
    "sk_effective_eps": "(e1 DOUBLE, e2 DOUBLE) RETURNS DOUBLE RETURN -ln(exp(-e1) + exp(-e2) - exp(-e1 - e2))",
    "sk_xor_eps": "(e1 DOUBLE, e2 DOUBLE) RETURNS DOUBLE RETURN ln((1 + exp(e1 + e2)) / (exp(e1) + exp(e2)))",
    "sk_merge_prob": "(ones BIGINT, spent DOUBLE, eps DOUBLE) RETURNS DOUBLE RETURN CASE WHEN ones = 0 THEN 0D ELSE (1 - (CASE WHEN ones % 2 = 0 THEN 1 ELSE -1 END) * exp(-spent)) / (1 + exp(-eps)) END",
    "sk_epsilon": "(p DOUBLE, q DOUBLE) RETURNS DOUBLE RETURN ln(greatest(p / q, (1 - q) / (1 - p)))",
}


def register(spark: SparkSession, layout: Layout | None = None) -> None:
    """sk_effective_eps, sk_xor_eps, sk_merge_prob, sk_epsilon, and sk_cell and sk_stderr for a layout."""
    layout = layout or Layout()
    for name, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    # md5 cells: the first 60 bits, bucket from the remainder, level from the trailing zeros of the quotient
    h = f"cast(conv(substr(md5(cast(concat_ws('|', '{layout.seed}:0', item) AS BINARY)), 1, 15), 16, 10) AS BIGINT)"
    rest = f"({h} div {layout.buckets})"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sk_cell(item STRING) RETURNS INT RETURN cast({h} % {layout.buckets} * {layout.levels} + least({layout.levels}, bit_count({rest} ^ ({rest} - 1))) - 1 AS INT)")
    rho = "array(" + ", ".join(f"{r!r}D" for r in layout.rho()) + ")"
    term = "log1p(-r) * log1p(-r) * exp(n * log1p(-r)) * (p / (p - (p - q) * exp(n * log1p(-r))) - (1 - p) / (1 - p + (p - q) * exp(n * log1p(-r))))"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sk_stderr(n DOUBLE, p DOUBLE, q DOUBLE) RETURNS DOUBLE RETURN 1 / sqrt({layout.buckets} * (p - q) * aggregate(transform({rho}, r -> {term}), 0D, (a, x) -> a + x))")
