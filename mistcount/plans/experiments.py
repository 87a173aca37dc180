"""Experiments over grids of methods, budgets, sizes and trials.

`simulated` draws every cell of every sketch by keyed hashes, which SQL can repeat. `simulated_counts` draws level
counts only: cells of a level are independent and alike, so their number of ones is binomial. That is the same law at
a ten-thousandth of the draws, and lets the published 1,000 trials be run. `merged_trials` builds, flips, merges and
counts real sketches of numbered items, with nothing assumed about the union.
"""

from __future__ import annotations

import hashlib
import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import likelihood as lk
from ..functions import vectorised
from ..functions.budget import Flip, combine_or, half_flip, half_flip_loose, symmetric
from ..layout import Layout
from ..operators.baselines import BETA_GRID, BETA_LEAST, interval_estimate
from ..operators.simulate import private_levels

#: Methods by name: their flip at a budget, and whether the interval estimator is used.
METHODS = {
    "randomized": (symmetric, False),
    "xor": (half_flip, False),
    "interval_tight": (half_flip, True),
    "interval_loose": (half_flip_loose, True),
}


def settings(spark: SparkSession, methods: list[str], epsilons: list[float], sizes: list[float], trials: int) -> DataFrame:
    """A row a trial: method, eps, n, trial, p, q."""
    rows = []
    for method, eps, n in itertools.product(methods, epsilons, sizes):
        f: Flip = METHODS[method][0](eps)
        rows.append((method, float(eps), float(n), f.p, f.q))
    grid = spark.createDataFrame(rows, "method string, eps double, n double, p double, q double")
    return grid.crossJoin(spark.range(trials).select(F.col("id").cast("int").alias("trial")))


def simulated(spark: SparkSession, layout: Layout, methods: list[str], epsilons: list[float], sizes: list[float], trials: int, key: str = "trials") -> DataFrame:
    """n_hat and stderr of each trial, from independent-cell sketches."""
    by = ["method", "eps", "n", "trial"]
    grid = settings(spark, methods, epsilons, sizes, trials)
    levels = private_levels(grid, layout, key, ["method", "eps", "trial"])
    return _fitted(levels, layout, methods).select(*by, "n_hat", "status", "stderr")


def _random(*parts) -> np.random.Generator:
    """A generator that these parts determine."""
    return np.random.Generator(np.random.Philox(key=np.frombuffer(hashlib.sha256("|".join(map(str, parts)).encode()).digest()[:16], np.uint64)))


def level_draws(grid: DataFrame, layout: Layout, key: str) -> DataFrame:
    """grid (with n, p, q) and ones: level counts of noisy sketches of independent cells. Rows are told apart by all their columns."""
    rho, columns = np.array(layout.rho()), grid.columns

    def drawn(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in rows:
            out = []
            for row in batch.to_pylist():
                full = -np.expm1(row["n"] * np.log1p(-rho))
                out.append(_random("levels", key, layout, *row.values()).binomial(layout.buckets, row["q"] + (row["p"] - row["q"]) * full).tolist())
            yield pa.record_batch([*batch.columns, pa.array(out, pa.list_(pa.int64()))], names=[*columns, "ones"])

    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in grid.schema.fields)
    return grid.mapInArrow(drawn, f"{kinds}, ones array<bigint>")


def _fitted(levels: DataFrame, layout: Layout, methods: list[str]) -> DataFrame:
    """levels (method, n, p, q, ones) with n_hat, status and stderr at the true n."""
    p, q = F.col("p"), F.col("q")
    fitted, status = lk.estimate(F.col("ones"), layout, p, q)
    intervals = [m for m in methods if METHODS[m][1]]
    if not intervals:
        found = levels.withColumn("n_hat", fitted).withColumn("status", status)
    else:
        with_interval = F.col("method").isin(intervals)
        interval = interval_estimate(F.col("ones"), layout, p, q)
        found = levels.withColumn("n_hat", F.when(with_interval, interval).otherwise(fitted)).withColumn("status", F.when(with_interval, F.lit("ok")).otherwise(status))
    return found.withColumn("stderr", lk.stderr(layout, F.col("n"), p, q))


def fitted_counts(levels: DataFrame, layout: Layout) -> DataFrame:
    """levels (n, p, q, ones; with method, if some use the interval estimator) with n_hat (null where there is none), status
    and stderr at the true n, in place of ones. Sketches are fitted in batches, by numpy."""
    columns, betas = [c for c in levels.columns if c != "ones"], BETA_LEAST * np.exp(np.arange(BETA_GRID + 1) * np.log(1 / BETA_LEAST) / BETA_GRID)
    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in levels.select(*columns).schema.fields)

    def fitted(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in rows:
            for at in range(0, whole.num_rows, 1000):
                batch = whole.slice(at, 1000)
                ones, p, q = np.array(batch.column("ones").to_pylist()), batch.column("p").to_numpy(), batch.column("q").to_numpy()
                found = vectorised.fit(ones, layout, p, q)
                if "method" in columns:
                    other = np.array([METHODS.get(m, (None, False))[1] for m in batch.column("method").to_pylist()])
                    if other.any():
                        found[other] = vectorised.interval(ones[other], layout, p[other], q[other], betas)
                yield pa.record_batch([*(batch.column(c) for c in columns), pa.array(found, from_pandas=True)], names=[*columns, "n_hat"])

    done = levels.select(*columns, "ones").mapInArrow(fitted, f"{kinds}, n_hat double")
    status = F.when(F.col("n_hat").isNull(), "none").when(F.col("n_hat") == 0, "zero").otherwise("ok")
    return done.withColumn("status", status).withColumn("stderr", lk.stderr(layout, F.col("n"), F.col("p"), F.col("q")))


def simulated_counts(spark: SparkSession, layout: Layout, methods: list[str], epsilons: list[float], sizes: list[float], trials: int, key: str = "trials") -> DataFrame:
    """n_hat and stderr of each trial, from binomial level counts."""
    grid = settings(spark, methods, epsilons, sizes, trials).repartition(max(2, spark.sparkContext.defaultParallelism))
    return fitted_counts(level_draws(grid, layout, key), layout).select("method", "eps", "n", "trial", "n_hat", "status", "stderr")


def merged_trials(spark: SparkSession, layout: Layout, ks: list[int], epsilons: list[float], n: int, trials: int, key: str = "merged") -> DataFrame:
    """k, eps, n, trial, p, q, ones of randomized unions of k sketches that hold n items together.

    In each trial every item is put into its cell and dealt to one of max(ks) parties, which are joined in equal runs
    for smaller k. For each k and budget the parties' sketches are flipped, their noisy bits merged by the union's
    chances, and the ones of each level counted. Trials are tasks' rows; what a task holds is a few sketches.
    """
    most, cells = max(ks), layout.cells
    if any(most % k for k in ks):
        raise ValueError("every k must divide the largest one")

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in rows:
            for trial in batch.column("trial").to_pylist():
                r, out = _random("merge", key, layout, n, trial), []
                level = np.minimum(r.geometric(0.5, n), layout.levels).astype(np.int64) - 1
                at = r.integers(0, layout.buckets, n) * layout.levels + level
                held = np.zeros((most, cells), bool)
                held[r.integers(0, most, n), at] = True
                for k in ks:
                    bits = held.reshape(k, most // k, cells).any(axis=1)
                    for eps in epsilons:
                        f = symmetric(eps)
                        u = r.random(bits.shape, np.float32)
                        ones = np.where(bits, u < f.p, u < f.q).sum(axis=0)
                        star = combine_or([eps] * k)
                        # the chance of a merged 1 by the number of noisy ones, as operators.merge.merge_chance has it
                        m = np.arange(k + 1)
                        chance = np.where(m == 0, 0.0, (1 - np.where(m % 2, -1.0, 1.0) * np.exp(-eps * m)) / (1 + np.exp(-star)))
                        merged = (r.random(cells) < chance[ones]).reshape(layout.buckets, layout.levels).sum(axis=0)
                        g = symmetric(star)
                        out.append((k, eps, float(n), trial, g.p, g.q, merged.tolist()))
                kinds = (pa.int32(), pa.float64(), pa.float64(), pa.int32(), pa.float64(), pa.float64(), pa.list_(pa.int64()))
                yield pa.record_batch([pa.array(list(x), t) for x, t in zip(zip(*out, strict=True), kinds, strict=True)], names=["k", "eps", "n", "trial", "p", "q", "ones"])

    each = spark.range(trials, numPartitions=max(2, min(trials, 4 * spark.sparkContext.defaultParallelism))).select(F.col("id").cast("int").alias("trial"))
    return each.mapInArrow(run, "k int, eps double, n double, trial int, p double, q double, ones array<bigint>")


def fitted_unions(levels: DataFrame, layout: Layout) -> DataFrame:
    """n_hat of merged sketches' level counts, and stderr at the true n."""
    return fitted_counts(levels, layout).select("k", "eps", "n", "trial", "n_hat", "stderr")


def register_trials(spark: SparkSession, buckets: list[int], n: int, trials: int, key: str = "registers", levels: int = 24) -> DataFrame:
    """buckets, n, trial, n_hat of the harmonic mean of registers: each bucket's highest level among a Poisson share of the items."""

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in rows:
            out = []
            for b, trial in zip(batch.column("buckets").to_pylist(), batch.column("trial").to_pylist(), strict=True):
                r = _random("registers", key, b, n, trial)
                share = r.multinomial(n, np.full(b, 1 / b))
                # the highest of m levels is at most j with chance (1 - 2^-j)^m
                with np.errstate(divide="ignore"):
                    top = -np.log2(-np.expm1(np.log(r.random(b)) / np.maximum(share, 1)))
                height = np.where(share == 0, 0, np.minimum(np.ceil(top), levels))
                raw = 0.7213 / (1 + 1.079 / b) * b * b / np.exp2(-height).sum()
                empty = int((height == 0).sum())
                out.append((b, float(n), trial, float(b * np.log(b / empty)) if raw <= 2.5 * b and empty else float(raw)))
            if out:
                yield pa.record_batch([pa.array(list(x), t) for x, t in zip(zip(*out, strict=True), (pa.int32(), pa.float64(), pa.int32(), pa.float64()), strict=True)], names=["buckets", "n", "trial", "n_hat"])

    grid = spark.createDataFrame([(b,) for b in buckets], "buckets int").crossJoin(spark.range(trials).select(F.col("id").cast("int").alias("trial")))
    return grid.repartition(max(2, spark.sparkContext.defaultParallelism)).mapInArrow(run, "buckets int, n double, trial int, n_hat double")


def relative_error(runs: DataFrame, by: list[str]) -> DataFrame:
    """rrmse and the mean relative standard error by the formula, of finite estimates."""
    square: Column = F.avg(F.pow(F.col("n_hat") - F.col("n"), 2))
    extra = [(F.avg("stderr") / F.avg("n")).alias("rel_stderr")] if "stderr" in runs.columns else []
    return runs.groupBy(*by).agg((F.sqrt(square) / F.avg("n")).alias("rrmse"), *extra)
