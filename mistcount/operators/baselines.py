"""Methods to compare with: the earlier private sketch and its estimator, and non-private sketches."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import likelihood as lk
from ..functions.budget import Flip, symmetric
from ..functions.hashing import bucket_level, cell_of, md5_60
from ..functions.noise import bernoulli, draw, uniform
from ..layout import Bloom, Layout
from .build import densify, level_counts, set_cells, sketch
from .estimate import cardinality
from .privatize import flip

#: Places of the tolerance's geometric grid.
BETA_GRID, BETA_LEAST = 200, 1e-4


def _level_share(ones: Column, layout: Layout, p: Column, q: Column) -> Column:
    """Unbiased chance that a cell of a level is missed, by level, with the level's log g."""
    rho = F.array(*[F.lit(r) for r in layout.rho()])
    return F.zip_with(ones, rho, lambda k, r: F.struct(((p - k / float(layout.buckets)) / (p - q)).alias("s"), F.log1p(-r).alias("lg")))


def _interval(shares: Column, beta: Column, relative: bool) -> Column:
    """Intersection of the levels' intervals for n at a tolerance."""

    def ends(x: Column) -> Column:
        slack = beta * F.abs(x["s"]) if relative else beta
        low_s, high_s = x["s"] + slack, x["s"] - slack
        low = F.when(low_s <= 0, F.lit(float("inf"))).otherwise(F.log(F.least(F.lit(1.0), F.greatest(low_s, F.lit(1e-300)))) / x["lg"])
        high = F.when(high_s <= 0, F.lit(float("inf"))).otherwise(F.log(F.greatest(high_s, F.lit(1e-300))) / x["lg"])
        return F.struct(low.alias("a"), F.when(high_s >= 1, F.lit(0.0)).otherwise(high).alias("b"))

    all_ = F.transform(shares, ends)
    return F.struct(F.array_max(F.transform(all_, lambda x: x["a"])).alias("a"), F.array_min(F.transform(all_, lambda x: x["b"])).alias("b"))


def interval_estimate(ones: Column, layout: Layout, p, q, relative: bool = False) -> Column:
    """The midpoint of the levels' intersection at the least tolerance of a geometric grid at which it is
    neither empty nor unbounded. The earlier work's own intervals aren't known; these are one reading of them:
    each level's share of empty cells, give or take the tolerance."""
    p, q = lk._num(p), lk._num(q)
    shares = _level_share(ones, layout, p, q)
    step = math.log(1 / BETA_LEAST) / BETA_GRID
    tried = F.transform(F.sequence(F.lit(0), F.lit(BETA_GRID)), lambda i: _interval(shares, BETA_LEAST * F.exp(i * step), relative))
    fit = F.filter(tried, lambda x: (x["a"] <= x["b"]) & (x["b"] < float("inf")) & (x["a"] < float("inf")))
    first = F.get(fit, F.lit(0))
    return (first["a"] + first["b"]) / 2


def interval_estimate_fixed(ones: Column, layout: Layout, p, q, beta: float) -> Column:
    """The same at one tolerance: null where the intersection is empty or unbounded."""
    p, q = lk._num(p), lk._num(q)
    x = _interval(_level_share(ones, layout, p, q), F.lit(beta), False)
    return F.when((x["a"] <= x["b"]) & (x["b"] < float("inf")), (x["a"] + x["b"]) / 2)


def interval_method(df: DataFrame, item: Column, layout: Layout, mechanism: Flip, key: str, release: str, by: list[str] | None = None) -> DataFrame:
    """Half flips with the interval estimator: tight or loose by the mechanism."""
    noisy = flip(sketch(df, item, layout, by), mechanism, key, release, by)
    levels = level_counts(noisy, layout, by)
    return levels.withColumn("n_hat", interval_estimate(F.col("ones"), layout, mechanism.p, mechanism.q))


def xor_subsample_build(df: DataFrame, item: Column, row_key: Column, layout: Layout, key: str, by: list[str] | None = None) -> DataFrame:
    """The earlier method's build: each row, repeats included, is kept by a fair coin and XORed into its cell.
    Ones become fair coins, zeros stay; row_key must be unique."""
    by = by or []
    coin = F.pmod(draw("coin", key, row_key), F.lit(2))
    cells = df.where(item.isNotNull()).select(*by, cell_of(item, layout).alias("cell"), coin.alias("c")).groupBy(*by, "cell").agg(F.pmod(F.sum("c"), F.lit(2)).cast("int").alias("bit"))
    ones = cells.where("bit = 1").select(*by, "cell")
    return densify(ones, df.select(*by).distinct() if by else df, layout, by)


def pcsa(df: DataFrame, item: Column, layout: Layout, by: list[str] | None = None, estimator: str = "likelihood") -> DataFrame:
    """The sketch without privacy, fitted by likelihood or by the classic mean of first unset levels."""
    by = by or []
    cells = sketch(df, item, layout, by)
    if estimator == "likelihood":
        return cardinality(level_counts(cells, layout, by), layout, 1.0, 0.0).select(*by, "n_hat", "stderr", "status")
    bucket, level = bucket_level(F.col("cell"), layout)
    first = cells.groupBy(*by, bucket.alias("bucket")).agg(F.coalesce(F.min(F.when(F.col("bit") == 0, level - 1)), F.lit(layout.levels)).alias("r"))
    # 0.77351: the classic constant of the mean first unset level
    return first.groupBy(*by).agg((layout.buckets / 0.77351 * F.pow(F.lit(2.0), F.avg("r"))).alias("n_hat"))


def registers(df: DataFrame, item: Column, layout: Layout, by: list[str] | None = None) -> DataFrame:
    """(by, bucket, r): the highest level of each bucket that has any."""
    bucket, level = bucket_level(F.col("cell"), layout)
    return set_cells(df, item, layout, by).groupBy(*(by or []), bucket.alias("bucket")).agg(F.max(level).alias("r"))


def hll(df: DataFrame, item: Column, layout: Layout, by: list[str] | None = None) -> DataFrame:
    """Harmonic mean of the highest levels, and linear counting while buckets are empty and counts small."""
    by, b = by or [], layout.buckets
    alpha = 0.7213 / (1 + 1.079 / b)
    sums = registers(df, item, layout, by).groupBy(*by).agg(F.count("*").alias("used"), F.sum(F.pow(F.lit(2.0), -F.col("r"))).alias("z"))
    raw = alpha * b * b / (F.col("z") + (b - F.col("used")))
    linear = b * F.log(b / F.greatest(b - F.col("used"), F.lit(1)))
    return sums.select(*by, F.when((raw <= 2.5 * b) & (F.col("used") < b), linear).otherwise(raw).alias("n_hat"))


def hll_likelihood(df: DataFrame, item: Column, layout: Layout, by: list[str] | None = None, steps: int = 60) -> DataFrame:
    """The likelihood of the registers when each bucket gets a Poisson number of items."""
    by, b, top = by or [], layout.buckets, layout.levels
    counts = registers(df, item, layout, by).groupBy(*by, "r").agg(F.count("*").alias("c"))
    arrays = counts.groupBy(*by).agg(F.map_from_entries(F.collect_list(F.struct("r", "c"))).alias("m"), F.sum("c").alias("used"))
    at = F.transform(F.sequence(F.lit(1), F.lit(top)), lambda j: F.coalesce(F.element_at("m", j), F.lit(0)))

    def rises(n: Column) -> Column:
        # a register is at most j with chance exp(-(n / b) 2^-j); d/dn of the log of the step from j - 1 to j
        def part(c: Column, i: Column) -> Column:
            j = i + 1
            high = F.when(j == top, 0.0).otherwise(F.pow(F.lit(2.0), -j))
            low = F.pow(F.lit(2.0), -(j - 1))
            e = F.exp(-n / b * (low - high))
            return c * (-high / b + (low - high) / b * F.coalesce(F.try_divide(e, 1 - e), F.lit(0.0)))

        return F.aggregate(F.transform(at, part), -(b - F.col("used")) / float(b), lambda a, x: a + x) > 0

    def halve(s: Column, _: Column) -> Column:
        mid = (s["a"] + s["b"]) / 2
        up = rises(F.exp(mid))
        return F.struct(F.when(up, mid).otherwise(s["a"]).alias("a"), F.when(up, s["b"]).otherwise(mid).alias("b"))

    found = F.aggregate(F.sequence(F.lit(1), F.lit(steps)), F.struct(F.lit(0.0).alias("a"), F.lit(25.0).alias("b")), halve, lambda s: F.exp((s["a"] + s["b"]) / 2))
    return arrays.select(*by, found.alias("n_hat"))


def exact(df: DataFrame, item: str, by: list[str] | None = None) -> DataFrame:
    return df.groupBy(*(by or [])).agg(F.count_distinct(item).alias("n"))


def native(df: DataFrame, item: str, by: list[str] | None = None, lg_k: int = 12) -> DataFrame:
    """What Spark has of its own, side by side."""
    return df.groupBy(*(by or [])).agg(
        F.approx_count_distinct(item).alias("approx_count_distinct"), F.hll_sketch_estimate(F.hll_sketch_agg(item, lg_k)).alias("hll_sketch"),
        F.expr(f"theta_sketch_estimate(theta_sketch_agg({item}, {lg_k}))").alias("theta_sketch"), F.count_distinct(item).alias("n"),
    )


def noisy_estimate(df: DataFrame, item: Column, layout: Layout, epsilon: float, sensitivity: float, key: str, release: str, by: list[str] | None = None) -> DataFrame:
    """Laplace noise on the estimate only: the sketch behind it stays sensitive. The caller vouches for the sensitivity,
    and for a release that changes with the data: two estimates of one release have the same noise."""
    by = by or []
    v = uniform(draw("laplace", key, release, *[F.col(c) for c in by])) - 0.5
    noise = -(sensitivity / epsilon) * F.signum(v) * F.log1p(-F.least(2 * F.abs(v), F.lit(1 - 1e-12)))
    return hll(df, item, layout, by).withColumn("n_hat", F.col("n_hat") + noise)


def bloom_union(df_a: DataFrame, df_b: DataFrame, item: Column, layout: Bloom, epsilon: float, key: str, releases: tuple[str, str]) -> DataFrame:
    """Union of exactly two perturbed Bloom filters, released under two names: both bits' flips are inverted together, cell by cell."""
    if len(set(releases)) < 2:
        raise ValueError("two filters need two releases, or they share their noise")
    f = symmetric(epsilon / layout.hashes)
    noisy = [flip(sketch(df, item, layout), f, key, name) for df, name in zip((df_a, df_b), releases, strict=True)]
    pair = noisy[0].withColumnRenamed("bit", "x").join(noisy[1].withColumnRenamed("bit", "y"), "cell")
    inverse = lambda c: (f.p - F.col(c)) / (f.p - f.q)
    empty = pair.agg(F.avg(inverse("x") * inverse("y")).alias("empty"))
    return empty.select("empty", (F.log(F.least(F.lit(1.0), F.greatest("empty", F.lit(1e-9)))) / math.log1p(-layout.rho()[0])).alias("n_hat"))


def subsampled(df: DataFrame, item: Column, rate: float, layout: Layout, mechanism: Flip, key: str, release: str, solver: str = "safe") -> DataFrame:
    """Items are kept by hash at a rate before the flips. Not differentially private as published; for comparison only."""
    kept = df.where(item.isNotNull() & (F.pmod(md5_60(F.concat_ws("|", F.lit("sample"), item.cast("string"))), F.lit(1 << 20)) < int(rate * (1 << 20))))
    levels = level_counts(flip(sketch(kept, item, layout), mechanism, key, release), layout)
    return cardinality(levels, layout, mechanism.p, mechanism.q, solver).withColumn("n_hat", F.col("n_hat") / rate)


def union_joint(cells: DataFrame, layout: Layout, p: float, q: float, by: list[str] | None = None) -> DataFrame:
    """The union's size straight from k noisy sketches of equal budgets, without merging them: by level, the
    mean product of the bits' inverted flips is unbiased for the share of cells empty in all; then n by least
    squares over levels weighted by that share's information."""
    by = by or []
    counts = cells.groupBy(*by, "cell").agg(F.sum("bit").alias("m"), F.count("*").alias("k"))
    # a one contributes (p - 1) / (p - q), a zero p / (p - q)
    product = F.pow(F.lit((p - 1) / (p - q)), F.col("m")) * F.pow(F.lit(p / (p - q)), F.col("k") - F.col("m"))
    level = F.pmod("cell", F.lit(layout.levels))
    shares = counts.groupBy(*by, level.alias("level")).agg(F.avg(product).alias("empty")).groupBy(*by).agg(F.transform(F.sort_array(F.collect_list(F.struct("level", "empty"))), lambda x: x["empty"]).alias("e"))
    rho = F.array(*[F.lit(r) for r in layout.rho()])

    def slope(n: Column) -> Column:
        # derivative of the weighted squares, up to a positive factor
        return F.aggregate(F.zip_with("e", rho, lambda e, r: (e - F.exp(n * F.log1p(-r))) * F.exp(n * F.log1p(-r)) * F.log1p(-r)), F.lit(0.0), lambda a, x: a + x) > 0

    def halve(s: Column, _: Column) -> Column:
        mid = (s["a"] + s["b"]) / 2
        up = ~slope(F.exp(mid))
        return F.struct(F.when(up, s["a"]).otherwise(mid).alias("a"), F.when(up, mid).otherwise(s["b"]).alias("b"))

    found = F.aggregate(F.sequence(F.lit(1), F.lit(60)), F.struct(F.lit(0.0).alias("a"), F.lit(25.0).alias("b")), halve, lambda s: F.exp((s["a"] + s["b"]) / 2))
    return shares.select(*by, found.alias("n_hat"))
