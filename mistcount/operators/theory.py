"""Claims that can be checked by enumeration."""

from __future__ import annotations

import itertools
import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.budget import combine_or
from ..functions.noise import draw
from ..layout import Layout


def deterministic_merge_feasibility(spark: SparkSession, grid: int = 16) -> DataFrame:
    """For each symmetric deterministic operation and target (or, and), the flips p, q on a grid for which
    op(F(x), F(y)) has a law that depends on target(x, y) alone, differs for its values, and has q <= 1/2 <= p.

    Columns: op (outputs for 00, 01 = 10, 11), target, p, q, works.
    """
    steps = spark.range(1, 2 * grid).select((F.col("id") / (2.0 * grid)).alias("v"))
    pairs = steps.select(F.col("v").alias("p")).where("p >= 0.5").crossJoin(F.broadcast(steps.select(F.col("v").alias("q")).where("q <= 0.5"))).where("q < p")
    ops = spark.createDataFrame([(f"{a}{b}{c}", a, b, c) for a, b, c in itertools.product((0, 1), repeat=3)], "op string, o0 int, o1 int, o2 int")
    targets = spark.createDataFrame([("or",), ("and",)], "target string")
    rows = pairs.crossJoin(F.broadcast(ops)).crossJoin(F.broadcast(targets))

    def chance(a, b):  # of a 1, when the two noisy bits are 1 with chances a and b
        return (1 - a) * (1 - b) * F.col("o0") + (a * (1 - b) + (1 - a) * b) * F.col("o1") + a * b * F.col("o2")

    p, q = F.col("p"), F.col("q")
    f00, f01, f11 = chance(q, q), chance(q, p), chance(p, p)
    same = lambda x, y: F.abs(x - y) < 1e-12
    is_or = F.col("target") == "or"
    one, zero = F.when(is_or, f01).otherwise(f11), f00
    consistent = F.when(is_or, same(f01, f11)).otherwise(same(f00, f01))
    works = consistent & ~same(one, zero) & (zero <= 0.5 + 1e-12) & (one >= 0.5 - 1e-12)
    return rows.select("op", "target", "p", "q", works.alias("works"))


def max_feasible_eps(spark: SparkSession, epsilons: list[float], step: float = 1e-3) -> DataFrame:
    """The largest budget on a grid at which a randomized union of these sketches has chances in [0, 1].

    The chances follow from inverting the flips, input by input: 2^k inputs for each place of the grid.
    """
    k = len(epsilons)
    grid = spark.range(1, int(max(epsilons) / step) + 1).select((F.col("id") * step).alias("eps"))
    inputs = spark.range(1 << k).select(F.col("id").alias("bits"))
    ws = F.array(*[F.lit(math.exp(-e)) for e in epsilons])
    # the inverse of a flip has rows (1, -w) and (-w, 1) over 1 - w, so for the target (q, 1 - q, ..., 1 - q)
    # the chance is (1 - q) - (1 - 2 q) * product over bits of (1 or -w) / (1 - w)
    product = F.aggregate(F.transform(ws, lambda w, i: F.when(F.expr("0") == F.call_function("getbit", F.col("bits"), i), F.lit(1.0)).otherwise(-w) / (1 - w)), F.lit(1.0), lambda a, x: a * x)
    q = 1 / (F.exp("eps") + 1)
    t = (1 - q) - (1 - 2 * q) * product
    fits = grid.crossJoin(F.broadcast(inputs)).groupBy("eps").agg(F.min(t).alias("least"), F.max(t).alias("most"))
    return fits.where("least >= -1e-12 and most <= 1 + 1e-12").agg(F.max("eps").alias("max_eps")).withColumn("law_eps", F.lit(combine_or(epsilons)))


def coupling_agreement(spark: SparkSession, n: int, layout: Layout, trials: int, key: str) -> DataFrame:
    """How often three coupled sketches agree in all bits (trials, n, share_equal: all three; share_poisson: the first two;
    mean_differ: cells in which not all agree): one of n items, one of the same stream cut or carried on to a Poisson
    length, and one of independent cells with the first one's margins.

    The Poisson length is a rounded normal draw of the same mean and variance. The bits of the second sketch are
    independent; each gets a uniform that lies below its chance of a 1 exactly if it is one, and the third sketch's bit is
    whether that uniform lies below its own chance.
    """
    trial = spark.range(trials).select(F.col("id").alias("trial"))
    u1, u2 = (F.greatest(draw("sim", key, f"len{i}", F.col("trial")) / float(1 << 52), F.lit(1e-15)) for i in (1, 2))
    normal = F.sqrt(-2 * F.log(u1)) * F.cos(6.283185307179586 * u2)
    lengths = trial.withColumn("len", F.greatest(F.lit(0), F.round(n + normal * n**0.5)).cast("long"))
    longest = int(n + 8 * n**0.5) + 1
    rows = spark.range(longest).select(F.col("id").alias("i")).crossJoin(F.broadcast(lengths))
    bucket = F.pmod(draw("sim", key, "bucket", F.col("trial"), F.col("i")), F.lit(layout.buckets))
    bits = draw("sim", key, "level", F.col("trial"), F.col("i"))
    level = F.least(F.lit(layout.levels), F.bit_count(bits.bitwiseXOR(bits - 1)))
    cells = rows.select("trial", (bucket * layout.levels + level - 1).cast("int").alias("cell"), (F.col("i") < n).alias("fixed"), (F.col("i") < F.col("len")).alias("poisson"))
    per_cell = cells.groupBy("trial", "cell").agg(F.max(F.col("fixed").cast("int")).alias("f"), F.max(F.col("poisson").cast("int")).alias("p"))
    grid = trial.crossJoin(F.broadcast(spark.range(layout.cells).select(F.col("id").cast("int").alias("cell"))))
    rho = F.element_at(F.array(*[F.lit(r) for r in layout.rho()]), F.pmod("cell", F.lit(layout.levels)) + 1)
    every = grid.join(per_cell, ["trial", "cell"], "left").select("trial", "cell", F.coalesce("f", F.lit(0)).alias("f"), F.coalesce("p", F.lit(0)).alias("p"), rho.alias("rho"))
    v, one = draw("sim", key, "couple", F.col("trial"), F.col("cell")) / float(1 << 52), -F.expm1(-n * F.col("rho"))
    uniform = F.when(F.col("p") == 1, v * one).otherwise(one + v * (1 - one))
    alone = (uniform < -F.expm1(n * F.log1p(-F.col("rho")))).cast("int")
    diff = every.withColumn("i", alone).groupBy("trial").agg(F.sum(((F.col("f") != F.col("p")) | (F.col("p") != F.col("i"))).cast("int")).alias("differ"), F.sum((F.col("f") != F.col("p")).cast("int")).alias("two"))
    same = lambda c: F.avg((F.col(c) == 0).cast("int"))
    return diff.agg(F.count("*").alias("trials"), same("differ").alias("share_equal"), same("two").alias("share_poisson"), F.avg("differ").alias("mean_differ")).withColumn("n", F.lit(n))


def membership_leak(items: DataFrame, item, cells: DataFrame, layout: Layout) -> DataFrame:
    """Items that a plain sketch proves absent: a cell of theirs is 0, as anyone with the public hash can see."""
    from ..functions.hashing import cell_of

    ones = cells.where("bit = 1").select("cell").distinct()
    return items.withColumn("cell", cell_of(item, layout)).join(ones, "cell", "left_anti").drop("cell")
