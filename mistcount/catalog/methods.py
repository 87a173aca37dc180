"""Queries of the methods themselves."""

from __future__ import annotations

import itertools
import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import budget as bd
from ..functions import likelihood as lk
from ..functions.hashing import bucket_level, cell_of, joined
from ..layout import Bloom, Exponential, Layout, LinearCounting
from ..operators import boolean as bo
from ..operators import merge as mg
from ..operators import simulate, theory
from ..operators.build import level_counts, packed, set_cells, sketch, unpack
from ..operators.estimate import asymptotic_constant, cardinality, plan_buckets, plan_epsilon, stderr_after_merge
from ..operators.privatize import bound_groups, flip, flip_symmetric
from ..plans import arrow
from ..sources.io import read_table
from . import sql as S
from .registry import query

#: The default shape, and a smaller one for many groups; md5 so that DuckDB has the same cells.
WIDE = Layout(4096, 24, family="md5")
SMALL = Layout(256, 16, family="md5")
#: A public key: what it protects is not private.
KEY = "public-test-key"


def line_items(spark: SparkSession, d: str) -> DataFrame:
    """One group of line item keys (orderkey, linenumber), which repeat."""
    return read_table(spark, d, "lineitem").select(F.lit("all").alias("g"), joined(F.col("l_orderkey"), F.col("l_linenumber")).alias("item"), "l_suppkey")


LINES = "SELECT 'all' AS g, concat_ws('|', l_orderkey, l_linenumber) AS item, l_suppkey FROM lineitem"


def order_items(spark: SparkSession, d: str) -> DataFrame:
    """Customers of orders by priority."""
    return read_table(spark, d, "orders").select(F.col("o_orderpriority").alias("g"), F.col("o_custkey").cast("string").alias("item"))


ORDERS = "SELECT o_orderpriority AS g, CAST(o_custkey AS VARCHAR) AS item FROM orders"


_SIZES = "SELECT l_returnflag AS g, CAST(count(DISTINCT l_partkey) AS DOUBLE) AS n FROM lineitem GROUP BY 1"


def group_sizes(spark: SparkSession, d: str) -> DataFrame:
    """g, n: how many parts the line items of each return flag have."""
    return read_table(spark, d, "lineitem").groupBy(F.col("l_returnflag").alias("g")).agg(F.count_distinct("l_partkey").cast("double").alias("n"))


_RATES = "SELECT l_discount AS a, l_tax AS b, count(*) AS n_lines FROM lineitem GROUP BY ALL"


def line_rates(spark: SparkSession, d: str) -> DataFrame:
    """a, b, n_lines: pairs of discount and tax of line items, as stand-ins for choices that rows carry."""
    return read_table(spark, d, "lineitem").groupBy(F.col("l_discount").alias("a"), F.col("l_tax").alias("b")).agg(F.count("*").alias("n_lines"))


def party_items(spark: SparkSession, d: str, k: int = 4) -> DataFrame:
    """Line items by party: suppliers modulo k; parties overlap in items."""
    return line_items(spark, d).withColumn("party", F.pmod("l_suppkey", F.lit(k)).cast("string"))


def party_sql(k: int = 4) -> str:
    return f"SELECT CAST(l_suppkey % {k} AS VARCHAR) AS party, item FROM ({LINES})"


def csv(ones: Column) -> Column:
    return F.array_join(F.transform(ones, lambda x: x.cast("string")), ",")


def rounded(df: DataFrame, **digits: int) -> DataFrame:
    return df.withColumns({c: F.round(c, n) for c, n in digits.items()})


# --- hashing and plain sketches


@query("m01_cell_hashing", f"SELECT CAST(cell % 24 + 1 AS INTEGER) AS level, count(*) AS n_items, count(DISTINCT cell // 24) AS n_buckets FROM (SELECT DISTINCT item, {S.cell('item', WIDE)} AS cell FROM ({LINES})) GROUP BY 1")
def m01(spark: SparkSession, d: str) -> DataFrame:
    rows = line_items(spark, d).select("item").distinct().select(cell_of(F.col("item"), WIDE).alias("cell"))
    bucket, level = bucket_level(F.col("cell"), WIDE)
    return rows.groupBy(level.alias("level")).agg(F.count("*").alias("n_items"), F.count_distinct(bucket).alias("n_buckets"))


@query("m02_plain_sketch", S.ones_csv(S.levels(S.dense(ORDERS, SMALL), SMALL)))
def m02(spark: SparkSession, d: str) -> DataFrame:
    return level_counts(sketch(order_items(spark, d), F.col("item"), SMALL, ["g"]), SMALL, ["g"]).select("g", csv(F.col("ones")).alias("ones"))


@query("m02_packed_sketch", f"SELECT g, (cell // 32768 + 1)::BIGINT AS bucket_no, count(*) AS n_ones FROM ({S.set_cells(LINES, WIDE)}) GROUP BY 1, 2")
def m02_packed(spark: SparkSession, d: str) -> DataFrame:
    return packed(line_items(spark, d), F.col("item"), WIDE, ["g"]).select("g", "bucket_no", F.bitmap_count("bits").alias("n_ones"))


@query("m02_packed_to_long", S.ones_csv(S.levels(S.dense(LINES, WIDE), WIDE)))
def m02_unpacked(spark: SparkSession, d: str) -> DataFrame:
    return level_counts(unpack(packed(line_items(spark, d), F.col("item"), WIDE, ["g"]), WIDE, ["g"]), WIDE, ["g"]).select("g", csv(F.col("ones")).alias("ones"))


@query("m02_xxhash_sketch")
def m02_fast(spark: SparkSession, d: str) -> DataFrame:
    layout = Layout()
    return level_counts(unpack(packed(line_items(spark, d), F.col("item"), layout, ["g"]), layout, ["g"]), layout, ["g"]).select("g", csv(F.col("ones")).alias("ones"))


@query("m03_union_plain", S.ones_csv(S.levels(S.dense(LINES, WIDE), WIDE)))
def m03(spark: SparkSession, d: str) -> DataFrame:
    parts = set_cells(party_items(spark, d), F.col("item"), WIDE, ["g", "party"]).withColumn("bit", F.lit(1))
    return level_counts(mg.union_plain(parts, ["g"]), WIDE, ["g"]).select("g", csv(F.col("ones")).alias("ones"))


@query("m03_union_packed", f"SELECT g, (cell // 32768 + 1)::BIGINT AS bucket_no, count(*) AS n_ones FROM ({S.set_cells(LINES, WIDE)}) GROUP BY 1, 2")
def m03_packed(spark: SparkSession, d: str) -> DataFrame:
    return mg.union_packed(packed(party_items(spark, d), F.col("item"), WIDE, ["g", "party"]), ["g"]).select("g", "bucket_no", F.bitmap_count("bits").alias("n_ones"))


# --- flips


def _noisy_orders(spark: SparkSession, d: str, f: bd.Flip, release: str) -> DataFrame:
    return flip(sketch(order_items(spark, d), F.col("item"), SMALL, ["g"]), f, KEY, release, ["g"])


def _noisy_sql(f: bd.Flip, release: str) -> str:
    return S.flip(S.dense(ORDERS, SMALL), f.p, f.q, KEY, release)


for _name, _flip in {
    "m04_randomized_response": bd.Flip(0.8, 0.3),
    "m06_half_flip": bd.half_flip(1.0),
    "m08_symmetric_flip": bd.symmetric(1.0),
    "b01_half_flip_loose": bd.half_flip_loose(1.0),
    "b01f_half_flip_appendix": bd.half_flip_appendix(1.0),
}.items():
    query(_name, S.ones_csv(S.levels(_noisy_sql(_flip, _name), SMALL)))(
        lambda spark, d, f=_flip, r=_name: level_counts(_noisy_orders(spark, d, f, r), SMALL, ["g"]).select("g", csv(F.col("ones")).alias("ones"))
    )

_PQ = f"SELECT 0.5::DOUBLE + 4.5::DOUBLE * a AS p, 0.5::DOUBLE - 5.0::DOUBLE * b AS q, n_lines FROM ({_RATES})"


@query("m05_dp_verifier", f"SELECT p, q, n_lines, round(ln(greatest(p / q, (1 - q) / (1 - p))), 9) AS epsilon, greatest(p / q, (1 - q) / (1 - p)) <= exp(1.0::DOUBLE) AS private_at_1 FROM ({_PQ})")
def m05(spark: SparkSession, d: str) -> DataFrame:
    """Flips that line items ask for: p from 0.5 by the discount, q from 0.5 down by the tax."""
    grid = line_rates(spark, d).select((0.5 + 4.5 * F.col("a")).alias("p"), (0.5 - 5.0 * F.col("b")).alias("q"), "n_lines")
    e = bd.epsilon_column(F.col("p"), F.col("q"))
    return grid.select("p", "q", "n_lines", F.round(e, 9).alias("epsilon"), (e <= 1.0).alias("private_at_1"))


# --- merges

_EPS = {"0": 3.0, "1": 2.0, "2": 2.5, "3": 4.0}
_EPS_SQL = "CASE party " + " ".join(f"WHEN '{k}' THEN {v}::DOUBLE" for k, v in _EPS.items()) + " END"


def _eps_column() -> Column:
    return F.element_at(F.create_map(*[F.lit(x) for kv in _EPS.items() for x in kv]), F.col("party"))


def released_parties(spark: SparkSession, d: str, epsilon: Column | float, layout: Layout = WIDE, k: int = 4) -> DataFrame:
    """Each party's own noisy sketch: party, cell, bit, eps."""
    bits = sketch(party_items(spark, d, k), F.col("item"), layout, ["party"])
    return flip_symmetric(bits, F.lit(float(epsilon)) if isinstance(epsilon, int | float) else epsilon, KEY, "parties", ["party"])


def released_sql(epsilon: str, layout: Layout = WIDE, k: int = 4) -> str:
    bits = f"SELECT *, {epsilon} AS eps FROM ({S.dense(party_sql(k), layout, 'party')})"
    return f"SELECT 'all' AS g, party, cell, bit, eps FROM ({S.flip(bits, '(1 - 1 / (exp(eps) + 1))', '(1 / (exp(eps) + 1))', KEY, 'parties', 'party', 'eps,')})"


def _union_sql(epsilon: str, keep: str = "star") -> str:
    merged = S.union_randomized(released_sql(epsilon), "union")
    counts = f"SELECT g, max(star) AS star, list(k ORDER BY level) AS k FROM (SELECT g, star, cell % 24 AS level, sum(bit)::BIGINT AS k FROM ({merged}) GROUP BY ALL) GROUP BY g"
    return S.fit(counts, WIDE, "(1 - 1 / (exp(star) + 1))", "(1 / (exp(star) + 1))", keep=keep)


def _union(spark: SparkSession, d: str, epsilon) -> DataFrame:
    noisy = released_parties(spark, d, epsilon).withColumn("g", F.lit("all"))
    levels = level_counts(mg.union_randomized(noisy, "union", ["g"]), WIDE, ["g"], ["eps_effective"])
    q = bd.symmetric_q(F.col("eps_effective"))
    return cardinality(levels, WIDE, 1 - q, q, "bisect")


@query("m07_union_xor", "SELECT g, round(n_hat, 3) AS n_hat FROM (" + S.fit(S.arrays(S.levels(f"SELECT 'all' AS g, cell, CAST(sum(bit) % 2 AS INTEGER) AS bit FROM ({S.flip(S.dense(party_sql(), WIDE, 'party'), 0.5, bd.half_flip(3.0).q, KEY, 'half', 'party')}) GROUP BY cell", WIDE)), WIDE, 0.5, 0.5 * math.exp(-bd.combine_or([3.0] * 4))) + ")")
def m07(spark: SparkSession, d: str) -> DataFrame:
    noisy = flip(sketch(party_items(spark, d), F.col("item"), WIDE, ["party"]), bd.half_flip(3.0), KEY, "half", ["party"]).withColumn("eps", F.lit(3.0)).withColumn("g", F.lit("all"))
    levels = level_counts(mg.union_xor(noisy, ["g"]), WIDE, ["g"])
    return cardinality(levels, WIDE, 0.5, 0.5 * math.exp(-bd.combine_or([3.0] * 4)), "bisect").select("g", F.round("n_hat", 3).alias("n_hat"))


@query("m09k_union_randomized", f"SELECT g, round(star, 9) AS eps_effective, round(n_hat, 3) AS n_hat FROM ({_union_sql('3.0::DOUBLE')})")
def m09k(spark: SparkSession, d: str) -> DataFrame:
    """In packed form throughout, with the noise of the long form."""
    f = bd.symmetric(3.0)
    plain = arrow.sketch_packed(party_items(spark, d), F.col("item"), WIDE, ["party"])
    noisy = arrow.flip_packed(plain, f, WIDE, KEY, "parties", ["party"], "cell").withColumn("eps", F.lit(3.0)).withColumn("g", F.lit("all"))
    levels = arrow.level_counts_packed(arrow.merge_packed(noisy, WIDE, ["g"], "union", "cell"), WIDE, ["g", "eps_effective"])
    q = bd.symmetric_q(F.col("eps_effective"))
    return cardinality(levels, WIDE, 1 - q, q, "bisect").select("g", F.round("eps_effective", 9).alias("eps_effective"), F.round("n_hat", 3).alias("n_hat"))


@query("m09k_union_long", f"SELECT g, round(star, 9) AS eps_effective, round(n_hat, 3) AS n_hat FROM ({_union_sql('3.0::DOUBLE')})")
def m09k_long(spark: SparkSession, d: str) -> DataFrame:
    return _union(spark, d, 3.0).select("g", F.round("eps_effective", 9).alias("eps_effective"), F.round("n_hat", 3).alias("n_hat"))


@query("m09n_mixed_budgets", f"SELECT g, round(star, 9) AS eps_effective, round(n_hat, 3) AS n_hat FROM ({_union_sql(_EPS_SQL)})")
def m09n(spark: SparkSession, d: str) -> DataFrame:
    return _union(spark, d, _eps_column()).select("g", F.round("eps_effective", 9).alias("eps_effective"), F.round("n_hat", 3).alias("n_hat"))


def _pair_sql(t: list[float]) -> str:
    u = S.draw("merge", "pair", "CAST(cell AS VARCHAR)")
    t_sql = "CASE 2 * x.bit + y.bit " + " ".join(f"WHEN {i} THEN {int(min(1.0, max(0.0, v)) * (1 << 52))}" for i, v in enumerate(t)) + " END"
    side = lambda p: f"SELECT cell, bit FROM ({released_sql('2.0::DOUBLE', k=2)}) WHERE party = '{p}'"
    return f"SELECT 'all' AS g, x.cell, CAST({u.replace('CAST(cell', 'CAST(x.cell')} < {t_sql} AS INTEGER) AS bit FROM ({side(0)}) x JOIN ({side(1)}) y ON x.cell = y.cell"


@query("m09_union_pair", S.ones_csv(S.levels(_pair_sql(bd.transition(2.0, 2.0)), WIDE)))
def m09(spark: SparkSession, d: str) -> DataFrame:
    noisy = released_parties(spark, d, 2.0, k=2)
    merged = mg.merge_pair(noisy.where("party = '0'"), noisy.where("party = '1'"), 2.0, 2.0, "pair").withColumn("g", F.lit("all"))
    return level_counts(merged, WIDE, ["g"]).select("g", csv(F.col("ones")).alias("ones"))


_PAIRS = f"SELECT 0.25::DOUBLE + 40.0::DOUBLE * a AS e1, 0.25::DOUBLE + 50.0::DOUBLE * b AS e2, n_lines FROM ({_RATES})"


def budget_pairs(spark: SparkSession, d: str) -> DataFrame:
    """e1, e2, n_lines: two parties' budgets for each line item, from 0.25 up by its discount and tax."""
    return line_rates(spark, d).select((0.25 + 40.0 * F.col("a")).alias("e1"), (0.25 + 50.0 * F.col("b")).alias("e2"), "n_lines")


@query("m09g_transition", f"SELECT e1, e2, n_lines, 0.0::DOUBLE AS t00, round(r * (1 + w2), 9) AS t01, round(r * (1 + w1), 9) AS t10, round(r * (1 - w1 * w2), 9) AS t11 FROM (SELECT *, exp(-e1) AS w1, exp(-e2) AS w2, 1 / (2 - (1 - exp(-e1)) * (1 - exp(-e2))) AS r FROM ({_PAIRS}))")
def m09g(spark: SparkSession, d: str) -> DataFrame:
    """From the matrix inverse; the SQL has the closed form."""
    solved = F.udf(lambda a, b: [abs(round(x, 9)) if i == 0 else round(x, 9) for i, x in enumerate(bd.transition(a, b))], "array<double>")
    rows = budget_pairs(spark, d).withColumn("t", solved("e1", "e2"))
    return rows.select("e1", "e2", "n_lines", *[F.col("t")[i].alias(c) for i, c in enumerate(("t00", "t01", "t10", "t11"))])


@query("m13_budget_algebra", f"SELECT e1, e2, n_lines, round(-ln(exp(-e1) + exp(-e2) - exp(-e1 - e2)), 9) AS or_eps, round(ln((1 + exp(e1 + e2)) / (exp(e1) + exp(e2))), 9) AS xor_eps FROM ({_PAIRS})")
def m13(spark: SparkSession, d: str) -> DataFrame:
    rows = budget_pairs(spark, d).withColumn("eps", F.explode(F.array("e1", "e2")))
    return rows.groupBy("e1", "e2", "n_lines").agg(F.round(bd.combine_or_column(F.col("eps")), 9).alias("or_eps"), F.round(bd.combine_xor_column(F.col("eps")), 9).alias("xor_eps"))


# --- Boolean operations on the bits of two attributes of documents


def label_bits(spark: SparkSession, d: str, column: str) -> DataFrame:
    return read_table(spark, d, "labels").select(F.col("doc_id").alias("cell"), F.coalesce(F.col(column), F.lit(0)).alias("bit"))


def _noisy_labels(spark: SparkSession, d: str, eps: float = 2.0, release: str = "labels") -> DataFrame:
    """Both attributes as released vectors: v, cell, bit, eps."""
    out = [flip(label_bits(spark, d, c).withColumn("v", F.lit(c)), bd.symmetric(eps), KEY, release, ["v"]).withColumn("eps", F.lit(eps)) for c in ("quality", "toxic")]
    return out[0].unionByName(out[1])


def _labels_sql(eps: float = 2.0, release: str = "labels") -> str:
    f = bd.symmetric(eps)
    both = " UNION ALL ".join(f"SELECT '{c}' AS v, doc_id AS cell, coalesce({c}, 0) AS bit FROM labels" for c in ("quality", "toxic"))
    return f"SELECT v, cell, bit, {eps}::DOUBLE AS eps FROM ({S.flip(both, f.p, f.q, KEY, release, 'v')})"


def _count(df: DataFrame, f: bd.Flip) -> DataFrame:
    return bo.debiased_count(df, f.p, f.q).select(F.round("n_ones", 6).alias("n_ones"), "n_bits")


def _count_sql(bits: str, f: bd.Flip) -> str:
    return f"SELECT round((sum(bit) - {f.q!r} * count(*)) / {f.p - f.q!r}, 6) AS n_ones, count(*) AS n_bits FROM ({bits})"


@query("m10_not", _count_sql(f"SELECT 1 - bit AS bit FROM ({_labels_sql()}) WHERE v = 'quality'", bd.symmetric(2.0)))
def m10(spark: SparkSession, d: str) -> DataFrame:
    return _count(bo.not_(_noisy_labels(spark, d).where("v = 'quality'")), bd.symmetric(2.0))


@query("m11_xor", _count_sql(f"SELECT cell, sum(bit) % 2 AS bit FROM ({_labels_sql()}) GROUP BY cell", bd.symmetric(bd.combine_xor([2.0, 2.0]))))
def m11(spark: SparkSession, d: str) -> DataFrame:
    return _count(bo.xor_agg(_noisy_labels(spark, d)), bd.symmetric(bd.combine_xor([2.0, 2.0])))


@query("m12_and", _count_sql(f"SELECT 1 - bit AS bit FROM ({S.union_randomized(f'SELECT 1 AS g, cell, 1 - bit AS bit, eps FROM ({_labels_sql()})', 'and')})".replace("CAST(g AS VARCHAR), ", ""), bd.symmetric(bd.combine_or([2.0, 2.0]))))
def m12(spark: SparkSession, d: str) -> DataFrame:
    return _count(bo.and_agg(_noisy_labels(spark, d), "and"), bd.symmetric(bd.combine_or([2.0, 2.0])))


@query("m12_or", _count_sql(S.union_randomized(f"SELECT 1 AS g, cell, bit, eps FROM ({_labels_sql()})", "or").replace("CAST(g AS VARCHAR), ", ""), bd.symmetric(bd.combine_or([2.0, 2.0]))))
def m12_or(spark: SparkSession, d: str) -> DataFrame:
    return _count(bo.or_agg(_noisy_labels(spark, d), "or"), bd.symmetric(bd.combine_or([2.0, 2.0])))


_TRUTHS = list(itertools.product((0, 1), repeat=4))


def _binary_sql() -> str:
    parts = []
    side = lambda v: f"(SELECT cell, bit FROM ({_labels_sql()}) WHERE v = '{v}')"
    u = S.draw("merge", "binary", "CAST(x.cell AS VARCHAR)")
    for truth in _TRUTHS:
        name, odd = "".join(map(str, truth)), truth in ((0, 1, 1, 0), (1, 0, 0, 1))
        if len(set(truth)) == 1:
            bit, eps = str(truth[0]), math.inf
        elif truth in ((0, 0, 1, 1), (1, 1, 0, 0)):
            bit, eps = "x.bit" if truth[2] else "1 - x.bit", 2.0
        elif truth in ((0, 1, 0, 1), (1, 0, 1, 0)):
            bit, eps = "y.bit" if truth[1] else "1 - y.bit", 2.0
        elif odd:
            bit, eps = "(x.bit + y.bit) % 2" if truth[1] else "1 - (x.bit + y.bit) % 2", bd.combine_xor([2.0, 2.0])
        else:
            t = bd.transition(2.0, 2.0, truth=truth)
            bit = f"CAST({u} < CASE 2 * x.bit + y.bit " + " ".join(f"WHEN {i} THEN {int(min(1.0, max(0.0, v)) * (1 << 52))}" for i, v in enumerate(t)) + " END AS INTEGER)"
            eps = bd.combine_or([2.0, 2.0])
        f = bd.symmetric(eps)
        parts.append(f"SELECT '{name}' AS truth, round((sum(bit) - {f.q!r} * count(*)) / {f.p - f.q!r}, 6) AS n_ones FROM (SELECT {bit} AS bit FROM {side('quality')} x JOIN {side('toxic')} y ON x.cell = y.cell)")
    return " UNION ALL ".join(parts)


@query("m12g_all_binary_operations", _binary_sql())
def m12g(spark: SparkSession, d: str) -> DataFrame:
    noisy = _noisy_labels(spark, d)
    a, b = noisy.where("v = 'quality'"), noisy.where("v = 'toxic'")
    out = None
    for truth in _TRUTHS:
        cells, eps = bo.binary(a, b, 2.0, 2.0, truth, "binary")
        f = bd.symmetric(eps)
        row = bo.debiased_count(cells, f.p, f.q).select(F.lit("".join(map(str, truth))).alias("truth"), F.round("n_ones", 6).alias("n_ones"))
        out = row if out is None else out.unionByName(row)
    return out


# --- estimation

_SYM = bd.symmetric(2.0)
_LINE_COUNTS = S.arrays(S.levels(S.flip(S.dense(LINES, WIDE), _SYM.p, _SYM.q, KEY, "lines"), WIDE))
_LINE_FIT = S.fit(_LINE_COUNTS, WIDE, _SYM.p, _SYM.q)


def line_levels(spark: SparkSession, d: str, f: bd.Flip = _SYM, release: str = "lines") -> DataFrame:
    return level_counts(flip(sketch(line_items(spark, d), F.col("item"), WIDE, ["g"]), f, KEY, release, ["g"]), WIDE, ["g"])


@query("m14_likelihood_fit", f"SELECT g, round(n_hat, 3) AS n_hat, round({S.stderr(WIDE, 'n_hat', repr(_SYM.p), repr(_SYM.q))}, 3) AS stderr, 'ok' AS status FROM ({_LINE_FIT})")
def m14(spark: SparkSession, d: str) -> DataFrame:
    fitted = cardinality(line_levels(spark, d), WIDE, _SYM.p, _SYM.q, "bisect")
    return rounded(fitted.select("g", "n_hat", "stderr", "status"), n_hat=3, stderr=3)


for _solver in ("safe", "newton"):
    query(f"m14b_{_solver}_solver", f"SELECT g, round(n_hat, 2) AS n_hat FROM ({_LINE_FIT})")(
        lambda spark, d, s=_solver: cardinality(line_levels(spark, d), WIDE, _SYM.p, _SYM.q, s).select("g", F.round("n_hat", 2).alias("n_hat"))
    )

_NS = [1000.0, 30000.0, 45832.0, 60000.0, 1000000.0]


def _ll_sql() -> str:
    lg, p, q = f"{S.log_miss(WIDE)}[j]", repr(_SYM.p), repr(_SYM.q)
    g = f"exp(n * {lg})"
    ll = f"list_sum(list_transform(range(1, 25), lambda j: (4096 - k[j]) * ln(1 - {p} + ({p} - {q}) * {g}) + k[j] * ln({p} - ({p} - {q}) * {g})))"
    h = f"list_sum(list_transform(range(1, 25), lambda j: {lg} * {lg} * ((4096 - k[j]) * (1 - {p}) * ({p} - {q}) * {g} / pow(1 - {p} + ({p} - {q}) * {g}, 2) - k[j] * {p} * ({p} - {q}) * {g} / pow({p} - ({p} - {q}) * {g}, 2))))"
    ns = ", ".join(f"({n!r}::DOUBLE)" for n in _NS)
    return f"SELECT n, round({ll}, 4) AS loglik, round(n * {S.score(WIDE, 'k', 'n', p, q)}, 4) AS n_score, round(n * n * {h}, 3) AS n2_hessian FROM ({_LINE_COUNTS}) CROSS JOIN (VALUES {ns}) x(n)"


@query("m14a_loglik_and_derivatives", _ll_sql())
def m14a(spark: SparkSession, d: str) -> DataFrame:
    at = spark.createDataFrame([(n,) for n in _NS], "n double")
    rows = line_levels(spark, d).crossJoin(F.broadcast(at))
    o, n, p, q = F.col("ones"), F.col("n"), _SYM.p, _SYM.q
    return rows.select("n", F.round(lk.loglik(o, WIDE, n, p, q), 4).alias("loglik"), F.round(n * lk.score(o, WIDE, n, p, q), 4).alias("n_score"), F.round(n * n * lk.hessian(o, WIDE, n, p, q), 3).alias("n2_hessian"))


def _flip_of(kind: str, e: float) -> bd.Flip:
    return bd.symmetric(e) if kind == "symmetric" else bd.half_flip(e)


_SE_ROWS = [(kind, e, _flip_of(kind, e).p, _flip_of(kind, e).q) for kind in ("symmetric", "half") for e in (0.25, 0.5, 1.0, 2.0, 4.0)]
_SE_VALUES = "(VALUES " + ", ".join(f"('{k}', {e!r}::DOUBLE, {p!r}::DOUBLE, {q!r}::DOUBLE)" for k, e, p, q in _SE_ROWS) + ") x(kind, eps, p, q)"


@query("m15_stderr_formula", f"SELECT g, kind, eps, n, round({S.stderr(WIDE, 'n', 'p', 'q')} / n, 6) AS rel_stderr FROM ({_SIZES}), {_SE_VALUES}")
def m15(spark: SparkSession, d: str) -> DataFrame:
    """The relative error to expect of each return flag's count of parts."""
    rows = group_sizes(spark, d).crossJoin(F.broadcast(spark.createDataFrame(_SE_ROWS, "kind string, eps double, p double, q double")))
    return rows.select("g", "kind", "eps", "n", F.round(lk.stderr(WIDE, F.col("n"), F.col("p"), F.col("q")) / F.col("n"), 6).alias("rel_stderr"))


@query("m15a_observed_and_sandwich")
def m15a(spark: SparkSession, d: str) -> DataFrame:
    fitted = cardinality(line_levels(spark, d), WIDE, _SYM.p, _SYM.q, "bisect")
    n, p, q = F.col("n_hat"), _SYM.p, _SYM.q
    return fitted.select("g", F.round("stderr", 2).alias("stderr"), F.round(lk.observed_stderr(F.col("ones"), WIDE, n, p, q), 2).alias("observed"), F.round(lk.sandwich_stderr(WIDE, n, p, q), 2).alias("sandwich"))


_KS = (1, 2, 4, 8, 16, 32)
_KE = (1.0, 2.0, 3.0, 4.0)
_MERGE_VALUES = "(VALUES " + ", ".join(f"({k}, {e!r}::DOUBLE)" for k in _KS for e in _KE) + ") x(k, eps)"


@query("m15b_stderr_after_merge", f"SELECT k, eps, round({S.stderr(WIDE, '1e6', '(1 - q)', 'q')} / 1e6, 5) AS rel_stderr FROM (SELECT *, 1 / (1 / (1 - pow(1 - exp(-eps), k)) + 1) AS q FROM {_MERGE_VALUES})")
def m15b(spark: SparkSession, d: str) -> DataFrame:
    rows = [(k, e, round(stderr_after_merge(WIDE, [e] * k, 1e6) / 1e6, 5)) for k in _KS for e in _KE]
    return spark.createDataFrame(rows, "k int, eps double, rel_stderr double")


_C_ROWS = [(kind, e, _flip_of(kind, e)) for kind in ("symmetric", "half") for e in (0.25, 0.5, 1.0, 2.0, 4.0, math.inf)]
_C_VALUES = ", ".join(f"('{k}', '{e}'::DOUBLE, {f.p!r}::DOUBLE, {f.q!r}::DOUBLE)" for k, e, f in _C_ROWS)


@query("m15c_asymptotic_constants", f"SELECT kind, eps, round({S.stderr(WIDE, '16777216.0', 'p', 'q')} / 16777216.0 * 64, 4) AS c FROM (VALUES {_C_VALUES}) x(kind, eps, p, q)")
def m15c(spark: SparkSession, d: str) -> DataFrame:
    rows = [(kind, e, round(asymptotic_constant(WIDE, _flip_of(kind, e).p, _flip_of(kind, e).q), 4)) for kind in ("symmetric", "half") for e in (0.25, 0.5, 1.0, 2.0, 4.0, math.inf)]
    return spark.createDataFrame(rows, "kind string, eps double, c double")


@query("m15d_plans")
def m15d(spark: SparkSession, d: str) -> DataFrame:
    rows = [("buckets", t, e, float(plan_buckets(t, e, 1e6))) for t in (0.02, 0.05) for e in (1.0, 2.0)]
    rows += [("epsilon", t, float(k), round(plan_epsilon(t, k, 1e6), 5)) for t in (0.02, 0.05) for k in (1, 4, 16)]
    return spark.createDataFrame(rows, "what string, target double, given double, answer double")


@query("m16_deterministic_merges")
def m16(spark: SparkSession, d: str) -> DataFrame:
    found = theory.deterministic_merge_feasibility(spark).where("works")
    return found.groupBy("op", "target").agg(F.count("*").alias("n_flips"), F.min("p").alias("least_p"), F.max("p").alias("most_p"))


@query("m17_largest_budget")
def m17(spark: SparkSession, d: str) -> DataFrame:
    parts = [theory.max_feasible_eps(spark, e).withColumn("epsilons", F.lit(str(e))) for e in ([1.0, 1.0], [0.5, 2.0], [0.7, 1.3, 2.2])]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).select("epsilons", F.round("max_eps", 6).alias("max_eps"), F.round("law_eps", 6).alias("law_eps"))


# --- simulated sketches

_TINY = Layout(64, 16, family="md5")


def _sim(spark: SparkSession, law: str) -> DataFrame:
    trials = spark.range(20).select(F.col("id").cast("int").alias("trial"), F.lit(5000.0).alias("n"))
    if law == "independent":
        cells = simulate.independent_cells(trials, _TINY, law, ["trial"])
    elif law == "poissonized":
        cells = simulate.poissonized(trials, _TINY, law, ["trial"])
    elif law == "multinomial":
        cells = simulate.multinomial(trials, 5000, _TINY, law, ["trial"])
    else:
        cells = simulate.exact(trials, 5000, _TINY, ["trial"])
    fitted = cardinality(level_counts(cells, _TINY, ["trial"]), _TINY, 1.0, 0.0, "bisect")
    return rounded(fitted.select("trial", "n_hat"), n_hat=3)


def _sim_sql(law: str) -> str:
    rho = "[" + ", ".join(repr(r) + "::DOUBLE" for r in _TINY.rho()) + "]"
    if law == "independent":
        full = f"(1 - exp(5000.0 * {S.log_miss(_TINY)}[cell % 16 + 1]))"
    else:
        full = f"(1 - exp(-5000.0 * {rho}[cell % 16 + 1]))"
    u = S.draw("sim", law, "CAST(trial AS VARCHAR)", "CAST(cell AS VARCHAR)")
    bits = f"SELECT CAST(trial AS INTEGER) AS trial, cell, CAST({u} < {S.chance(full)} AS INTEGER) AS bit FROM (SELECT range AS trial FROM range(20)), (SELECT CAST(range AS INTEGER) AS cell FROM range({_TINY.cells}))"
    return f"SELECT trial, round(n_hat, 3) AS n_hat FROM ({S.fit(S.arrays(S.levels(bits, _TINY, 'trial'), 'trial'), _TINY, 1.0, 0.0, 'trial')})"


_SIM_ITEMS = "SELECT CAST(t.range AS INTEGER) AS trial, concat_ws('|', t.range, i.range) AS item FROM range(20) t, range(5000) i"
query("m18_independent_cells", _sim_sql("independent"))(lambda spark, d: _sim(spark, "independent"))
query("m18_poissonized", _sim_sql("poissonized"))(lambda spark, d: _sim(spark, "poissonized"))
query("m18_exact_items", f"SELECT trial, round(n_hat, 3) AS n_hat FROM ({S.fit(S.arrays(S.levels(S.dense(_SIM_ITEMS, _TINY, 'trial'), _TINY, 'trial'), 'trial'), _TINY, 1.0, 0.0, 'trial')})")(lambda spark, d: _sim(spark, "exact"))
query("m18_multinomial")(lambda spark, d: _sim(spark, "multinomial"))


#: Few buckets for many items, so that the sketches have room to agree.
COUPLED = Layout(4, 20)


@query("m18c_coupling_agreement")
def m18c(spark: SparkSession, d: str) -> DataFrame:
    parts = [theory.coupling_agreement(spark, n, COUPLED, 20, "coupling") for n in (1000, 10000)]
    return parts[0].unionByName(parts[1])


@query("m18p_poisson_fit")
def m18p(spark: SparkSession, d: str) -> DataFrame:
    levels = line_levels(spark, d)
    a = cardinality(levels, WIDE, _SYM.p, _SYM.q, "bisect").select("g", F.round("n_hat", 1).alias("likelihood"))
    b = cardinality(levels, WIDE, _SYM.p, _SYM.q, "bisect", "poisson").select("g", F.round("n_hat", 1).alias("poisson"))
    return a.join(b, "g")


# --- other bitmaps under the same mechanism

EXPONENTIAL = Exponential(512, 16, decay=8.0, family="md5")
_LINEAR, _BLOOM = LinearCounting(8192, family="md5"), Bloom(16384, k=2, family="md5")


def _bitmap(spark: SparkSession, d: str, layout: Layout, eps: float, release: str) -> DataFrame:
    f = bd.symmetric(eps / layout.hashes)
    levels = level_counts(flip(sketch(order_items(spark, d), F.col("item"), layout, ["g"]), f, KEY, release, ["g"]), layout, ["g"])
    return rounded(cardinality(levels, layout, f.p, f.q, "bisect").select("g", "n_hat", "status"), n_hat=3)


def bitmap_sql(layout: Layout, eps: float, release: str) -> str:
    f = bd.symmetric(eps / layout.hashes)
    return f"SELECT g, round(n_hat, 3) AS n_hat, 'ok' AS status FROM ({S.fit(S.arrays(S.levels(S.flip(S.dense(ORDERS, layout), f.p, f.q, KEY, release), layout)), layout, f.p, f.q, high=math.log(layout.most()))})"


query("m19_linear_counting", bitmap_sql(_LINEAR, 2.0, "linear"))(lambda spark, d: _bitmap(spark, d, _LINEAR, 2.0, "linear"))
query("m19_bloom_filter", bitmap_sql(_BLOOM, 4.0, "bloom"))(lambda spark, d: _bitmap(spark, d, _BLOOM, 4.0, "bloom"))
query("m19_exponential_bitmap")(lambda spark, d: _bitmap(spark, d, EXPONENTIAL, 2.0, "exponential"))


@query("t13_bounded_contribution")
def bounded(spark: SparkSession, d: str) -> DataFrame:
    """An item counts in two groups at most, so its whole budget is at most twice a group's."""
    kept = bound_groups(order_items(spark, d), "item", "g", 2)
    return kept.groupBy("item").agg(F.count_distinct("g").alias("n")).groupBy("n").agg(F.count("*").alias("n_items"))
