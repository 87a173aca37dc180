"""Queries of the relational, streaming and SQL operators around the sketches."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import budget as bd
from ..functions import sqlapi
from ..functions.hashing import canonical, cell_of
from ..layout import Layout
from ..operators import merge as mg
from ..operators.build import cell_frame, level_counts, packed, set_cells, sketch
from ..operators.estimate import cardinality
from ..operators.privatize import flip
from ..plans import arrow
from ..sources import io
from ..sources.io import read_table
from ..streaming import windows as st
from . import sql as S
from .comparisons import _nations, event_items
from .methods import KEY, LINES, ORDERS, SMALL, WIDE, csv, line_items, order_items, party_items, party_sql
from .registry import query, shared_path


# --- sources and sinks

for _kind in ("parquet", "orc", "json", "csv"):

    def _source(spark: SparkSession, d: str, kind: str = _kind) -> DataFrame:
        path = shared_path(spark, kind)
        rows = read_table(spark, d, "orders").select("o_custkey", "o_orderpriority")
        rows.write.format(kind).option("header", True).save(path)
        back = io.read_any(spark, path, kind, "o_custkey BIGINT, o_orderpriority STRING")
        return set_cells(back.select(F.col("o_orderpriority").alias("g"), F.col("o_custkey").cast("string").alias("item")), F.col("item"), SMALL, ["g"]).groupBy("g").agg(F.count("*").alias("n_cells"))

    query(f"op_source_{_kind}", f"SELECT g, count(*) AS n_cells FROM ({S.set_cells(ORDERS, SMALL)}) GROUP BY g")(_source)


@query("op_source_text", "SELECT count(DISTINCT trim(lower(text))) AS n FROM (SELECT unnest(string_split(text, chr(10))) AS text FROM benchmark) WHERE trim(lower(text)) <> ''")
def source_text(spark: SparkSession, d: str) -> DataFrame:
    path = shared_path(spark, "text")
    read_table(spark, d, "benchmark").select(F.col("text").alias("value")).write.text(path)
    lines = io.read_any(spark, path, "text").select(F.trim(F.lower("value")).alias("line"))
    return lines.where("line <> ''").agg(F.count_distinct("line").alias("n"))


@query("op_sink_catalogue", f"SELECT g AS grp, {SMALL.cells} AS n_rows, 1 AS n_sources FROM (SELECT DISTINCT g FROM ({ORDERS}))")
def catalogue(spark: SparkSession, d: str) -> DataFrame:
    """Two writes of one release leave one."""
    f, path = bd.symmetric(2.0), shared_path(spark, "catalogue")
    noisy = flip(sketch(order_items(spark, d), F.col("item"), SMALL, ["g"]), f, KEY, "catalogue", ["g"])
    rows = io.catalogued(noisy, SMALL, 2.0, f.kind, f.p, f.q, "g", "r1")
    for _ in range(2):
        io.write_sketches(rows, path, "r1", shared_path(spark, "ledger"))
    back = io.read_sketches(spark, path)
    mg.check_mergeable(io.heads(back)).collect()
    return back.groupBy("grp").agg(F.count("*").cast("int").alias("n_rows"), F.max("n_sources").alias("n_sources"))


# --- relational operators

_CELLS = S.set_cells(ORDERS, SMALL)


@query("op_filter", "SELECT count(DISTINCT o_custkey) AS n FROM orders WHERE o_orderstatus IN ('F', 'O') AND o_totalprice BETWEEN 1000 AND 100000 AND o_orderpriority LIKE '%-%' AND o_orderdate IS NOT NULL")
def op_filter(spark: SparkSession, d: str) -> DataFrame:
    o = read_table(spark, d, "orders")
    kept = o.where(F.col("o_orderstatus").isin("F", "O") & F.col("o_totalprice").between(1000, 100000) & F.col("o_orderpriority").like("%-%") & F.col("o_orderdate").isNotNull())
    return kept.agg(F.count_distinct("o_custkey").alias("n"))


@query("op_projection", "SELECT o_orderkey AS k, o_orderpriority || '/' || o_orderstatus AS kind, round(o_totalprice / 100, 6) AS hundreds FROM orders")
def op_projection(spark: SparkSession, d: str) -> DataFrame:
    """Columns picked, renamed and computed: the scan reads these four only."""
    return read_table(spark, d, "orders").select(F.col("o_orderkey").alias("k"), F.concat_ws("/", "o_orderpriority", "o_orderstatus").alias("kind"), F.round(F.col("o_totalprice") / 100, 6).alias("hundreds"))


@query("op_join_inner", "SELECT r_name AS region, count(DISTINCT o_custkey) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def op_join_inner(spark: SparkSession, d: str) -> DataFrame:
    return _nations(spark, d).select("region", F.split("item", r"\|")[0].alias("c")).groupBy("region").agg(F.count_distinct("c").alias("n"))


@query("op_join_left_densify", f"SELECT count(*) AS n_cells, sum(bit)::BIGINT AS n_ones FROM ({S.dense(ORDERS, SMALL)})")
def op_join_left(spark: SparkSession, d: str) -> DataFrame:
    return sketch(order_items(spark, d), F.col("item"), SMALL, ["g"]).agg(F.count("*").alias("n_cells"), F.sum("bit").alias("n_ones"))


@query("op_join_semi", "SELECT count(*) AS n FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
def op_join_semi(spark: SparkSession, d: str) -> DataFrame:
    c, o = read_table(spark, d, "customer"), read_table(spark, d, "orders").select("o_custkey")
    return c.join(o, c.c_custkey == o.o_custkey, "left_semi").agg(F.count("*").alias("n"))


@query("op_join_anti", "SELECT count(*) AS n FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 45)")
def op_join_anti(spark: SparkSession, d: str) -> DataFrame:
    p, x = read_table(spark, d, "part"), read_table(spark, d, "lineitem").where("l_quantity > 45").select("l_partkey")
    return p.join(x, p.p_partkey == x.l_partkey, "left_anti").agg(F.count("*").alias("n"))


_PERIODS = [("p1", "1970-01-01 00:00:00", "2024-01-08 00:00:00", 1.0), ("p2", "2024-01-08 00:00:00", "2024-01-20 00:00:00", 0.5), ("p3", "2024-01-20 00:00:00", "2100-01-01 00:00:00", 0.25)]
_PERIOD_SQL = "(VALUES " + ", ".join(f"('{p}', TIMESTAMP '{a}', TIMESTAMP '{b}', {e}::DOUBLE)" for p, a, b, e in _PERIODS) + ") x(period, a, b, eps)"


@query("op_join_interval", f"SELECT period, eps, count(DISTINCT user_id) AS n_users FROM events JOIN {_PERIOD_SQL} ON ts >= a AND ts < b GROUP BY 1, 2")
def op_join_interval(spark: SparkSession, d: str) -> DataFrame:
    """Events to the budget periods that they fall into: a fixed schedule, broadcast."""
    periods = spark.createDataFrame(_PERIODS, "period string, a string, b string, eps double").select("period", F.col("a").cast("timestamp").alias("a"), F.col("b").cast("timestamp").alias("b"), "eps")
    e = event_items(spark, d)
    return e.join(F.broadcast(periods), (e.ts >= F.col("a")) & (e.ts < F.col("b"))).groupBy("period", "eps").agg(F.count_distinct("item").alias("n_users"))


@query("op_join_asof", "SELECT g AS scope, count(*) AS n_asks, count(rid) AS n_answered, max(rid) AS last_id FROM (SELECT a.event_type AS g, (SELECT max_by(printf('%010d', b.event_id), (b.ts, b.event_id)) FROM events b WHERE b.user_id = a.user_id AND b.event_type = 'purchase' AND b.ts <= a.ts) AS rid FROM events a) GROUP BY g")
def op_join_asof(spark: SparkSession, d: str) -> DataFrame:
    """For each event its user's last purchase so far, as a ledger's entry as of a time."""
    e = event_items(spark, d)
    ledger = e.where("g = 'purchase'").select(F.col("item").alias("scope"), F.col("ts").alias("released_at"), F.format_string("%010d", "event_id").alias("release_id"))
    asks = e.select(F.col("item").alias("scope"), F.col("ts").alias("at"), "g")
    return io.latest(ledger, asks, keep=["g"]).groupBy(F.col("g").alias("scope")).agg(F.count("*").alias("n_asks"), F.count("release_id").alias("n_answered"), F.max("release_id").alias("last_id"))


@query("op_join_cross", "SELECT count(*) AS n_settings FROM range(4), range(5), range(3)")
def op_join_cross(spark: SparkSession, d: str) -> DataFrame:
    a, b, c = (F.broadcast(spark.range(n).toDF(x)) for n, x in ((4, "a"), (5, "b"), (3, "c")))
    return spark.range(1).select().crossJoin(a).crossJoin(b).crossJoin(c).agg(F.count("*").alias("n_settings"))


@query("op_aggregate_rollup", f"SELECT region, nation, n_cells FROM (SELECT region, nation, count(DISTINCT cell) AS n_cells FROM (SELECT region, nation, {S.cell('item', SMALL)} AS cell FROM (SELECT n_name AS nation, r_name AS region, CAST(o_custkey AS VARCHAR) || '|' || o_orderpriority AS item FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)) GROUP BY ROLLUP (region, nation))")
def op_rollup(spark: SparkSession, d: str) -> DataFrame:
    """Roll-ups unite sketches; counts of cells are never added."""
    cells = set_cells(_nations(spark, d), F.col("item"), SMALL, ["region", "nation"])
    return cells.rollup("region", "nation").agg(F.count_distinct("cell").alias("n_cells"))


@query("op_aggregate_cube", "SELECT o_orderstatus AS s, o_orderpriority AS p, count(DISTINCT o_custkey) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def op_cube(spark: SparkSession, d: str) -> DataFrame:
    return read_table(spark, d, "orders").cube(F.col("o_orderstatus").alias("s"), F.col("o_orderpriority").alias("p")).agg(F.count_distinct("o_custkey").alias("n"))


@query("op_aggregate_grouping_sets", "SELECT o_orderstatus AS s, o_orderpriority AS p, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))")
def op_grouping_sets(spark: SparkSession, d: str) -> DataFrame:
    o = read_table(spark, d, "orders")
    return o.groupingSets([["o_orderstatus"], ["o_orderpriority"]], "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")).withColumnsRenamed({"o_orderstatus": "s", "o_orderpriority": "p"})


@query("op_aggregate_bits", f"SELECT g, bit_or(cell)::BIGINT AS ors, bit_and(cell)::BIGINT AS ands, bit_xor(cell)::BIGINT AS xors FROM ({_CELLS}) GROUP BY g")
def op_bits(spark: SparkSession, d: str) -> DataFrame:
    c = set_cells(order_items(spark, d), F.col("item"), SMALL, ["g"]).withColumn("cell", F.col("cell").cast("long"))
    return c.groupBy("g").agg(F.bit_or("cell").alias("ors"), F.bit_and("cell").alias("ands"), F.bit_xor("cell").alias("xors"))


@query("op_aggregate_statistics", "SELECT round(avg(o_totalprice), 4) AS mean, round(stddev_samp(o_totalprice), 4) AS sd, round(var_pop(o_totalprice), 2) AS var, round(regr_slope(o_totalprice, o_orderkey), 9) AS slope, round(quantile_cont(o_totalprice, 0.5), 4) AS median FROM orders")
def op_statistics(spark: SparkSession, d: str) -> DataFrame:
    o = read_table(spark, d, "orders")
    return o.agg(F.round(F.avg("o_totalprice"), 4).alias("mean"), F.round(F.stddev_samp("o_totalprice"), 4).alias("sd"), F.round(F.var_pop("o_totalprice"), 2).alias("var"), F.round(F.regr_slope("o_totalprice", "o_orderkey"), 9).alias("slope"), F.round(F.percentile("o_totalprice", 0.5), 4).alias("median"))


@query("op_pivot", "SELECT event_type AS g, sum(CASE WHEN user_id % 2 = 0 THEN 1 ELSE 0 END)::BIGINT AS even_users, sum(CASE WHEN user_id % 2 = 1 THEN 1 ELSE 0 END)::BIGINT AS odd_users FROM events GROUP BY 1")
def op_pivot(spark: SparkSession, d: str) -> DataFrame:
    e = event_items(spark, d).withColumn("kind", F.when(F.col("item").cast("long") % 2 == 0, "even_users").otherwise("odd_users"))
    return e.groupBy("g").pivot("kind", ["even_users", "odd_users"]).agg(F.count(F.lit(1))).fillna(0)


@query("op_unpivot", "SELECT doc_id, 'quality' AS what, quality AS bit FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def op_unpivot(spark: SparkSession, d: str) -> DataFrame:
    return read_table(spark, d, "labels").select("doc_id", "quality", "toxic").unpivot("doc_id", ["quality", "toxic"], "what", "bit")


@query("op_window_running_union", f"SELECT day, (sum(count(*)) OVER (ORDER BY day))::BIGINT AS n_cells FROM (SELECT cell, min(day) AS day FROM (SELECT DISTINCT strftime(ts, '%Y-%m-%d') AS day, {S.cell('user_id', SMALL)} AS cell FROM events) GROUP BY cell) GROUP BY day")
def op_running(spark: SparkSession, d: str) -> DataFrame:
    """Cells of the union of all days so far: a cell counts from its first day on, so only days are windowed over."""
    days = set_cells(event_items(spark, d).withColumn("day", F.date_format("ts", "yyyy-MM-dd")), F.col("item"), SMALL, ["day"])
    first = days.groupBy("cell").agg(F.min("day").alias("day")).groupBy("day").agg(F.count("*").alias("n"))
    return first.select("day", F.sum("n").over(Window.orderBy("day")).alias("n_cells"))


@query("op_window_ranking", "SELECT o_orderkey, rn, rk, dr, nt, previous FROM (SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt, lag(o_orderkey) OVER w AS previous FROM orders WINDOW w AS (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey)) WHERE rn <= 5")
def op_ranking(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey")
    o = read_table(spark, d, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("nt"), F.lag("o_orderkey").over(w).alias("previous"))
    return o.where("rn <= 5")


@query("op_top_k", "SELECT o_custkey, n FROM (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1) ORDER BY n DESC, o_custkey LIMIT 10")
def op_top_k(spark: SparkSession, d: str) -> DataFrame:
    return read_table(spark, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "o_custkey").limit(10)


@query("op_set_operations", "SELECT (SELECT count(*) FROM (SELECT c_custkey AS k FROM customer UNION SELECT o_custkey FROM orders)) AS n_union, (SELECT count(*) FROM (SELECT c_custkey AS k FROM customer INTERSECT SELECT o_custkey FROM orders)) AS n_both, (SELECT count(*) FROM (SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders)) AS n_only")
def op_sets(spark: SparkSession, d: str) -> DataFrame:
    a, b = read_table(spark, d, "customer").select(F.col("c_custkey").alias("k")), read_table(spark, d, "orders").select(F.col("o_custkey").alias("k"))
    n = lambda df, name: df.agg(F.count("*").alias(name))
    return n(a.union(b).distinct(), "n_union").crossJoin(n(a.intersect(b), "n_both")).crossJoin(n(a.subtract(b), "n_only"))


@query("op_union_by_name", "SELECT 'a' AS src, count(*) AS n FROM benchmark UNION ALL SELECT 'b', count(*) FROM pages")
def op_union_by_name(spark: SparkSession, d: str) -> DataFrame:
    a = read_table(spark, d, "benchmark").select(F.lit("a").alias("src"), "text")
    b = read_table(spark, d, "pages").select("url", F.lit("b").alias("src"))
    return a.unionByName(b, allowMissingColumns=True).groupBy("src").agg(F.count("*").alias("n"))


@query("op_string_functions", "SELECT regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1) AS host, count(DISTINCT lower(trim(url))) AS n FROM pages GROUP BY 1")
def op_strings(spark: SparkSession, d: str) -> DataFrame:
    return read_table(spark, d, "pages").groupBy(F.regexp_extract("url", "^[a-z]+://([^/?#:]+)", 1).alias("host")).agg(F.count_distinct(F.lower(F.trim("url"))).alias("n"))


@query("op_date_functions", "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, count(DISTINCT o_custkey) AS n, max(datediff('day', DATE '1990-01-01', CAST(o_orderdate AS DATE)))::BIGINT AS last_day FROM orders GROUP BY 1")
def op_dates(spark: SparkSession, d: str) -> DataFrame:
    o = read_table(spark, d, "orders")
    return o.groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("month")).agg(F.count_distinct("o_custkey").alias("n"), F.max(F.date_diff(F.col("o_orderdate").cast("date"), F.lit("1990-01-01").cast("date"))).cast("long").alias("last_day"))


@query("op_math_and_bit_functions", "SELECT o_orderkey AS k, bit_count(o_orderkey)::INTEGER AS ones, (o_orderkey >> 3)::BIGINT AS eighth, ((o_orderkey >> 1) & 1)::INTEGER AS bit1, round(exp(-o_orderkey / 1000.0), 9) AS e, round(ln(1 + o_orderkey), 9) AS l FROM orders")
def op_math(spark: SparkSession, d: str) -> DataFrame:
    k = F.col("o_orderkey")
    return read_table(spark, d, "orders").select(k.alias("k"), F.bit_count(k).alias("ones"), F.shiftright(k, 3).alias("eighth"), F.getbit(k, F.lit(1)).cast("int").alias("bit1"), F.round(F.exp(-k / 1000.0), 9).alias("e"), F.round(F.log1p(k), 9).alias("l"))


@query("op_array_functions", "SELECT vec_id, len(embedding) AS n, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS squares FROM embeddings")
def op_arrays(spark: SparkSession, d: str) -> DataFrame:
    squares = F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x)
    return read_table(spark, d, "embeddings").select("vec_id", F.size("embedding").cast("long").alias("n"), F.round(squares, 6).alias("squares"))


@query("op_array_items", "SELECT count(DISTINCT embedding) AS n, count(DISTINCT embedding) AS n_exact FROM embeddings")
def op_array_items(spark: SparkSession, d: str) -> DataFrame:
    """Arrays as items: their JSON form is hashed."""
    e = read_table(spark, d, "embeddings").select("embedding", canonical(F.col("embedding"), "array<float>").alias("item"))
    return e.agg(F.count_distinct("item").alias("n"), F.count_distinct("embedding").alias("n_exact"))


@query("op_map_functions", "SELECT g, eps FROM (SELECT DISTINCT event_type AS g, 1.0::DOUBLE + length(event_type) AS eps FROM events)")
def op_maps(spark: SparkSession, d: str) -> DataFrame:
    """Budgets by group as one map."""
    types = event_items(spark, d).select("g").distinct()
    budgets = types.agg(F.map_from_entries(F.collect_list(F.struct("g", (1.0 + F.length("g")).alias("eps")))).alias("m"))
    return budgets.select(F.explode("m").alias("g", "eps"))


@query("op_json_functions", "SELECT count(DISTINCT props) AS n, count(DISTINCT json_extract_string(props, '$.k')) AS n_k FROM events")
def op_json(spark: SparkSession, d: str) -> DataFrame:
    e = read_table(spark, d, "events")
    return e.agg(F.count_distinct("props").alias("n"), F.count_distinct(F.get_json_object("props", "$.k")).alias("n_k"))


@query("op_null_functions", "SELECT sum(CASE WHEN x IS NULL THEN 1 ELSE 0 END)::BIGINT AS n_null, sum(coalesce(x, 0))::BIGINT AS s, count(DISTINCT x) AS n FROM (SELECT nullif(user_id % 10, 3) AS x FROM events)")
def op_nulls(spark: SparkSession, d: str) -> DataFrame:
    e = read_table(spark, d, "events").select(F.nullif(F.col("user_id") % 10, F.lit(3).cast("long")).alias("x"))
    return e.agg(F.sum(F.col("x").isNull().cast("long")).alias("n_null"), F.sum(F.coalesce("x", F.lit(0))).alias("s"), F.count_distinct("x").alias("n"))


@query("op_sampling_by_hash", f"SELECT count(*) AS n FROM (SELECT DISTINCT item FROM ({LINES})) WHERE {S.h60('item')} % 100 < 20")
def op_sampling(spark: SparkSession, d: str) -> DataFrame:
    """A repeatable sample of items: by their hash, so that repetitions go together."""
    from ..functions.hashing import md5_60

    return line_items(spark, d).select("item").distinct().where(F.pmod(md5_60(F.col("item")), F.lit(100)) < 20).agg(F.count("*").alias("n"))


@query("op_sample_by", f"SELECT g, count(*) AS n FROM (SELECT event_type AS g, {S.h60("concat_ws('|', event_type, event_id)")} % 1000 AS u FROM events) WHERE u < CASE g WHEN 'click' THEN 500 WHEN 'view' THEN 100 ELSE 0 END GROUP BY g")
def op_sample_by(spark: SparkSession, d: str) -> DataFrame:
    """A share of each group, by a hash of the row's key: sampleBy(), but the same rows in every run and partitioning."""
    from ..functions.hashing import md5_60

    share = F.coalesce(F.element_at(F.create_map(F.lit("click"), F.lit(500), F.lit("view"), F.lit(100)), F.col("g")), F.lit(0))
    e = event_items(spark, d).withColumn("u", F.pmod(md5_60(F.concat_ws("|", "g", F.col("event_id").cast("string"))), F.lit(1000)))
    return e.where(F.col("u") < share).groupBy("g").agg(F.count("*").alias("n"))


@query("op_sample_by_native", "SELECT DISTINCT event_type AS g, true AS plausible FROM events WHERE event_type IN ('click', 'view')")
def op_sample_by_native(spark: SparkSession, d: str) -> DataFrame:
    """Spark's own sampleBy: sizes within six standard deviations of their shares."""
    e, shares = event_items(spark, d), {"click": 0.5, "view": 0.1}
    n, p = F.col("n"), F.element_at(F.create_map(*[F.lit(x) for kv in shares.items() for x in kv]), F.col("g"))
    taken = e.sampleBy("g", shares, seed=7).groupBy("g").agg(F.count("*").alias("taken"))
    both = e.where(F.col("g").isin(*shares)).groupBy("g").agg(F.count("*").alias("n")).join(taken, "g", "left")
    return both.select("g", (F.abs(F.coalesce("taken", F.lit(0)) - n * p) <= 6 * F.sqrt(n * p * (1 - p)) + 1).alias("plausible"))


# --- streams: a table's rows as a file stream


def _files(spark: SparkSession, d: str) -> str:
    """events, dealt over three files by time. A stream reads them in the order in which they were done, which is any."""
    path = shared_path(spark, "stream")
    read_table(spark, d, "events").repartitionByRange(3, "ts").sortWithinPartitions("ts").write.parquet(path)
    return path


def _stream(spark: SparkSession, d: str) -> DataFrame:
    return st.event_stream(spark, _files(spark, d), read_table(spark, d, "events").schema)


def _run(spark: SparkSession, df: DataFrame, mode: str = "complete") -> DataFrame:
    name = f"q{uuid.uuid4().hex}"
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", shared_path(spark, "offsets")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def _windows_sql(width_days: int, slide_days: int) -> str:
    cell = S.cell("user_id", WIDE)
    w = f"SELECT to_timestamp((epoch(ts)::BIGINT // {slide_days * 86400} - i) * {slide_days * 86400}) AS a, {cell} AS cell FROM events, range({width_days // slide_days}) r(i)"
    return f"SELECT strftime(a AT TIME ZONE 'UTC', '%Y-%m-%d') AS day, count(DISTINCT cell) AS n_cells FROM ({w}) GROUP BY 1"


def _windows(spark: SparkSession, d: str, width: str, slide: str | None) -> DataFrame:
    s = st.window_bitmaps(_stream(spark, d), F.col("user_id").cast("string"), WIDE, width, slide)
    done = _run(spark, s)
    return done.groupBy(F.date_format(F.col("window.start"), "yyyy-MM-dd").alias("day")).agg(F.sum(F.bitmap_count("bits")).alias("n_cells"))


query("op_stream_tumbling_windows", _windows_sql(7, 7))(lambda spark, d: _windows(spark, d, "7 days", None))
query("op_stream_sliding_windows", _windows_sql(4, 2))(lambda spark, d: _windows(spark, d, "4 days", "2 days"))


def _closed(spark: SparkSession, d: str, build) -> DataFrame:
    """All rows that a stream over events gives in append mode: run over the files, then over an end marker that closes
    its windows. build(stream, lateness) makes the query."""
    e, files, path, checkpoint = read_table(spark, d, "events"), _files(spark, d), shared_path(spark, "windows"), shared_path(spark, "offsets")
    late = st.covering_days(e)
    s = build(st.event_stream(spark, files, e.schema), f"{late} days")
    run = lambda: s.writeStream.outputMode("append").format("parquet").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    run()
    st.end_marker(e, late, 7, "user_id").write.mode("append").parquet(files)
    run()
    return spark.read.schema(s.schema).parquet(path)


@query("op_stream_session_windows", "SELECT user_id, count(*) AS n_sessions, count(*) + sum(n_more)::BIGINT AS n_rows FROM (SELECT user_id, fresh, sum(1 - fresh) OVER (PARTITION BY user_id, s) AS n_more FROM (SELECT user_id, fresh, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT user_id, ts, event_id, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 1 DAY THEN 0 ELSE 1 END AS fresh FROM events))) WHERE fresh = 1 GROUP BY 1")
def op_sessions(spark: SparkSession, d: str) -> DataFrame:
    """Sessions on a stream, given out when the watermark has closed them."""
    sessions = _closed(spark, d, lambda s, late: st.session_counts(s, "1 day", "user_id", late))
    return sessions.groupBy("user_id").agg(F.count("*").alias("n_sessions"), F.sum("n_rows").alias("n_rows"))


_LATE = "SELECT max(ts) - INTERVAL 7 DAY AS mark, min(ts) + (max(ts) - min(ts)) / 2 AS half FROM events"


@query("op_stream_late_rows", f"SELECT strftime(to_timestamp(w * 604800) AT TIME ZONE 'UTC', '%Y-%m-%d') AS day, count(*) AS n_rows FROM (SELECT ts, epoch(ts)::BIGINT // 604800 AS w FROM events), ({_LATE}) WHERE ts >= half OR to_timestamp((w + 1) * 604800) AT TIME ZONE 'UTC' > mark GROUP BY 1")
def op_late(spark: SparkSession, d: str) -> DataFrame:
    """The later half of events comes first; of the earlier half, which comes in a second file, the rows whose window the
    watermark (a week behind) has passed by then are dropped."""
    e, files, path, checkpoint = read_table(spark, d, "events"), shared_path(spark, "late"), shared_path(spark, "windows"), shared_path(spark, "offsets")
    half = e.agg((F.min("ts") + (F.max("ts") - F.min("ts")) / 2).alias("h")).first()["h"]
    build = lambda: st.event_stream(spark, files, e.schema).withWatermark("ts", "7 days").groupBy(F.window("ts", "7 days").alias("window")).agg(F.count("*").alias("n_rows"))
    run = lambda: build().writeStream.outputMode("append").format("parquet").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    for part in (e.where(F.col("ts") >= half), e.where(F.col("ts") < half), st.end_marker(e, 7, 7, "user_id")):
        part.coalesce(1).write.mode("append").parquet(files)
        run()
    found = spark.read.schema(build().schema).parquet(path)
    return found.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "n_rows")


@query("op_stream_rate", "SELECT true AS all_there, true AS distinct_cells_fit")
def op_rate(spark: SparkSession, d: str) -> DataFrame:
    """A load of distinct items from the rate source, sketched as it comes: as many cells as so many items fill."""
    path, checkpoint = shared_path(spark, "rate"), shared_path(spark, "offsets")
    q = st.rate_stream(spark, 2000).writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).start()
    try:
        while q.isActive and sum(p["numInputRows"] for p in q.recentProgress) < 2000:
            q.awaitTermination(1)
    finally:
        q.stop()
    rows = spark.read.schema("item string, ts timestamp").parquet(path)
    n, cells = rows.agg(F.count("*").alias("n"), F.count_distinct("item").alias("d")), set_cells(rows, F.col("item"), WIDE).agg(F.count("*").alias("c"))
    return n.crossJoin(cells).select((F.col("n") == F.col("d")).alias("all_there"), ((F.col("c") <= F.col("n")) & (F.col("c") > 0)).alias("distinct_cells_fit"))


@query("op_stream_deduplication", "SELECT count(DISTINCT (user_id, event_type)) AS n FROM events")
def op_dedup(spark: SparkSession, d: str) -> DataFrame:
    s = st.deduplicated(_stream(spark, d), ["user_id", "event_type"], "3650 days").select("user_id", "event_type")
    return _run(spark, s, "append").agg(F.count("*").alias("n"))


def released(spark: SparkSession, e: DataFrame, files: str, release: str, noise: str = "stream", by: list[str] | None = None) -> tuple[DataFrame, DataFrame]:
    """Bitmaps of all windows of a table of events, streamed from its files and then closed by an end marker; and the ledger."""
    late = st.covering_days(e)
    s = st.window_bitmaps(st.event_stream(spark, files, e.schema), F.col("user_id").cast("string"), SMALL, "7 days", late=f"{late} days", by=by)
    path, ledger, checkpoint = shared_path(spark, "released"), shared_path(spark, "ledger"), shared_path(spark, "offsets")
    run = lambda: st.release_stream(s, SMALL, bd.symmetric(3.0), KEY, release, path, ledger, checkpoint, by, noise=noise).awaitTermination()
    run()
    # a run of its own, so that the marker is read last
    st.end_marker(e, late, 7, "user_id").write.mode("append").parquet(files)
    run()
    names = "".join(f"{c} string, " for c in by or [])
    return spark.read.option("basePath", path).schema(f"window_start string, {names}bucket_no long, bits binary, epoch int").parquet(path), io.read_ledger(spark, ledger)


_WEEKS = "SELECT strftime(to_timestamp(epoch(ts)::BIGINT // 604800 * 604800) AT TIME ZONE 'UTC', '%Y-%m-%d %H:%M:%S') AS g, CAST(user_id AS VARCHAR) AS item FROM events"
_STREAM = bd.symmetric(3.0)


@query("op_stream_private_release", f"SELECT g AS window_start, round(n_hat, 3) AS n_hat, 'ok' AS status, 3.0::DOUBLE AS eps_spent FROM ({S.fit(S.arrays(S.levels(S.flip(S.dense(_WEEKS, SMALL), _STREAM.p, _STREAM.q, KEY, 'events-stream'), SMALL)), SMALL, _STREAM.p, _STREAM.q)})")
def op_release(spark: SparkSession, d: str) -> DataFrame:
    """All windows of events, each released and booked once, when the watermark has closed it."""
    bitmaps, ledger = released(spark, read_table(spark, d, "events"), _files(spark, d), "events-stream", "cell")
    fitted = cardinality(arrow.level_counts_packed(bitmaps, SMALL, ["window_start"]), SMALL, _STREAM.p, _STREAM.q, "bisect")
    spent = io.spent(ledger).select(F.col("scope").alias("window_start"), F.round("eps_spent", 9).alias("eps_spent"))
    return fitted.join(spent, "window_start").select("window_start", F.round("n_hat", 3).alias("n_hat"), "status", "eps_spent")


_PARTY_FLIP = bd.symmetric(3.0)


@query("op_flip_packed", S.ones_csv(S.levels(S.flip(S.dense(party_sql(), WIDE, "party"), _PARTY_FLIP.p, _PARTY_FLIP.q, KEY, "packed", "party"), WIDE, "party"), "party"))
def op_flip_packed(spark: SparkSession, d: str) -> DataFrame:
    """Packed sketches flipped bitmap by bitmap, with the long form's noise: the same bits."""
    noisy = arrow.flip_packed(arrow.sketch_packed(party_items(spark, d), F.col("item"), WIDE, ["party"]), _PARTY_FLIP, WIDE, KEY, "packed", ["party"], "cell")
    return arrow.level_counts_packed(noisy, WIDE, ["party"]).select("party", csv(F.col("ones")).alias("ones"))


# --- user functions


@query("op_udaf_packed_merge", S.ones_csv(S.levels(S.dense(LINES, WIDE), WIDE)))
def op_udaf(spark: SparkSession, d: str) -> DataFrame:
    """Packed sketches of several parties, united in numpy group by group; infinite budgets give the plain union."""
    bitmaps = arrow.sketch_packed(party_items(spark, d), F.col("item"), WIDE, ["g", "party"]).withColumn("eps", F.lit(float("inf")))
    merged = arrow.merge_packed(bitmaps, WIDE, ["g"], "packed")
    counts = arrow.level_counts_packed(merged, WIDE, ["g"])
    return counts.select("g", csv(F.col("ones")).alias("ones"))


@query("op_udaf_packed_noisy")
def op_udaf_noisy(spark: SparkSession, d: str) -> DataFrame:
    plain = arrow.sketch_packed(party_items(spark, d), F.col("item"), WIDE, ["g", "party"])
    bitmaps = arrow.flip_packed(plain, bd.symmetric(3.0), WIDE, KEY, "packed-noisy", ["g", "party"], "cell").withColumn("eps", F.lit(3.0))
    levels = arrow.level_counts_packed(arrow.merge_packed(bitmaps, WIDE, ["g"], "packed", "cell"), WIDE, ["g"])
    f = bd.symmetric(bd.combine_or([3.0] * 4))
    return cardinality(levels, WIDE, f.p, f.q, "bisect").select("g", F.round("n_hat", 2).alias("n_hat"), "status")


@query("op_udtf_sketch_cells", f"SELECT g, cell // 16 AS bucket, (cell % 16 + 1)::INTEGER AS level FROM ({_CELLS})")
def op_udtf(spark: SparkSession, d: str) -> DataFrame:
    """Bitmaps to (bucket, level) rows by a table function."""
    bitmaps = packed(order_items(spark, d), F.col("item"), SMALL, ["g"])
    return arrow.cells_by_table_function(spark, bitmaps, SMALL)


_VECTOR = bd.symmetric(2.0)


@query("op_pandas_udf_fit", f"SELECT g, round(n_hat, 3) AS n_hat, round(n_hat, 3) AS vectorised FROM ({S.fit(S.arrays(S.levels(S.flip(S.dense(ORDERS, SMALL), _VECTOR.p, _VECTOR.q, KEY, 'vector'), SMALL)), SMALL, _VECTOR.p, _VECTOR.q)})")
def op_pandas_fit(spark: SparkSession, d: str) -> DataFrame:
    """The vectorised fit of many sketches, beside the one in expressions."""
    f = bd.symmetric(2.0)
    levels = level_counts(flip(sketch(order_items(spark, d), F.col("item"), SMALL, ["g"]), f, KEY, "vector", ["g"]), SMALL, ["g"])
    both = cardinality(levels, SMALL, f.p, f.q, "bisect").withColumn("vectorised", arrow.fit_udf(SMALL, f.p, f.q)(F.col("ones")))
    return both.select("g", F.round("n_hat", 3).alias("n_hat"), F.round("vectorised", 3).alias("vectorised"))


@query("op_sql_functions", f"SELECT e1, round(-ln(exp(-e1) + exp(-2.0::DOUBLE) - exp(-e1 - 2.0::DOUBLE)), 9) AS effective, round({S.stderr(SMALL, '1000.0::DOUBLE', '0.8', '0.2')}, 6) AS stderr, {S.cell(repr('abc'), SMALL)} AS cell FROM (VALUES (1.0::DOUBLE), (2.0::DOUBLE)) x(e1)")
def op_sql(spark: SparkSession, d: str) -> DataFrame:
    sqlapi.register(spark, SMALL)
    return spark.sql("SELECT e1, round(sk_effective_eps(e1, 2.0D), 9) AS effective, round(sk_stderr(1000.0D, 0.8D, 0.2D), 6) AS stderr, sk_cell('abc') AS cell FROM VALUES (1.0D), (2.0D) AS x(e1)")


__all__ = ["Layout", "T", "cell_frame", "cell_of", "party_sql"]
