"""Mixing sources to target weights by weighted fair queueing.

Each source is a queue of its documents in a shuffled order that depends on doc_id alone. A document's
virtual finish time is the size of its queue up to its own end, divided by the source's target; a
source that must give more than it has starts over, up to `repeats` times. All queues are range-sorted together
by finish time, sizes are summed along that one order, and the mix ends where the sum reaches the total budget,
which is the sum of the targets. A document that its source's target falls into is served in two pieces, before and
after the target, so that a long one doesn't keep its whole source out or push it far over.

The running sizes inside a queue come from slices: each source's order is cut by the leading bits of the shuffle key
into slices of about SLICE documents, sums over slices are accumulated, and each slice is summed on its
own, so that a source with a third of all rows is no single task's work. Sums along all queues are sums of ranges
(`common.running`), and so are those along the table of sources beyond BROADCAST_SOURCES of them.

Null texts have size 0 and are taken 0 times. Sources are ordered by code point, null last. Very long texts are
cut after a word. Rows of equal finish time go by source, then place in the queue; rows of a source with equal id and
size are interchangeable. Repeated rows are separate documents; an empty table gives an empty result. Sources
without words get target 0. The caller's columns stay together in the struct `row`, so none clashes.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import running, table, word_count, wrapped, written

#: Documents of a source that one window task adds up, about.
SLICE = 2000
REPEATS = 3
#: Sources up to which their table is broadcast; beyond, it is joined by shuffle with the slices.
BROADCAST_SOURCES = 200_000
HEX_BITS = 24


def shuffle_key(doc_id: Column) -> Column:
    """Six hex digits and more of a hash of the id: the same order in every run."""
    return F.md5(F.coalesce(doc_id.cast("string"), F.lit("null")).cast("binary"))


def targets(sources: DataFrame, repeats: int = REPEATS, weights: tuple[int, ...] = (1, 2, 3)) -> DataFrame:
    """_source, source_size, n_docs, target: shares of the whole by weight, none above repeats times its size.

    A source is at its limit exactly if the level at which all sources of lower limit per weight are
    full lies at or above its own limit per weight; the level of the others follows.
    """
    few = sources.limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES
    along = _at_once if few else running  # a table of this size is one task's work, a larger one is summed by ranges
    rows = along(sources, [F.col("_source")], {"_which": F.lit(1)})
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod("_which", F.lit(len(weights))) + 1).cast("int"))
    rows = rows.withColumn("w", weight).withColumn("cap", F.col("source_size") * float(repeats))
    rows = along(rows.drop("_which"), [F.col("cap") / F.col("w"), F.col("_source")], {"_caps": F.col("cap"), "_ws": F.col("w")})
    whole = rows.agg(F.sum("source_size").cast("double").alias("_all"), F.sum("w").alias("_w_all"))
    level = (F.col("_all") - F.col("_caps")) / (F.col("_w_all") - F.col("_ws"))
    # passing over a source that isn't full lowers the level, so the first such one's is the highest
    full = F.col("cap") <= F.col("level") * F.col("w")
    rows = rows.crossJoin(F.broadcast(whole)).withColumn("level", level).withColumn("_full", full)  # whole is a single row
    final = rows.agg(F.max(F.when(~F.col("_full"), F.col("level"))).alias("_final"))
    target = F.when(F.col("_full"), F.col("cap")).otherwise(F.least(F.col("cap"), F.col("w") * F.col("_final")))
    return rows.crossJoin(F.broadcast(final)).select("_source", "source_size", "n_docs", F.round(target, 6).alias("target"))


def _at_once(df: DataFrame, order: list[Column], sums: dict[str, Column]) -> DataFrame:
    """What common.running gives, by one task: for tables whose size has been checked."""
    before = Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    return df.select("*", *[F.coalesce(F.sum(x).over(before), F.lit(0)).alias(c) for c, x in sums.items()])


def _pieces(repeats: int) -> Column:
    """The pieces in which a queued document is served: round, first word in the queue, words, finish time."""
    line = F.floor(F.col("target") + 1e-6)
    found = []
    for e in range(repeats):
        start = F.lit(e) * F.col("source_size") + F.col("before")
        end, inside = start + F.col("size"), F.greatest(F.lit(0), F.least(F.col("size"), line - start))
        for first, words, last in ((start, inside, F.least(end, line)), (start + inside, F.col("size") - inside, end)):
            found.append(F.struct(F.lit(e).alias("e"), first.cast("long").alias("first"), words.cast("long").alias("words"), F.try_divide(last, F.col("target")).alias("finish")))
    return F.filter(F.array(*found), lambda x: x["words"] > 0)


def mix(docs: DataFrame, size: Column, key: str = "doc_id", source: str = "source", repeats: int = REPEATS) -> DataFrame:
    """`row` (docs' columns), size, source_size, target, `before` (the queue before the document), taken, and `rounds`:
    the words taken in each round, with the round's first word in the queue."""
    named = F.coalesce(F.concat(F.lit("="), F.col(source)), F.lit("null")).alias("_source")
    mine = [named, size.cast("long").alias("size"), shuffle_key(F.col(key)).alias("_u"), F.col(key).alias("_key")]
    # sizes are narrow, so they are written once for the steps that add them up
    narrow = written(docs.select(*mine), "sizes")
    sums = targets(written(narrow.groupBy("_source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n_docs")), "sources"), repeats)
    # bits of the shuffle key that cut a source's order into slices of about SLICE documents
    bits = F.greatest(F.lit(0), F.least(F.lit(HEX_BITS), F.ceil(F.log2(F.col("n_docs") / SLICE)))).cast("int")
    plan = written(sums.select("_source", "source_size", "target", bits.alias("_bits")), "targets")
    few = plan.limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES
    hint = F.broadcast if few else (lambda df: df)
    at = F.expr(f"shiftright(cast(conv(substr(_u, 1, {HEX_BITS // 4}), 16, 10) as int), {HEX_BITS} - _bits)")
    slices = narrow.join(hint(plan), "_source").withColumn("_slice", at).groupBy("_source", "_slice").agg(F.sum("size").alias("_sum"))
    order = Window.partitionBy("_source").orderBy("_slice").rowsBetween(Window.unboundedPreceding, -1)
    slices = written(slices.select("_source", "_slice", F.coalesce(F.sum("_sum").over(order), F.lit(0)).alias("_offset")), "slices")
    inside = Window.partitionBy("_source", "_slice").orderBy("_u", "_key", "size").rowsBetween(Window.unboundedPreceding, -1)

    def queue(rows: DataFrame) -> DataFrame:
        joined = rows.join(hint(plan), "_source").withColumn("_slice", at).join(slices, ["_source", "_slice"])
        return joined.withColumn("before", F.col("_offset") + F.coalesce(F.sum("size").over(inside), F.lit(0))).withColumn("_pieces", _pieces(repeats))

    budget = int(plan.agg(F.sum(F.floor(F.col("target") + 1e-6)).alias("n")).first()["n"] or 0)
    served = queue(narrow).select("_source", F.explode("_pieces").alias("_p")).select("_source", "_p.first", "_p.words", "_p.finish")
    summed = running(served, [F.col("finish"), F.col("_source"), F.col("first")], {"ahead": F.col("words")})
    # the piece in which the sum reaches the budget: everything before it in the order is taken, and its words up to there
    last = summed.where((F.col("ahead") < budget) & (F.col("ahead") + F.col("words") >= budget)).first() if budget else None
    if last is None:
        words = lambda p: F.lit(0).cast("long")
    else:
        at_last = F.lit(last["_source"]), F.lit(last["first"])
        sooner = lambda p: (p["finish"] < last["finish"]) | ((p["finish"] == last["finish"]) & ((F.col("_source") < at_last[0]) | ((F.col("_source") == at_last[0]) & (p["first"] < at_last[1]))))
        final = lambda p: (p["finish"] == last["finish"]) & (F.col("_source") == at_last[0]) & (p["first"] == at_last[1])
        words = lambda p: F.when(sooner(p), p["words"]).when(final(p), F.lit(budget - last["ahead"]).cast("long")).otherwise(F.lit(0).cast("long"))
    given = lambda e: lambda x, p: x + F.when(p["e"] == e, words(p)).otherwise(F.lit(0).cast("long"))
    rounds = F.array(*[
        F.struct(F.lit(e).alias("e"), (F.lit(e) * F.col("source_size") + F.col("before")).alias("first"), F.aggregate("_pieces", F.lit(0).cast("long"), given(e)).alias("words"))
        for e in range(repeats)
    ])
    queued = queue(docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), *mine)).withColumn("rounds", rounds)
    taken = F.aggregate("rounds", F.lit(0).cast("long"), lambda x, r: x + r["words"])
    return queued.select("row", "size", "source_size", "target", "before", taken.alias("taken"), "rounds")


def mixed_documents(docs: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", repeats: int = REPEATS) -> DataFrame:
    """The mix itself, range-sorted by virtual finish time: a row for each time that a document is taken, its
    text cut after the last word that is taken. Columns of docs."""
    rows = mix(wrapped(docs), word_count(F.col(f"row.{text}")), f"row.{key}", f"row.{source}", repeats)
    doc, doc_text = F.col("row.row"), F.col(f"row.row.{text}")
    each = rows.withColumn("_r", F.explode(F.filter("rounds", lambda r: r["words"] > 0)))
    runs = F.regexp_extract_all(doc_text, F.lit(r"[\x20\x09-\x0D]*[^\x20\x09-\x0D]+"), F.lit(0))
    cut = F.array_join(F.slice(runs, F.lit(1), F.col("_r.words").cast("int")), "")
    shown = F.when(F.col("_r.words") < F.col("size"), cut).otherwise(doc_text)
    finish = F.try_divide(F.col("_r.first") + F.col("_r.words"), F.col("target"))
    timed = each.select(doc.withField(text, shown).alias("row"), finish.alias("_finish"), F.col("_r.e").alias("_e"))
    return timed.repartitionByRange("_finish", "_e").sortWithinPartitions("_finish", f"row.{key}").select("row.*")


def op7_mixing(spark, sf_dir: str) -> DataFrame:
    """doc_id, size, source_size, target, taken of every document."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "source", word_count(F.col("text")).alias("words"))
    return mix(docs, F.col("words")).select("row.doc_id", "size", "source_size", "target", "taken")


OP7_SQL = r"""
WITH d AS (
  SELECT doc_id, coalesce('=' || source, 'null') AS source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size,
         md5(coalesce(CAST(doc_id AS VARCHAR), 'null')) AS u, row_number() OVER () AS id FROM documents
), s AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size, row_number() OVER (ORDER BY source) - 1 AS n FROM d GROUP BY source
), w AS (
  SELECT source, source_size, 3.0 * source_size AS cap, n % 3 + 1 AS w, CAST(sum(source_size) OVER () AS DOUBLE) AS total FROM s
), l AS (
  SELECT *, (total - coalesce(sum(cap) OVER o, 0)) / (sum(w) OVER () - coalesce(sum(w) OVER o, 0)) AS level
  FROM w WINDOW o AS (ORDER BY cap / w, source ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)
), t AS (
  SELECT source, source_size, round(CASE WHEN cap <= level * w THEN cap ELSE least(cap, w * max(CASE WHEN cap > level * w THEN level END) OVER ()) END, 6) AS target FROM l
), q AS (
  SELECT id, doc_id, source, size, source_size, target, CAST(floor(target + 1e-6) AS BIGINT) AS line,
    CAST(coalesce(sum(size) OVER (PARTITION BY source ORDER BY u, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS before
  FROM d JOIN t USING (source)
), e AS (
  SELECT *, before + e * source_size AS start, greatest(0, least(size, line - before - e * source_size)) AS inside FROM q, range(3) r(e)
), p AS (
  SELECT id, source, start AS first, inside AS words, CAST(least(start + size, line) AS DOUBLE) / target AS finish FROM e WHERE inside > 0
  UNION ALL SELECT id, source, start + inside, size - inside, CAST(start + size AS DOUBLE) / target FROM e WHERE size > inside
), a AS (
  SELECT id, words, coalesce(sum(words) OVER (ORDER BY finish, source, first ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ahead FROM p
), x AS (
  SELECT id, CAST(sum(greatest(0, least(words, (SELECT sum(floor(target + 1e-6)) FROM t) - ahead))) AS BIGINT) AS taken FROM a GROUP BY id
)
SELECT doc_id, size, source_size, target, coalesce(taken, 0) AS taken FROM q LEFT JOIN x USING (id)
"""
