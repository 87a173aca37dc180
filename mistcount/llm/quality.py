"""Quality rules of documents and of their hosts.

The base rules of a document count words, symbols, repeated lines and repeated three-word windows. A
host's rule failures are aggregated; its failure rate is shrunk towards a beta prior that is fitted to
all hosts by their mean and variance, so that hosts with few documents are not judged by chance. Hosts
then get a verdict, which is joined back to their documents:

* trusted (shrunk rate below SUSPECT): documents that pass the base rules stay;
* suspect: those that break a soft rule (symbols, repeated lines) go as well;
* blocked (the rate's lower bound above BLOCKED): all documents go.

A null text has no words, and fails. A null host is a host of its own. Repeated rows count one by one;
an empty table gives an empty result. Texts are read whole, whatever their length. A rate that equals a threshold is not
beyond it. The caller's columns stay together in the struct `row`, so none clashes with the measures.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import BLANKS, KEPT, table, text_bytes, tidy, wrapped, written

SYMBOLS = b"#*$%&|<>"
MIN_WORDS, REPEAT_PERCENT = 50, 50
#: Soft rules, in percent: symbols of word characters, words' lines that repeat of all lines with a word.
SYMBOL_PERCENT, LINE_PERCENT = 10, 30
SUSPECT, BLOCKED = 0.5, 0.9
#: Hosts up to which the table of verdicts is broadcast; beyond, Spark joins by shuffle, salted.
BROADCAST_HOSTS = 200_000
SALTS = 16

STATS = T.StructType([T.StructField(c, T.LongType()) for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_lines", "n_repeat_words")])


def repeat_words(words: list[bytes]) -> int:
    """Words inside three-word windows that occur at least twice."""
    n = len(words)
    if n < 4:
        return 0
    index: dict[bytes, int] = {}
    ids = np.array([index.setdefault(w, len(index)) for w in words], np.int64)
    v = len(index)
    if v < 2_000_000:
        key = (ids[:-2] * v + ids[1:-1]) * v + ids[2:]
    else:  # the product would overflow: number the pairs first
        _, pair = np.unique(ids[:-1] * v + ids[1:], return_inverse=True)
        key = pair[:-1] * v + ids[2:]
    _, which, count = np.unique(key, return_inverse=True, return_counts=True)
    again = count[which] > 1
    covered = np.zeros(n, bool)
    for k in range(3):
        covered[k : n - 2 + k] |= again
    return int(covered.sum())


def stats_of(raw: bytes | None) -> tuple[int, ...]:
    if not raw:
        return (0,) * 6
    words = raw.split()
    inked = raw.translate(None, BLANKS)
    # UTF-8 continuation bytes are no code points of their own
    chars = len(inked.decode("utf-8", "replace"))
    lines = [x for x in raw.split(b"\n") if x.strip(BLANKS)]
    return len(words), chars, len(raw) - len(raw.translate(None, SYMBOLS)), len(lines) - len(set(lines)), len(lines), repeat_words(words)


@F.arrow_udf(STATS)
def _stats(rows: Iterator[pa.Array]) -> Iterator[pa.Array]:
    KEPT.clear()
    for texts in rows:
        columns = [[] for _ in STATS.names]
        for at in range(0, len(texts), 512):
            for raw in text_bytes(texts.slice(at, 512)):
                for column, x in zip(columns, stats_of(raw), strict=True):
                    column.append(x)
        yield pa.StructArray.from_arrays([pa.array(c, pa.int64()) for c in columns], names=STATS.names)
    tidy()


def text_stats(text: Column) -> Column:
    """The base measures of a text, as a struct."""
    return _stats(text)


def base_failed(s: Column) -> Column:
    return (s["n_words"] < MIN_WORDS) | (s["n_repeat_words"] * 100 > s["n_words"] * REPEAT_PERCENT)


def soft_failed(s: Column) -> Column:
    return (s["n_symbols"] * 100 > s["word_chars"] * SYMBOL_PERCENT) | (s["n_dup_lines"] * 100 > s["n_lines"] * LINE_PERCENT)


def host_verdicts(failures: DataFrame) -> DataFrame:
    """Per host: documents, failures, shrunk failure rate, verdict. failures: host, failed boolean."""
    hosts = failures.groupBy("host").agg(F.count("*").alias("n_docs"), F.sum(F.col("failed").cast("long")).alias("n_failed"))
    rate = F.col("n_failed") / F.col("n_docs")
    prior = hosts.agg(F.avg(rate).alias("m"), F.coalesce(F.var_samp(rate), F.lit(0.0)).alias("v"))
    # by moments; a variance that no beta has, or none at all, gives a prior of one document's weight
    spread = F.col("m") * (1 - F.col("m"))
    weight = F.when((F.col("v") > 0) & (spread > F.col("v")), spread / F.when(F.col("v") > 0, F.col("v")) - 1).otherwise(F.lit(1.0))
    prior = prior.select("m", F.least(weight, F.lit(1000.0)).alias("w"))
    joined = hosts.crossJoin(F.broadcast(prior))  # the prior is a single row
    a = F.col("n_failed") + F.col("m") * F.col("w")
    total = F.col("n_docs") + F.col("w")
    shrunk = joined.withColumn("host_rate", a / total).withColumn("host_low", F.col("host_rate") - 2 * F.sqrt(F.col("host_rate") * (1 - F.col("host_rate")) / (total + 1)))
    verdict = F.when(F.col("host_low") > BLOCKED, "blocked").when(F.col("host_rate") > SUSPECT, "suspect").otherwise("trusted")
    return shrunk.select("host", "n_docs", "n_failed", "host_rate", verdict.alias("host_verdict"))


def with_verdicts(docs: DataFrame, hosts: DataFrame, host: Column) -> DataFrame:
    """docs with their host's rate and verdict; docs' own columns are left as they are."""
    hosts = written(hosts.select("host", "host_rate", "host_verdict"), "hosts")
    host = F.coalesce(F.concat(F.lit("="), host.cast("string")), F.lit("null"))
    keyed = hosts.withColumn("_host", F.coalesce(F.concat(F.lit("="), F.col("host").cast("string")), F.lit("null"))).drop("host")
    if hosts.count() <= BROADCAST_HOSTS:
        return docs.withColumn("_host", host).join(F.broadcast(keyed), "_host").drop("_host")
    spread = keyed.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    salted = docs.withColumn("_host", host).withColumn("_salt", F.pmod(F.monotonically_increasing_id(), F.lit(SALTS)).cast("int"))
    return salted.join(spread, ["_host", "_salt"]).drop("_host", "_salt")


def is_kept(s: Column, verdict: Column) -> Column:
    return ~base_failed(s) & (verdict != "blocked") & ((verdict == "trusted") | ~soft_failed(s))


def judge(docs: DataFrame, text: str = "text", host: str = "source") -> DataFrame:
    """`row` (docs' columns), `stats` (the measures), host_rate, host_verdict and kept. The texts are measured
    twice, once for the hosts and once for the rows themselves, so that no text is shuffled."""
    rows, s = wrapped(docs), F.col("stats")
    failures = rows.select(F.col(f"row.{host}").alias("host"), text_stats(F.col(f"row.{text}")).alias("stats")).select("host", (base_failed(s) | soft_failed(s)).alias("failed"))
    measured = rows.withColumn("stats", text_stats(F.col(f"row.{text}")))
    return with_verdicts(measured, host_verdicts(failures), F.col(f"row.{host}")).withColumn("kept", is_kept(s, F.col("host_verdict")))


def quality_filter(docs: DataFrame, text: str = "text", host: str = "source") -> DataFrame:
    """The documents that the rules keep, with the columns of docs."""
    return judge(docs, text, host).where("kept").select("row.*")


def op2_quality_rules(spark, sf_dir: str) -> DataFrame:
    """doc_id, n_words, the four base measures, base_failed, kept, and the host's rate and verdict."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "source")
    # the measures are narrow, so they are written once and used for the hosts and for the rows
    rows = written(docs.select("doc_id", "source", text_stats(F.col("text")).alias("_stats")), "measures")
    s = F.col("_stats")
    hosts = host_verdicts(rows.select(F.col("source").alias("host"), (base_failed(s) | soft_failed(s)).alias("failed")))
    return with_verdicts(rows, hosts, F.col("source")).select("doc_id", *[s[c].alias(c) for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")], base_failed(s).alias("base_failed"), is_kept(s, F.col("host_verdict")).alias("kept"), F.round("host_rate", 9).alias("host_rate"), "host_verdict")


OP2_SQL = rf"""
WITH d AS (SELECT row_number() OVER () AS id, doc_id, source, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
t AS (SELECT id, i, ws[i] AS a, ws[i + 1] AS b, ws[i + 2] AS c FROM d, unnest(range(1, greatest(len(ws) - 1, 1))) u(i)),
r AS (SELECT id, count(DISTINCT i + k) AS n FROM (SELECT id, i, count(*) OVER (PARTITION BY id, a, b, c) AS times FROM t), range(3) z(k) WHERE times > 1 GROUP BY id),
l AS (SELECT id, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls FROM d),
m AS (
  SELECT doc_id, source, len(ws)::BIGINT AS n_words, coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0)::BIGINT AS word_chars, len(regexp_extract_all(text, '[#*$%&|<>]'))::BIGINT AS n_symbols,
    (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines, len(ls) AS n_lines, coalesce(r.n, 0)::BIGINT AS n_repeat_words FROM d JOIN l USING (id) LEFT JOIN r USING (id)
),
f AS (SELECT *, n_words < {MIN_WORDS} OR 100 * n_repeat_words > {REPEAT_PERCENT} * n_words AS base_failed, 100 * n_symbols > {SYMBOL_PERCENT} * word_chars OR 100 * n_dup_lines > {LINE_PERCENT} * n_lines AS soft FROM m),
h AS (SELECT source, count(*) AS n, count(*) FILTER (WHERE base_failed OR soft) AS bad FROM f GROUP BY source),
p AS (SELECT avg(bad / n) AS m, coalesce(var_samp(bad / n), 0) AS v FROM h),
q AS (SELECT m, least(1000.0, CASE WHEN v > 0 AND m * (1 - m) > v THEN m * (1 - m) / nullif(v, 0) - 1 ELSE 1.0 END) AS w FROM p),
g AS (SELECT source, (bad + m * w) / (n + w) AS rate, n + w AS total FROM h, q),
v AS (SELECT source, rate, CASE WHEN rate - 2 * sqrt(rate * (1 - rate) / (total + 1)) > {BLOCKED} THEN 'blocked' WHEN rate > {SUSPECT} THEN 'suspect' ELSE 'trusted' END AS verdict FROM g)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND verdict <> 'blocked' AND (verdict = 'trusted' OR NOT soft) AS kept, round(rate, 9) AS host_rate, verdict AS host_verdict
FROM f JOIN v ON f.source IS NOT DISTINCT FROM v.source
"""
