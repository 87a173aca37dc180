"""Exact top-k inner products by a three-phase uniform threshold.

The components of the vectors are dealt into a few lists (blocks of components); the score of a pair
is the sum of its partial scores in the lists. Every task holds some rows of all lists.

1. Each task gathers its local score lists: for each query and list the rows of highest partial
   score. A row that is seen in some lists scores at least its partial scores there plus the lowest
   partial score of the others; the k-th highest of these bounds is one that the answers reach.
2. That bound, less the lists' lowest scores and divided by the number of lists, is the uniform
   cutoff, broadcast to all tasks: a row below it in every list cannot be an answer.
3. Each task goes through the lists of its rows, adding up partial scores of the pairs that may still be answers: those
   whose sum so far, with the most that the norms of the lists to come allow, reaches the bound. Pairs that reach it
   with all lists, and the cutoff in some list, are sufficient entries and have been scored exactly; a row that no query
   needs any more is left out of the lists to come. Each task returns its k best of each query; the k best of these are
   the answer. How much is saved depends on the vectors: `survivors` tells the share of rows read of each list.

Queries go in blocks of at most QUERY_BLOCK vectors, so that what is broadcast has a fixed bound. For
each query a task returns k rows at most, however many rows tie.

Vectors that are null, or hold null or non-finite components, or have another length than the most
frequent one, take no part; vectors may be of any length. Candidates with the query's own vec_id, repeated rows of it included, are
left out; further rows that repeat a vec_id count once, with their highest score; so do queries. Ties
go to the smaller vec_id. Scores are exact while they stay below 2**53. An empty table gives an empty result. Only vec_id
and vec are read, so other columns of any name do no harm.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import partitions, table, written

#: Queries whose vectors and cutoffs are broadcast at a time.
QUERY_BLOCK = 4096
#: Rows that are scored against a block of queries at a time: bounds the score matrix.
ROWS = 1024
LISTS = 4


def _scored(rows: Iterator[pa.RecordBatch], width: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Ids and vectors, some rows at a time."""
    for batch in rows:
        for at in range(0, batch.num_rows, ROWS):
            part = batch.slice(at, ROWS)
            flat = part.column("vec").flatten().to_numpy(zero_copy_only=False)
            yield part.column("vec_id").to_numpy(zero_copy_only=False), flat.reshape(-1, width)


def _best(scores: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Columns of the k highest distinct ids of a row of scores, ties to smaller ids; -inf doesn't count."""
    def of(keep: np.ndarray) -> np.ndarray:
        keep = keep[np.lexsort((ids[keep], -scores[keep]))]
        _, first = np.unique(ids[keep], return_index=True)
        return keep[np.sort(first)[:k]]

    if len(scores) > 4 * k:
        floor = np.partition(scores, len(scores) - k)[len(scores) - k]
        if floor > -np.inf and len(found := of(np.flatnonzero(scores >= floor))) == k:
            return found  # else rows of one id have crowded out others
    return of(np.flatnonzero(scores > -np.inf))


def survivors(q: np.ndarray, v: np.ndarray, edges: np.ndarray, low: np.ndarray, above: np.ndarray, alive: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Scores of queries and rows, which of them may be answers (only their scores are whole), and the share of rows read
    of each list. low: the least partial scores; above: what a score must be over their sum; alive: pairs to look at."""
    norms = lambda x: np.stack([np.sqrt((x[:, a:b] ** 2).sum(axis=1)) for a, b in zip(edges[:-1], edges[1:], strict=True)], axis=1)
    of_q, of_v, lists = norms(q), norms(v), len(edges) - 1
    need = above + low.sum(axis=1)  # a score below this is no answer
    need = np.where(np.isfinite(need), need - 1e-9 * np.abs(need) - 1e-6, -np.inf)
    uniform, total, reach, read = above / lists, np.zeros(alive.shape), np.zeros(alive.shape, bool), np.zeros(lists)
    for j in range(lists):
        rows = np.flatnonzero(alive.any(axis=0))
        read[j] = len(rows) / max(1, len(v))
        if not len(rows):
            break
        part = q[:, edges[j] : edges[j + 1]] @ v[rows, edges[j] : edges[j + 1]].T
        reach[:, rows] |= part - low[:, j, None] >= uniform[:, None]
        total[:, rows] += part
        most = of_q[:, j + 1 :] @ of_v[rows, j + 1 :].T  # what the lists to come can add
        alive[:, rows] &= total[:, rows] + most * (1 + 1e-9) >= need[:, None]
    return total, alive & reach, read


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 5, lists: int = LISTS) -> DataFrame:
    """query_id, rank, vec_id, score of the k highest inner products of each query with other rows.

    Both inputs: vec_id long, vec array<double> of whole numbers.
    """
    spark = vectors.sparkSession
    fit = lambda df: df.where(F.col("vec_id").isNotNull() & F.col("vec").isNotNull() & ~F.exists("vec", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))))
    vectors, queries = fit(vectors.select("vec_id", "vec")), fit(queries.select("vec_id", "vec"))
    shapes = queries.groupBy(F.size("vec").alias("w")).count().orderBy(F.desc("count"), "w").take(1)
    out = "query_id long, rank int, vec_id long, score long"
    if not shapes or not shapes[0]["w"]:
        return spark.createDataFrame([], out)
    width, held = shapes[0]["w"], F.size("vec") == shapes[0]["w"]
    vectors, queries = vectors.where(held), queries.where(held)
    n_blocks = 1 + queries.count() * 5 // (QUERY_BLOCK * 4)
    parts = [_block(vectors, queries.where(F.pmod(F.xxhash64("vec_id"), F.lit(n_blocks)) == b), width, k, lists) for b in range(n_blocks)]
    found = parts[0]
    for part in parts[1:]:
        found = found.unionByName(part)
    return found


def _block(vectors: DataFrame, queries: DataFrame, width: int, k: int, lists: int) -> DataFrame:
    spark = vectors.sparkSession
    rows = queries.orderBy("vec_id").collect()  # about QUERY_BLOCK at most
    q_ids, q = np.array([r["vec_id"] for r in rows], np.int64), np.array([r["vec"] for r in rows], float).reshape(-1, width)
    edges = np.linspace(0, width, lists + 1).astype(int)
    shared = spark.sparkContext.broadcast((q_ids, q))

    def local_lists(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, q = shared.value
        held = [[(np.empty(0), np.empty(0, np.int64))] * lists for _ in ids]
        low = np.full((len(ids), lists), np.inf)
        for vec_ids, v in _scored(batches, width):
            for j in range(lists):
                s = q[:, edges[j] : edges[j + 1]] @ v[:, edges[j] : edges[j + 1]].T
                own = ids[:, None] == vec_ids[None, :]
                low[:, j] = np.minimum(low[:, j], s.min(axis=1))
                s[own] = -np.inf
                for i in range(len(ids)):
                    best = _best(s[i], vec_ids, k)
                    a, b = np.concatenate([held[i][j][0], s[i, best]]), np.concatenate([held[i][j][1], vec_ids[best]])
                    best = _best(a, b, k)
                    held[i][j] = (a[best], b[best])
        if np.isfinite(low).any():
            n = [[len(held[i][j][0]) for j in range(lists)] for i in range(len(ids))]
            flat = np.array(n).ravel()
            yield pa.record_batch([pa.array(np.repeat(np.repeat(ids, lists), flat + 1)), pa.array(np.repeat(np.tile(np.arange(lists), len(ids)), flat + 1), pa.int32()), pa.array([x for i in range(len(ids)) for j in range(lists) for x in [None, *held[i][j][1].tolist()]], pa.int64()), pa.array([x for i in range(len(ids)) for j in range(lists) for x in [low[i, j], *held[i][j][0].tolist()]], pa.float64())], names=["query_id", "list", "vec_id", "part"])

    # a few rows for each task, query and list; three steps read them
    seen = written(vectors.mapInArrow(local_lists, "query_id long, list int, vec_id long, part double"), "lists")
    # the lowest partial scores, and the sum over the lists of what is known of a row beyond them
    lows = seen.where(F.col("vec_id").isNull()).groupBy("query_id", "list").agg(F.min("part").alias("low"))
    bound = (
        seen.where(F.col("vec_id").isNotNull()).groupBy("query_id", "vec_id", "list").agg(F.max("part").alias("part"))
        .join(lows, ["query_id", "list"]).groupBy("query_id", "vec_id").agg(F.sum(F.col("part") - F.col("low")).alias("above"))
    )
    ranked = bound.withColumn("r", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("above"), "vec_id")))
    cutoffs = lows.groupBy("query_id").agg(F.sort_array(F.collect_list(F.struct("list", "low"))).alias("lows")).join(ranked.where(F.col("r") == k).select("query_id", "above"), "query_id", "left")
    known = {r["query_id"]: ([x["low"] for x in r["lows"]], r["above"]) for r in cutoffs.collect()}  # a row a query of the block
    low = np.array([known[i][0] if i in known else [0.0] * lists for i in q_ids.tolist()]).reshape(-1, lists)
    # none where fewer than k rows are known: then every row is resolved
    above = np.array([x if (x := known.get(i, (0, None))[1]) is not None else -np.inf for i in q_ids.tolist()])
    cut = spark.sparkContext.broadcast((low, above))

    def resolve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        (ids, q), (low, above) = shared.value, cut.value
        held = [(np.empty(0), np.empty(0, np.int64))] * len(ids)
        for vec_ids, v in _scored(batches, width):
            total, alive, _ = survivors(q, v, edges, low, above, ids[:, None] != vec_ids[None, :])
            for i in np.flatnonzero(alive.any(axis=1)).tolist():
                mine = np.flatnonzero(alive[i])
                mine = mine[_best(total[i, mine], vec_ids[mine], k)]
                a, b = np.concatenate([held[i][0], total[i, mine]]), np.concatenate([held[i][1], vec_ids[mine]])
                best = _best(a, b, k)
                held[i] = (a[best], b[best])
        n = np.array([len(a) for a, _ in held], np.int64)
        if n.sum():
            yield pa.record_batch([pa.array(np.repeat(ids, n)), pa.array(np.concatenate([b for _, b in held])), pa.array(np.concatenate([a for a, _ in held]).astype(np.int64))], names=["query_id", "vec_id", "score"])

    local = vectors.mapInArrow(resolve, "query_id long, vec_id long, score long").groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return local.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def op1_exact_top_k(spark, sf_dir: str) -> DataFrame:
    """query_id, rank, vec_id, score: the 5 highest of every vec_id divisible by 50 over all embeddings."""
    # floor() of a non-finite double is not defined as a long, so such rows go before
    fit = table(spark, sf_dir, "embeddings").where(~F.exists("embedding", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))))
    rows = fit.select(F.col("vec_id").cast("long").alias("vec_id"), F.transform("embedding", lambda x: F.floor(x.cast("double") * 256).cast("double")).alias("vec"))
    spread = rows.repartition(partitions(spark)) if rows.rdd.getNumPartitions() < 2 else rows
    return top_k(spread, rows.where(F.col("vec_id") % 50 == 0))


OP1_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(CAST(x AS DOUBLE) * 256)) AS e FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id AS vec_id, CAST(list_dot_product(q.e, c.e) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id
), r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS n FROM s)
SELECT query_id, CAST(n AS INTEGER) AS rank, vec_id, score FROM r WHERE n <= 5
"""
