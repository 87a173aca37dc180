"""Removal of byte strings that occur twice, by suffix arrays of shards.

Every byte of a text is removed that a string of `length` bytes covers which also starts anywhere else,
in the same or another text. Matches do not cross texts, and strings are judged on the input.

Sharding. Each string of `length` bytes belongs to the least hash of the GRAM-byte grams inside it, so
equal strings belong to one hash wherever they stand. Neighbouring strings of one gram form a piece. A
hash that occurs once in the corpus needs no sorting; the texts' other pieces are dealt to shards by
their hash. Equal pieces are sorted once, with their number. A task hands on one row for each hash and
for each different piece it has met, and settles further ones at once, so that copies and frequent
passages are no hot keys. Each shard builds a suffix array of its pieces by induced sorting, and their
common prefixes; where `length` bytes are shared, strings are equal, and their places are removed. A
hash whose pieces are all equal needs no sorting. A
hash whose different pieces outgrow a shard (HOT_BYTES) is settled string by string instead, each told by a 128-bit
hash and its offset, so that no string is shuffled.

Texts that are equal count as so many copies of one text. Null texts are empty; texts shorter than
`length` are never changed; very long ones are held one at a time. Rows keep their own results, repeated
ones included, and all their columns, whatever their names; an empty table gives an empty result. Equal strings are all
removed, so nothing hangs on ties. Texts and pieces are told apart by 64-bit hashes (pieces together with the hash they belong to).
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batches, mixed, partitions, table, text_bytes, wrapped, written
from .suffixes import common_prefixes, suffix_array

LENGTH, GRAM = 200, 100
#: Bytes of text that are hashed at a time, rows that a task holds before it hands them on.
CHUNK, FLUSH = 1 << 19, 500_000
#: Bytes of pieces in a suffix array, about; bytes of one hash's pieces at most.
SHARD_BYTES, HOT_BYTES = 1 << 21, 1 << 24
#: Bits that hold a gram's place among its neighbours.
_PLACES = np.uint64((1 << 24) - 1)
_CODES = mixed(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
_BASE = 0xD6E8FEB86659FD93


def gram_hashes(raw: np.ndarray, size: int) -> np.ndarray:
    """A hash of the `size` bytes from each place on, by doubling."""
    def join(left: np.ndarray, right: np.ndarray, width: int) -> np.ndarray:
        return left * np.uint64(pow(_BASE, width, 1 << 64)) + right

    power, width, whole, done = _CODES[raw], 1, None, 0
    while True:
        if size & width:  # the bits of size, from the lowest: `whole` covers the last `done` bytes
            whole = power if whole is None else join(power[: len(whole) - width], whole[width:], done)
            done += width
        if done == size:
            return mixed(whole)
        power = join(power[: len(power) - width], power[width:], width)
        width *= 2


def sliding_least(values: np.ndarray, window: int) -> np.ndarray:
    """The least of each `window` neighbours."""
    width, least = 1, values
    while 2 * width <= window:
        least = np.minimum(least[: len(least) - width], least[width:])
        width *= 2
    rest = window - width
    return np.minimum(least[: len(least) - rest], least[rest:]) if rest else least


def pieces(raws: list[bytes], length: int = LENGTH, gram: int = GRAM) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """For some texts at a time: hash, number of the text, place, and strings of each piece."""
    at = 0
    while at < len(raws):
        upto, size = at, 0
        while upto < len(raws) and (upto == at or size + len(raws[upto]) <= CHUNK):
            size += len(raws[upto])
            upto += 1
        some = raws[at:upto]
        lengths = np.array(list(map(len, some)), np.int64)
        ends = np.cumsum(lengths)
        text = np.frombuffer(b"".join(some), np.uint8)
        if len(text) >= length:
            grams = gram_hashes(text, gram)
            # the upper bits of the hash, then the place: of equal grams in a string the first one counts
            tags = (grams & ~_PLACES) | (np.arange(len(grams), dtype=np.uint64) & _PLACES)
            least = sliding_least(tags, length - gram + 1)
            strings = np.maximum(lengths - length + 1, 0)
            owner = np.repeat(np.arange(len(some)), strings)
            place = np.repeat(ends - lengths - (np.cumsum(strings) - strings), strings) + np.arange(len(owner))
            if len(place):
                tag = least[place]
                start = np.flatnonzero(np.concatenate([[True], (tag[1:] != tag[:-1]) | (owner[1:] != owner[:-1])]))
                count, who, at_gram = np.diff(np.append(start, len(tag))), owner[start], place[start]
                at_gram = at_gram + ((tag[start] - at_gram.astype(np.uint64)) & _PLACES).astype(np.int64)
                yield grams[at_gram], who + at, place[start] - (ends - lengths)[who], count
        at = upto


ROWS = "key long, kind int, text long, place int, n int"
ALONE, WITNESS, KNOWN = 0, 1, 2


def _recurring(docs: DataFrame, length: int, gram: int) -> DataFrame:
    """Pieces (text, place, strings, hash) whose hash occurs at least twice in the corpus."""

    def cut(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0

        def flush() -> Iterator[pa.RecordBatch]:
            h, text, place, n = (np.concatenate(x) for x in zip(*held, strict=True))
            order = np.argsort(h, kind="stable")
            h, text, place, n = h[order].view(np.int64), text[order], place[order], n[order]
            new = np.concatenate([[True], h[1:] != h[:-1]])
            several = np.diff(np.append(np.flatnonzero(new), len(h)))[np.cumsum(new) - 1] > 1
            yield _batch(h[~several], ALONE, text[~several], place[~several], n[~several])
            yield _batch(h[new & several], WITNESS, text[new & several], place[new & several], n[new & several])
            yield _batch(h[several], KNOWN, text[several], place[several], n[several])

        for batch in batches(rows, 512):
            raws, names = [x or b"" for x in text_bytes(batch.column("text"))], batch.column("th").to_numpy()
            for h, who, place, n in pieces(raws, length, gram):
                held.append((h, names[who], place.astype(np.int32), n.astype(np.int32)))
                size += len(h)
            if size >= FLUSH:
                yield from flush()
                held, size = [], 0
        if size:
            yield from flush()

    def meet(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, several, waiting = None, False, None  # the last key, whether it recurs, and its only row if it may yet
        for batch in rows:
            kind = batch.column("kind").to_numpy()
            if (kind == KNOWN).any():
                yield batch.filter(pa.array(kind == KNOWN))
            batch = batch.filter(pa.array(kind != KNOWN))
            if not batch.num_rows:
                continue
            key, alone = batch.column("key").to_numpy(), batch.column("kind").to_numpy() == ALONE
            if key[0] == last and waiting is not None:
                yield waiting
                waiting = None
            new = np.concatenate([[True], key[1:] != key[:-1]])
            start = np.flatnonzero(new)
            size = np.diff(np.append(start, len(key)))
            if key[0] == last:
                size[0] += 1  # with those of the batch before
            recurs = size > 1
            yield batch.filter(pa.array(recurs[np.cumsum(new) - 1] & alone))
            waiting = batch.slice(len(key) - 1, 1) if not recurs[-1] and alone[-1] else None
            last = key[-1]

    # each hash's rows of all tasks meet; those that are known to recur are already dealt by text
    dealt = docs.select("th", "text").mapInArrow(cut, ROWS)
    deal = F.when(F.col("kind") == KNOWN, F.xxhash64("text", "place")).otherwise(F.col("key"))
    met = dealt.repartition(partitions(docs.sparkSession), deal).sortWithinPartitions("key", "kind")
    return met.mapInArrow(meet, ROWS).select(F.col("text").alias("th"), "place", "n", F.col("key").alias("h"))


def _batch(h: np.ndarray, kind: int, text: np.ndarray, place: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
    return pa.record_batch([pa.array(h), pa.array(np.full(len(h), kind, np.int32)), pa.array(text), pa.array(place), pa.array(n)], names=["key", "kind", "text", "place", "n"])


CONTENT, PLACE, WHOLE, VERDICT, STRING = 0, 1, 2, 3, 4
FOUND = "kind int, h long, piece long, th long, place int, n int, weight long, bytes binary"
_KINDS = (pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.binary())
_NAMES = [x.split()[0] for x in FOUND.split(", ")]


def _found(rows: list[tuple]) -> pa.RecordBatch:
    return pa.record_batch([pa.array(list(x), t) for x, t in zip(zip(*rows, strict=True), _KINDS, strict=True)], names=_NAMES)


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _contents(length: int):
    """Texts with their recurring pieces -> contents of different pieces, and places of pieces."""

    def contents(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches(rows, 1024):
            known: dict[tuple[int, bytes], list] = {}
            for th, raw, copies, hs, places, ns in zip(batch.column("th").to_pylist(), text_bytes(batch.column("text")), batch.column("copies").to_pylist(), *(batch.column(c).to_pylist() for c in ("hs", "places", "ns")), strict=True):
                for h, place, n in zip(hs, places, ns, strict=True):
                    entry = known.setdefault((h, raw[place : place + n + length - 1]), [0, []])
                    entry[0] += copies
                    entry[1].append((th, place, n))
            out = []
            for (h, content), (weight, where) in known.items():
                piece = _signed(xxhash.xxh64_intdigest(content))
                out.append((CONTENT, h, piece, None, None, len(content) - length + 1, weight, content))
                # pieces that stand twice here are removed as a whole, whatever the shard finds
                out += [(WHOLE if weight > 1 else PLACE, h, piece, th, place, n, None, None) for th, place, n in where]
            for at in range(0, len(out), 50_000):
                yield _found(out[at : at + 50_000])

    return contents


def repeated(contents: list[bytes], weights: list[int], length: int = LENGTH) -> list[np.ndarray]:
    """For each piece, which of its strings of `length` bytes occur at least twice in all pieces together."""
    raw = b"\xff".join(contents)
    sizes = np.array(list(map(len, contents)), np.int64)
    starts = np.cumsum(sizes + 1) - sizes - 1
    order = suffix_array(np.frombuffer(raw, np.uint8))
    shared = common_prefixes(raw, order)
    owner = np.searchsorted(starts, order, side="right") - 1
    counts = order + length <= starts[owner] + sizes[owner]  # the string ends inside its piece
    run = np.cumsum(shared[order] < length)
    total = np.bincount(run, np.where(counts, np.array(weights, np.int64)[owner], 0))
    hit = np.zeros(len(raw), bool)
    hit[order[counts & (total[run] > 1)]] = True
    return [hit[a : a + n - length + 1] for a, n in zip(starts.tolist(), sizes.tolist(), strict=True)]


def spans(hit: np.ndarray) -> np.ndarray:
    """Pairs of first and last-but-one of the runs of a mask."""
    edge = np.diff(np.concatenate([[0], hit.astype(np.int8), [0]]))
    return np.stack([np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)], axis=1)


def _sort_shards(length: int):
    """Contents sorted by hash -> verdicts, and strings of hashes that outgrow a shard."""

    def settle(shard: list[tuple]) -> pa.RecordBatch | None:
        hits = repeated([c for _, _, c, _ in shard], [w for *_, w in shard], length)
        out = [(VERDICT, h, piece, None, None, None, None, spans(hit).astype("<i4").tobytes()) for (h, piece, _, _), hit in zip(shard, hits, strict=True) if hit.any()]
        return _found(out) if out else None

    def strings(group: list[tuple]) -> Iterator[pa.RecordBatch]:
        for h, piece, content, weight in group:
            yield _found([(STRING, h, piece, None, i, None, weight, xxhash.xxh3_128_digest(content[i : i + length])) for i in range(len(content) - length + 1)])

    def sort(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard: list[tuple] = []  # complete hashes
        alone: list[tuple] = []  # verdicts on hashes of a single piece
        group: dict[tuple[int, bytes], int] = {}  # the pieces of the current hash, and their numbers
        size, group_size, current, hot = 0, 0, None, False

        def close() -> None:
            nonlocal group, group_size, size
            if len(group) == 1:
                # strings of one piece differ, as the gram stands at another place in each; so all of them
                # recur if the piece does, and none otherwise: a sort could tell no more
                ((piece, content), weight), *_ = group.items()
                if weight > 1:
                    alone.append((VERDICT, current, piece, None, None, None, None, np.array([0, len(content) - length + 1], "<i4").tobytes()))
            else:
                shard.extend((current, p, c, w) for (p, c), w in group.items())
                size += group_size
            group, group_size = {}, 0

        for batch in batches(rows, 4096):
            for h, piece, weight, content in zip(*(batch.column(c).to_pylist() for c in ("h", "piece", "weight", "bytes")), strict=True):
                if h != current:
                    close()
                    current, hot = h, False
                    if size >= SHARD_BYTES:
                        if (out := settle(shard)) is not None:
                            yield out
                        shard, size = [], 0
                if hot:
                    yield from strings([(h, piece, content, weight)])
                elif (piece, content) in group:
                    group[piece, content] += weight
                else:
                    group[piece, content] = weight
                    group_size += len(content)
                    if group_size > HOT_BYTES:
                        yield from strings([(h, p, c, w) for (p, c), w in group.items()])
                        group, group_size, hot = {}, 0, True
            if alone:
                yield _found(alone)
                alone.clear()
        close()
        if alone:
            yield _found(alone)
        if shard and (out := settle(shard)) is not None:
            yield out

    return sort


def _covered(length: int):
    def rows(batches_: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Covered parts of each text: sorted, disjoint pairs of first byte and end."""
        for batch in batches(batches_, 1024):
            out = []
            for places, firsts, lasts in zip(*(batch.column(c).to_pylist() for c in ("places", "ns", "verdicts")), strict=True):
                parts = []
                for place, n, verdict in zip(places, firsts, lasts, strict=True):
                    if verdict is None:
                        parts.append(np.array([[place, place + n + length - 1]], np.int64))
                    else:
                        s = np.frombuffer(verdict, "<i4").reshape(-1, 2).astype(np.int64)
                        parts.append(np.stack([s[:, 0] + place, s[:, 1] + place + length - 1], axis=1))
                s = np.concatenate(parts)
                s = s[np.argsort(s[:, 0], kind="stable")]
                reach = np.maximum.accumulate(s[:, 1])
                new = np.concatenate([[True], s[1:, 0] > reach[:-1]])
                last = np.append(np.flatnonzero(new)[1:], len(s)) - 1
                out.append(np.stack([s[new, 0], reach[last]], axis=1).ravel().tolist())
            yield pa.record_batch([batch.column("th"), pa.array(out, pa.list_(pa.int64()))], names=["th", "spans"])

    return rows


def text_key(text):
    return F.xxhash64(F.coalesce(text, F.lit("")))


def repeated_spans(docs: DataFrame, text: str = "text", length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """th (the hash of a text), spans: its repeated parts as first, end, first, end ... in bytes. Texts without any have no row."""
    spark = docs.sparkSession
    keyed = docs.select(text_key(F.col(text)).alias("th"), F.col(text).alias("text")).where(F.octet_length("text") >= length)
    by_text = _recurring(keyed, length, gram).groupBy("th").agg(F.collect_list(F.struct("h", "place", "n")).alias("x"))
    # one copy of each text, and how many there are; a task's copies are put together before the shuffle
    distinct = keyed.groupBy("th").agg(F.first("text").alias("text"), F.count("*").alias("copies"))
    # rows of equal texts gave equal pieces
    lists = distinct.join(by_text, "th").withColumn("x", F.array_distinct("x")).select("th", "text", "copies", *[F.col(f"x.{c}").alias(d) for c, d in (("h", "hs"), ("place", "places"), ("n", "ns"))])
    # places are kept where they were found; only contents are dealt by their hash
    found = written(lists.mapInArrow(_contents(length), FOUND), "pieces")
    dealt = found.where(F.col("kind") == CONTENT).select("h", "piece", "weight", "bytes").repartition(partitions(spark), "h").sortWithinPartitions("h", "piece")
    settled = written(dealt.mapInArrow(_sort_shards(length), FOUND).select("kind", "h", "piece", "place", "weight", "bytes"), "verdicts")
    whole = found.where(F.col("kind") == WHOLE).select("th", "place", "n", F.lit(None).cast("binary").alias("verdict"))
    verdicts = settled.where(F.col("kind") == VERDICT).select("h", "piece", F.col("bytes").alias("verdict"))
    single = found.where(F.col("kind") == PLACE).select("th", "place", "n", "h", "piece")
    parts = single.join(verdicts, ["h", "piece"]).select("th", "place", "n", "verdict").unionByName(whole)
    strings = settled.where(F.col("kind") == STRING).select("h", "piece", F.col("place").alias("i"), "weight", "bytes")
    if strings.limit(1).count():  # hashes whose pieces outgrew a shard
        twice = strings.groupBy("bytes").agg(F.sum("weight").alias("w")).where("w > 1").select("bytes")
        hot = strings.join(twice, "bytes").select("h", "piece", "i")
        parts = parts.unionByName(single.join(hot, ["h", "piece"]).select("th", (F.col("place") + F.col("i")).alias("place"), F.lit(1).alias("n"), F.lit(None).cast("binary").alias("verdict")))
    together = parts.groupBy("th").agg(F.collect_list(F.struct("place", "n", "verdict")).alias("x")).select("th", *[F.col(f"x.{c}").alias(d) for c, d in (("place", "places"), ("n", "ns"), ("verdict", "verdicts"))])
    return written(together.mapInArrow(_covered(length), "th long, spans array<long>"), "spans")


def _keep(raw: bytes, spans_: list[int]) -> bytes:
    edges = [0, *spans_, len(raw)]
    return b"".join(raw[a:b] for a, b in zip(edges[::2], edges[1::2], strict=True))


def _cut_rows(with_text: bool):
    def rows(batches_: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches(batches_, 512):
            kept = [_keep(raw, s) for raw, s in zip(text_bytes(batch.column("text")), batch.column("spans").to_pylist(), strict=True)]
            if with_text:  # a cut may fall inside a character, whose rest goes as well
                out = pa.array([x.decode("utf-8", "ignore") for x in kept], pa.string())
            else:
                out = pa.array([hashlib.sha256(x).hexdigest() for x in kept], pa.string())
            size = pa.array([sum(s[1::2]) - sum(s[::2]) for s in batch.column("spans").to_pylist()], pa.int64())
            yield pa.record_batch([batch.column("th"), size, pa.array([len(s) // 2 for s in batch.column("spans").to_pylist()], pa.int64()), out], names=["th", "removed", "parts", "out"])

    return rows


def _by_text(docs: DataFrame, text: str, with_text: bool) -> DataFrame:
    """th, removed bytes, removed runs, and what is left of each text with repeated parts (or its SHA-256)."""
    found = repeated_spans(docs, text)
    distinct = docs.select(text_key(F.col(text)).alias("th"), F.col(text).alias("text")).where(F.octet_length("text") >= LENGTH).groupBy("th").agg(F.first("text").alias("text"))
    return distinct.join(found, "th").mapInArrow(_cut_rows(with_text), "th long, removed long, parts long, out string")


def remove_repeated(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs without the repeated parts of their texts: same rows and columns."""
    left = _by_text(docs, text, True).select(F.col("th").alias("_th"), F.col("out").alias("_out"))
    rows = wrapped(docs)
    joined = rows.withColumn("_t", text_key(F.col(f"row.{text}"))).join(left, F.col("_t") == F.col("_th"), "left")
    return joined.select(F.col("row").withField(text, F.coalesce("_out", F.col(f"row.{text}"))).alias("row")).select("row.*")


def op6_suffix_dedup(spark, sf_dir: str) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of every document."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    raw = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", text_key(F.col("text")).alias("th"), F.octet_length(raw).cast("long").alias("n_bytes"), F.sha2(raw.cast("binary"), 256).alias("sha"))
    found = rows.join(_by_text(docs, "text", False), "th", "left")
    return found.select("doc_id", "n_bytes", F.coalesce("removed", F.lit(0)).alias("n_removed"), F.coalesce("parts", F.lit(0)).alias("n_spans"), F.coalesce("out", "sha").alias("kept_sha256"))


#: String by string, for small tables. Bytes are two hexadecimal digits each; strings come from blocks of 200 bytes with
#: the 200 after them.
OP6_SQL = f"""
WITH d AS (SELECT row_number() OVER () AS id, doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
b AS (SELECT id, k, substr(h, k * {2 * LENGTH} + 1, {4 * LENGTH}) AS s FROM d, unnest(range(0, (len(h) + {2 * LENGTH - 1}) // {2 * LENGTH})) u(k)),
p AS (SELECT id, k * {LENGTH} + j AS i, md5(substr(s, 2 * j + 1, {2 * LENGTH})) AS m FROM b, range({LENGTH}) r(j) WHERE len(s) >= 2 * j + {2 * LENGTH}),
c AS (SELECT id, i FROM p WHERE m IN (SELECT m FROM p GROUP BY m HAVING count(*) > 1)),
g AS (SELECT id, i, CASE WHEN i <= lag(i) OVER w + {LENGTH} THEN 0 ELSE 1 END AS fresh FROM c WINDOW w AS (PARTITION BY id ORDER BY i)),
s AS (SELECT id, min(i) AS a, max(i) + {LENGTH} AS z FROM (SELECT id, i, sum(fresh) OVER (PARTITION BY id ORDER BY i) AS run FROM g) GROUP BY id, run),
e AS (SELECT id, [0] || list(z ORDER BY a) AS starts, list(a ORDER BY a) AS ends, sum(z - a) AS removed, count(*) AS n FROM s GROUP BY id)
SELECT doc_id, (len(h) // 2)::BIGINT AS n_bytes, coalesce(removed, 0)::BIGINT AS n_removed, coalesce(n, 0)::BIGINT AS n_spans,
  sha256(unhex(CASE WHEN n IS NULL THEN h ELSE array_to_string(list_transform(range(1, n + 2), lambda q: substr(h, 2 * starts[q] + 1, 2 * (coalesce(ends[q], len(h) // 2) - starts[q]))), '') END)) AS kept_sha256
FROM d LEFT JOIN e USING (id)
"""
