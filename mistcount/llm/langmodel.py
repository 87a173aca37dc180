"""Language-model scores from a log-frequency Bloom filter.

Words (A-Z lowered) and runs of two and three neighbouring words of the training texts are counted exactly; the
counts' levels, 1 + log2, are kept in a Bloom filter: an n-gram is put in once for each level up to its
own. A count is read by probing level after level until one is missing. The filter is cut into slices by
the n-grams' hashes; a slice is filled by one task from the counts of its own n-grams, so no task or driver sees
all of them. A slice is sized by the levels that it holds, which are counted exactly, so that a level that
isn't there is found with a chance of `false_rate` at any size of the corpus; the number of slices grows with
the number of tokens.

The filter grows with the corpus, so it is never gathered and never broadcast. Texts are read once and kept in
chunks, as numbers of the chunk's different words. Each chunk asks each slice for its different n-grams there,
and says how often they stand in its training texts; the answers, a byte each, are brought back to the chunk.
`fit` and `score` do this for texts that are not known together; `fit_and_score` fills and probes each slice in one go.

A token's probability is that of its run of three, smoothed towards that of its pair and that towards the
word's own, by prior weights (PRIORS); a text's first token has no run of three.

The base score needs exact counts of words: slices keep those beside the filter's bits and answer for them too.

Null texts are empty: their end token alone. A null doc_id belongs to the training part. Repeated rows
are scored and counted one by one. A very long text is a chunk of its own. Words are told apart by 64-bit hashes,
n-grams by 32 bits within a slice. An empty table gives an empty result, and with no training text all counts are 0.
Only doc_id and text are read, so other columns of any name do no harm.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import batches, mixed, table, text_bytes, tidy, written

PROBES = 3
LEVELS = 40
#: Chance that a level that isn't in the filter is found.
FALSE_RATE = 0.01
#: Bytes of text in a chunk; n-grams that a slice is asked for, about; least power of two of slices.
CHUNK_BYTES, SLICE_GRAMS, LEAST_BITS = 6_000_000, 1 << 21, 6
#: Weights, in counts, of the word's probability beside the pair's and of the pair's beside that of three words.
PRIORS = (100.0, 20.0)
#: Words that a worker remembers.
MEMORY = 250_000
#: The end token: no UTF-8 text holds this byte.
END = b"\xff"


def held_out(doc_id: Column) -> Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 7 == 2


def tokens(raw: bytes | None) -> list[bytes]:
    words = raw.lower().split() if raw else []
    words.append(END)
    return words


def pair_hash(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    return mixed(mixed(first ^ np.uint64(0x5851F42D4C957F2D)) + second)


class Words:
    """Hashes of the words seen by a worker."""

    def __init__(self):
        self.index: dict[bytes, int] = {}

    def hashes(self, words: list[bytes]) -> np.ndarray:
        if len(self.index) > MEMORY:
            self.index = {}
        index = self.index
        for w in set(words).difference(index):
            index[w] = xxhash.xxh64_intdigest(w)
        return np.fromiter(map(index.__getitem__, words), np.uint64, len(words))


def levels_of(counts: np.ndarray) -> np.ndarray:
    """The number of levels that counts of 1 or more fill."""
    return np.minimum(np.log2(counts).astype(np.int64) + 1, LEVELS)


def slice_size(n_levels: int, false_rate: float = FALSE_RATE) -> int:
    """Bits, a multiple of 8, in which so many levels leave this chance."""
    return 8 * math.ceil(max(n_levels, 8) * -PROBES / math.log(1 - false_rate ** (1 / PROBES)) / 8)


def _positions(cut: np.ndarray, level: int, probe: int, size: int) -> np.ndarray:
    """Places in a slice of this size for the 32 bits of n-grams there."""
    salt = np.uint64((level * PROBES + probe + 1) * 0x9E3779B97F4A7C15 & (1 << 64) - 1)
    return ((mixed(cut.astype(np.uint64) + salt) >> np.uint64(32)) * np.uint64(size)) >> np.uint64(32)


def fill_slice(cut: np.ndarray, counts: np.ndarray, size: int) -> bytes:
    """The bits of a slice that holds these n-grams (32-bit hashes) with these counts."""
    bits = np.zeros(size, bool)
    for level in range(LEVELS):
        cut, counts = (cut, counts) if level == 0 else (cut[counts >= 1 << level], counts[counts >= 1 << level])
        if not len(cut):
            break
        for probe in range(PROBES):
            bits[_positions(cut, level, probe, size)] = True
    return np.packbits(bits, bitorder="little").tobytes()


def probe_slice(bits: np.ndarray, cut: np.ndarray) -> np.ndarray:
    """The highest level that n-grams reach in a slice (uint8); 0 if none."""
    size, levels, alive = 8 * len(bits), np.zeros(len(cut), np.uint8), np.arange(len(cut))
    for level in range(LEVELS):
        for probe in range(PROBES):
            at = _positions(cut[alive], level, probe, size)
            alive = alive[(bits[at >> np.uint64(3)] >> (at & np.uint64(7)).astype(np.uint8)) & 1 == 1]
        if not len(alive):
            break
        levels[alive] = level + 1
    return levels


def split_hash(hashes: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Slice (of 2**bits) and 32-bit hash there of n-grams."""
    return (hashes >> np.uint64(64 - bits)).astype(np.int64), ((hashes >> np.uint64(32 - bits)) & np.uint64(0xFFFFFFFF)).astype(np.uint32)


def planes(values: np.ndarray) -> bytes:
    """Unsigned 32-bit integers with all lowest bytes first, then the next ones: sorted or small ones compress well."""
    return values.astype("<u4").view(np.uint8).reshape(-1, 4).T.tobytes()


def from_planes(raw: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(4, -1).T).view("<u4").ravel()


#: The middle of the range of counts of each level; 0 for none.
MIDDLE = np.concatenate([[0.0], (3 * np.exp2(np.arange(LEVELS)) - 1) / 2])

CHUNK = "uid long, n_tokens long, doc_id array<long>, held_out array<boolean>, trains binary, lengths binary, words binary, ids binary"


def _encode(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Texts as chunks. A chunk's uid is the number of its first text, among those of all tasks."""
    from pyspark import TaskContext

    known, uid, held, size = Words(), TaskContext.get().partitionId() << 40, [], 0

    def chunk() -> pa.RecordBatch:
        doc, out, trains, lengths, h = (list(x) for x in zip(*held, strict=True))
        words, ids = np.unique(np.concatenate(h), return_inverse=True)
        cells = [np.concatenate(trains).astype(np.uint8).tobytes(), np.concatenate(lengths).astype("<u4").tobytes(), words.tobytes(), planes(ids)]
        lists = [pa.array([pa.concat_arrays(x).to_pylist()], pa.list_(t)) for x, t in ((doc, pa.int64()), (out, pa.bool_()))]
        return pa.record_batch([pa.array([uid]), pa.array([len(ids)]), *lists, *(pa.array([c], pa.binary()) for c in cells)], names=[x.split()[0] for x in CHUNK.split(", ")])

    for batch in batches(rows, 256):
        lists = [tokens(x) for x in text_bytes(batch.column("text"))]
        lengths = np.fromiter(map(len, lists), np.int64, len(lists))
        held.append((batch.column("doc_id"), batch.column("held_out"), batch.column("trains").to_numpy(zero_copy_only=False), lengths, known.hashes([w for x in lists for w in x])))
        size += batch.nbytes
        if size >= CHUNK_BYTES:
            yield chunk()
            uid, held, size = uid + sum(len(x[3]) for x in held), [], 0
    if held:
        yield chunk()


def chunks(docs: DataFrame, trains: Column, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """All texts of docs, read and cut into words once; `trains` tells those to learn from."""
    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), held_out(F.col(doc_id)).alias("held_out"), trains.alias("trains"), F.col(text).alias("text"))
    return written(rows.mapInArrow(_encode, CHUNK), "chunks")


def _previous(values: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """What stands before each token; before a text's first one, the end of the text before."""
    before = np.roll(values, 1)
    before[np.cumsum(lengths) - lengths] = values[-1]  # the last token of any text is its end
    return before


class Grams:
    """The n-grams of a chunk: different ones of each order, and which one stands at each token."""

    def __init__(self, words: bytes, ids: bytes, lengths: bytes):
        self.words, self.ids, self.lengths = np.frombuffer(words, "<u8"), from_planes(ids), np.frombuffer(lengths, "<u4").astype(np.int64)
        self.inner = np.ones(len(self.ids), bool)
        self.inner[np.cumsum(self.lengths) - self.lengths] = False
        h = self.words[self.ids]
        pair = pair_hash(_previous(h, self.lengths), h)
        three = pair_hash(mixed(np.roll(pair, 1)[self.inner]), h[self.inner])
        self.pairs, self.pair_at = np.unique(pair, return_inverse=True)
        self.threes, self.three_at = np.unique(three, return_inverse=True)
        every = np.concatenate([self.words, self.pairs, self.threes])
        self.order = np.argsort(every, kind="stable")
        self.asked = every[self.order]

    def slices(self, hashes: np.ndarray, bits: int) -> np.ndarray:
        """Where each slice begins in sorted hashes."""
        return np.searchsorted(hashes, np.arange(1, 1 << bits, dtype=np.uint64) << np.uint64(64 - bits))


ASKED = "uid long, slice long, cut binary, low binary, high binary, words binary, word_counts binary"


def _packed(counts: np.ndarray) -> tuple[bytes, bytes]:
    """Counts as a byte each; those of 255 and more once again, as four bytes."""
    return np.minimum(counts, 255).astype(np.uint8).tobytes(), counts[counts >= 255].astype("<u4").tobytes()


def _unpacked(low: list[bytes], high: list[bytes]) -> np.ndarray:
    counts = np.frombuffer(b"".join(low), np.uint8).astype(np.int64)
    counts[counts == 255] = np.frombuffer(b"".join(high), "<u4")
    return counts


def _ask(bits: int):
    """What each chunk asks each slice for, and how often it stands in the chunk's training texts."""

    def rows(batches_: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches(batches_, 1):
            row = {c: batch.column(c)[0].as_py() for c in ("uid", "trains", "lengths", "words", "ids")}
            g = Grams(row["words"], row["ids"], row["lengths"])
            learns = np.repeat(np.frombuffer(row["trains"], np.uint8), g.lengths) == 1
            single = np.bincount(g.ids[learns], minlength=len(g.words))
            counts = np.concatenate([single, np.bincount(g.pair_at[learns], minlength=len(g.pairs)), np.bincount(g.three_at[learns[g.inner]], minlength=len(g.threes))])[g.order]
            _, cut = split_hash(g.asked, bits)
            edges, word_edges = ([0, *g.slices(x, bits).tolist(), len(x)] for x in (g.asked, g.words))
            out = []
            for s in np.flatnonzero(np.diff(edges)).tolist():
                a, b, c, d = edges[s], edges[s + 1], word_edges[s], word_edges[s + 1]
                out.append((row["uid"], s, planes(cut[a:b]), *_packed(counts[a:b]), g.words[c:d].tobytes(), planes(single[c:d])))
            kinds = (pa.int64(), pa.int64(), *(pa.binary(),) * 5)
            yield pa.record_batch([pa.array(list(x), t) for x, t in zip(zip(*out, strict=True), kinds, strict=True)], names=[x.split()[0] for x in ASKED.split(", ")])

    return rows


def asked(encoded: DataFrame, bits: int) -> DataFrame:
    return encoded.select("uid", "trains", "lengths", "words", "ids").mapInArrow(_ask(bits), ASKED)


def slice_bits(encoded: DataFrame) -> int:
    """Power of two of slices, so that each is asked for about SLICE_GRAMS n-grams at most."""
    n = encoded.agg(F.sum("n_tokens").alias("n")).first()["n"] or 0
    return min(30, max(LEAST_BITS, math.ceil(math.log2(max(1, 3 * n) / SLICE_GRAMS))))


class Asked:
    """All that a slice is asked for."""

    def __init__(self, group: pa.Table):
        self.uid, self.slice = group.column("uid"), group.column("slice")
        cells, words = group.column("cut").to_pylist(), group.column("words").to_pylist()
        self.sizes, self.word_sizes = [len(x) // 4 for x in cells], [len(x) // 8 for x in words]
        self.cut, self.at = np.unique(np.concatenate([from_planes(x) for x in cells]), return_inverse=True)
        self.words, self.word_at = np.unique(np.frombuffer(b"".join(words), "<u8"), return_inverse=True)
        self.group = group

    def slice_row(self, false_rate: float) -> dict:
        """The slice of the model: its filter's bits, and exact counts of words."""
        counts = np.bincount(self.at, _unpacked(self.group.column("low").to_pylist(), self.group.column("high").to_pylist()), len(self.cut))
        words = np.bincount(self.word_at, np.concatenate([from_planes(x) for x in self.group.column("word_counts").to_pylist()]), len(self.words)).astype(np.int64)
        cut, counts = self.cut[counts > 0], counts[counts > 0].astype(np.int64)
        bits = fill_slice(cut, counts, slice_size(int(levels_of(counts).sum()), false_rate))
        return {"bits": bits, "hashes": self.words[words > 0], "counts": words[words > 0]}

    def answers(self, bits: bytes | None, hashes: np.ndarray, counts: np.ndarray) -> pa.Table:
        """Levels of n-grams and exact counts of words, for each chunk; 0 where nothing of it was in a training text."""
        levels = probe_slice(np.frombuffer(bits, np.uint8), self.cut) if bits else np.zeros(len(self.cut), np.uint8)
        exact = np.zeros(len(self.words), np.int64)
        if len(hashes):
            found = np.minimum(np.searchsorted(hashes, self.words), len(hashes) - 1)
            exact = np.where(hashes[found] == self.words, counts[found], 0)
        levels, exact = levels[self.at], exact[self.word_at].astype("<i8")
        cells = [x.tobytes() for x in np.split(levels, np.cumsum(self.sizes)[:-1])]
        more = [x.tobytes() for x in np.split(exact, np.cumsum(self.word_sizes)[:-1])]
        tidy()
        return pa.table({"uid": self.uid, "slice": self.slice, "levels": pa.array(cells, pa.binary()), "counts": pa.array(more, pa.binary())})


MODEL = "slice long, cut_bits int, bits binary, hashes binary, counts binary, n long, v long"
ANSWERS = "uid long, slice long, levels binary, counts binary"


def fit(training: DataFrame, text: str = "text", false_rate: float = FALSE_RATE) -> DataFrame:
    """The model's table: a row a slice."""
    encoded = chunks(training.select(F.lit(None).cast("long").alias("doc_id"), F.col(text).alias("text")), F.lit(True))
    cut_bits = slice_bits(encoded)

    def fill(key: tuple[pa.Scalar, ...], group: pa.Table) -> pa.Table:
        row = Asked(group).slice_row(false_rate)
        cells = [[key[0].as_py()], [cut_bits], [row["bits"]], [row["hashes"].tobytes()], [row["counts"].tobytes()], [int(row["counts"].sum())], [len(row["counts"])]]
        kinds = (pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.int64(), pa.int64())
        return pa.table({c.split()[0]: pa.array(x, t) for c, x, t in zip(MODEL.split(", "), cells, kinds, strict=True)})

    return written(asked(encoded, cut_bits).groupBy("slice").applyInArrow(fill, MODEL), "model")


SCORES = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def _scores(encoded: DataFrame, answers: DataFrame, n: int, v: int) -> DataFrame:
    """Scores of all texts from the answers to their chunks, and the numbers of training tokens and of different ones."""

    def scored(chunk: pa.Table, told: pa.Table) -> pa.Table:
        g = Grams(*(chunk.column(c)[0].as_py() for c in ("words", "ids", "lengths")))
        in_order = sorted(zip(told.column("slice").to_pylist(), told.column("levels").to_pylist(), told.column("counts").to_pylist(), strict=True))
        levels = np.frombuffer(b"".join(x for _, x, _ in in_order), np.uint8)
        exact = np.frombuffer(b"".join(x for _, _, x in in_order), "<i8")
        if len(levels) != len(g.asked) or len(exact) != len(g.words):
            raise ValueError(f"{len(g.asked)} n-grams and {len(g.words)} words asked for, {len(levels)} and {len(exact)} answered")
        about, pairs, threes = (MIDDLE[levels[np.searchsorted(g.asked, x)]] for x in (g.words, g.pairs, g.threes))
        about, pairs, threes, scale = about[g.ids], pairs[g.pair_at], threes[g.three_at], float(n + v + 1)
        chance = (pairs + PRIORS[0] * (about + 1) / scale) / (np.maximum(_previous(about, g.lengths), pairs) + PRIORS[0])
        context = np.maximum(np.roll(pairs, 1)[g.inner], threes)
        chance[g.inner] = (threes + PRIORS[1] * chance[g.inner]) / (context + PRIORS[1])
        firsts = np.cumsum(g.lengths) - g.lengths
        base = np.add.reduceat(np.log10((exact + 1) / scale)[g.ids], firsts)
        known = np.add.reduceat((exact > 0).astype(np.int64)[g.ids], firsts)
        ids, out = (chunk.column(c).combine_chunks().flatten() for c in ("doc_id", "held_out"))
        tidy()
        columns = [ids, out, pa.array(g.lengths), pa.array(known), pa.array(np.full(len(ids), n)), pa.array(base), pa.array(np.add.reduceat(np.log10(chance), firsts))]
        return pa.table(dict(zip([x.split()[0] for x in SCORES.split(", ")], columns, strict=True)))

    return encoded.drop("trains").groupBy("uid").cogroup(answers.groupBy("uid")).applyInArrow(scored, SCORES)


def score(docs: DataFrame, model: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score for every row of docs."""
    total = model.agg(F.sum("n").alias("n"), F.sum("v").alias("v"), F.max("cut_bits").alias("bits")).first()
    encoded = chunks(docs, F.lit(False), doc_id, text)

    def answer(group: pa.Table, filled: pa.Table) -> pa.Table:
        row = filled.to_pylist()[0] if filled.num_rows else {"bits": None, "hashes": b"", "counts": b""}
        if not group.num_rows:
            return pa.table({c.split()[0]: pa.array([], t) for c, t in zip(ANSWERS.split(", "), (pa.int64(), pa.int64(), pa.binary(), pa.binary()), strict=True)})
        return Asked(group).answers(row["bits"], np.frombuffer(row["hashes"], "<u8"), np.frombuffer(row["counts"], "<i8"))

    answers = asked(encoded, total["bits"] or LEAST_BITS).groupBy("slice").cogroup(model.groupBy("slice")).applyInArrow(answer, ANSWERS)
    return _scores(encoded, answers, int(total["n"] or 0), int(total["v"] or 0))


def fit_and_score(docs: DataFrame, trains: Column, doc_id: str = "doc_id", text: str = "text", false_rate: float = FALSE_RATE) -> DataFrame:
    """What score() of docs gives with a model fitted to those rows of them that `trains` tells, with every text read and
    every n-gram shuffled once: a slice is filled and probed by the same task."""
    encoded = chunks(docs, trains, doc_id, text)

    def fill_and_answer(group: pa.Table) -> pa.Table:
        asks = Asked(group)
        row = asks.slice_row(false_rate)
        found = asks.answers(row["bits"], row["hashes"], row["counts"])
        # the slice's numbers of training tokens and of different ones stand in its first row
        sums = [pa.array([int(x), *[0] * (found.num_rows - 1)], pa.int64()) for x in (row["counts"].sum(), len(row["counts"]))]
        return found.append_column("n", sums[0]).append_column("v", sums[1])

    answers = written(asked(encoded, slice_bits(encoded)).groupBy("slice").applyInArrow(fill_and_answer, f"{ANSWERS}, n long, v long"), "answers", free=True)
    total = answers.agg(F.sum("n").alias("n"), F.sum("v").alias("v")).first()
    return _scores(encoded, answers.drop("n", "v"), int(total["n"] or 0), int(total["v"] or 0))


def op8_lm_scoring(spark, sf_dir: str) -> DataFrame:
    """Scores of all documents by a model of those that aren't held out."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return fit_and_score(docs, ~held_out(F.col("doc_id")))
