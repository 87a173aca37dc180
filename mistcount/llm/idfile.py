"""Token ids as files: one concatenated array of ids with Elias-Fano coded document boundaries.

A segment holds some hundred thousand ids of consecutive documents:

    magic "MIDS1" | bytes an id (2 or 4) | documents (u32) | ids (u64) | length of the boundaries (u32)
    | Elias-Fano boundaries | ids, little-endian

The boundaries are the running ends of the documents. Elias-Fano keeps about 2 + log2(ids / documents)
bits for each and finds the i-th by a select on its upper bits, so no table of 64-bit offsets is needed: documents
are read through it, one boundary after the other.
Segments are rows of a table that Spark writes and reads, so that any store that Spark knows can hold
them; `export_segment` and `parse_segment` treat a single one as plain bytes.

A null text counts as empty and still gets its end id. Documents keep the order of doc_id (null first,
ties by a hash of the text); repeated rows are encoded one by one; an empty table gives no segment. A very long text is a
segment of its own. Only doc_id and text are read, so other columns of any name do no harm.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batches, partitions, table, written
from .tokens import ChunkEncoder, crc, ready, tokenizer_path

MAGIC = b"MIDS1"
#: Ids after which a segment is closed; a longer document has a segment to itself.
SEGMENT_IDS = 1 << 20


class EliasFano:
    """A non-decreasing sequence of unsigned integers in near-minimal space."""

    #: Ones of the upper bits between two entries of the select directory.
    STEP = 64
    #: Bytes of the upper bits that a scan looks at together.
    LOOK = 32

    def __init__(self, count: int, low_bits: int, lows: np.ndarray, upper: np.ndarray):
        self.count, self.low_bits, self.lows, self.upper = count, low_bits, lows, upper
        self._directory: np.ndarray | None = None

    @classmethod
    def of(cls, values: np.ndarray) -> EliasFano:
        values = np.asarray(values, np.uint64)
        n = len(values)
        low = max(0, int(values[-1] // max(n, 1)).bit_length() - 1) if n else 0
        bits = ((values[:, None] >> np.arange(low, dtype=np.uint64)) & np.uint64(1)).astype(np.uint8)
        at = (values >> np.uint64(low)).astype(np.int64) + np.arange(n)
        upper = np.zeros(int(at[-1]) + 1 if n else 0, np.uint8)
        upper[at] = 1
        return cls(n, low, np.packbits(bits.ravel(), bitorder="little"), np.packbits(upper, bitorder="little"))

    def to_bytes(self) -> bytes:
        return struct.pack("<IBII", self.count, self.low_bits, len(self.lows), len(self.upper)) + self.lows.tobytes() + self.upper.tobytes()

    @classmethod
    def from_bytes(cls, raw: bytes) -> EliasFano:
        n, low, a, b = struct.unpack_from("<IBII", raw)
        body = np.frombuffer(raw, np.uint8, a + b, struct.calcsize("<IBII"))
        return cls(n, low, body[:a], body[a:])

    def _low(self, i: int) -> int:
        at = i * self.low_bits
        held = int.from_bytes(self.lows[at >> 3 : (at + self.low_bits + 7) >> 3].tobytes(), "little")
        return (held >> (at & 7)) & ((1 << self.low_bits) - 1)

    def _sampled(self) -> np.ndarray:
        """Where each STEP-th one of the upper bits stands; some bytes of them at a time."""
        found, seen = [], 0
        for at in range(0, len(self.upper), 1 << 12):
            ones = np.flatnonzero(np.unpackbits(self.upper[at : at + (1 << 12)], bitorder="little"))
            found.append(ones[-seen % self.STEP :: self.STEP] + 8 * at)
            seen += len(ones)
        return np.concatenate(found) if found else np.empty(0, np.int64)

    def select(self, i: int) -> int:
        """The i-th value, from 0: a directory entry, then a scan of fewer than STEP ones."""
        if not 0 <= i < self.count:
            raise IndexError(i)
        if self._directory is None:
            self._directory = self._sampled()
        at = int(self._directory[i // self.STEP])
        skip, byte = i % self.STEP, at >> 3
        chunk = np.unpackbits(self.upper[byte : byte + self.LOOK], bitorder="little")
        chunk[: at & 7] = 0
        while len(ones := np.flatnonzero(chunk)) <= skip:
            skip, byte = skip - len(ones), byte + self.LOOK
            chunk = np.unpackbits(self.upper[byte : byte + self.LOOK], bitorder="little")
        found = byte * 8 + int(ones[skip])
        return ((found - i) << self.low_bits) | self._low(i)

    def all(self) -> np.ndarray:
        """Every value, unpacked: for checks."""
        ones = np.flatnonzero(np.unpackbits(self.upper, bitorder="little"))[: self.count]
        values = (ones - np.arange(self.count)).astype(np.uint64) << np.uint64(self.low_bits)
        if self.low_bits:
            bits = np.unpackbits(self.lows, bitorder="little")[: self.count * self.low_bits].reshape(self.count, self.low_bits)
            values |= (bits.astype(np.uint64) << np.arange(self.low_bits, dtype=np.uint64)).sum(axis=1, dtype=np.uint64)
        return values


def export_segment(ids: list[bytes]) -> bytes:
    """The file of some documents, whose ids come as little-endian unsigned 32-bit integers."""
    ends = np.cumsum([len(x) // 4 for x in ids], dtype=np.uint64)
    every = np.frombuffer(b"".join(ids), "<u4")
    width = 2 if not len(every) or every.max() < 1 << 16 else 4
    marks = EliasFano.of(ends).to_bytes()
    return MAGIC + struct.pack("<BIQI", width, len(ids), len(every), len(marks)) + marks + every.astype(f"<u{width}").tobytes()


def parse_segment(raw: bytes) -> tuple[EliasFano, np.ndarray]:
    """Document ends, still coded, and ids of a segment."""
    if raw[: len(MAGIC)] != MAGIC:
        raise ValueError("not a segment of token ids")
    width, _, n, size = struct.unpack_from("<BIQI", raw, len(MAGIC))
    at = len(MAGIC) + struct.calcsize("<BIQI")
    return EliasFano.from_bytes(raw[at : at + size]), np.frombuffer(raw, f"<u{width}", n, at + size).astype("<u4")


def in_order(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key and text, range-partitioned and sorted by key; ties by the text's hash."""
    spark = docs.sparkSession
    narrow = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text"), F.xxhash64(text).alias("tie"))
    return narrow.repartitionByRange(partitions(spark), "doc_id", "tie").sortWithinPartitions("doc_id", "tie")


SEGMENT = "part int, seg int, before long, n_ids long, doc_ids array<long>, payload binary"


def encode_segments(docs: DataFrame, vocabulary: str, end_id: int, segment_ids: int = SEGMENT_IDS, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Segments in the order of key: partition, number there, ids before it there, ids, keys, payload."""

    def encode(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encoder, part = ready(ChunkEncoder, tokenizer_path(vocabulary)), TaskContext.get().partitionId()
        end, seg, before, keys, held, size = np.array([end_id], "<u4").tobytes(), 0, 0, [], [], 0

        def close() -> pa.RecordBatch:
            return pa.record_batch([pa.array([part], pa.int32()), pa.array([seg], pa.int32()), pa.array([before], pa.int64()), pa.array([size], pa.int64()), pa.array([keys], pa.list_(pa.int64())), pa.array([export_segment(held)], pa.binary())], names=["part", "seg", "before", "n_ids", "doc_ids", "payload"])

        for batch in batches(rows, 512, keep=True):
            for doc, ids in zip(batch.column("doc_id").to_pylist(), encoder.many(batch.column("text").to_pylist()), strict=True):
                ids += end
                if held and size + len(ids) // 4 > segment_ids:
                    yield close()
                    seg, before, keys, held, size = seg + 1, before + size, [], [], 0
                keys.append(doc)
                held.append(ids)
                size += len(ids) // 4
        if held:
            yield close()

    return in_order(docs, key, text).mapInArrow(encode, SEGMENT)


def read_documents(segments: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens and ids_crc32 of every document in written segments."""
    spark = segments.sparkSession
    # one row a partition of the writer: bounded by the session's number of shuffle partitions
    sums = sorted((r["part"], r["n"]) for r in segments.groupBy("part").agg(F.sum("n_ids").alias("n")).collect())
    firsts, total = [], 0
    for part, n in sums:
        firsts.append((part, total))
        total += n
    bases = spark.createDataFrame(firsts, "part int, base long")

    def decode(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches(rows, 1):
            row = batch.to_pylist()[0]
            ends, ids = parse_segment(row["payload"])
            raw, first, start = memoryview(ids.tobytes()), row["base"] + row["before"], 0
            for at in range(0, ends.count, 1024):
                out = []
                for i in range(at, min(at + 1024, ends.count)):
                    end = ends.select(i)
                    out.append((row["doc_ids"][i], first + start, end - start, crc(raw[4 * start : 4 * end])))
                    start = end
                yield pa.record_batch([pa.array(list(x), pa.int64()) for x in zip(*out, strict=True)], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    joined = segments.join(F.broadcast(bases), "part").select("base", "before", "doc_ids", "payload")
    return joined.mapInArrow(decode, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op5_token_ids(spark, sf_dir: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32, all read back from the written segments."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return read_documents(written(encode_segments(docs, "word_bpe_49k.json", 2), "ids"))
