"""Packing of documents into training windows, in their order.

The documents of a partition form one stream of ids. Windows are cut from it by dynamic programming:
the cost of a window is its padding, and each cut costs nothing at a document's end, a little at a
sentence's end, and more inside a sentence. The cheapest last cut before each candidate comes from a
monotone queue over the candidates in reach, so the time is linear in their number. Only what is left
at a partition's end may stay short; it is split at powers of two where that is cheaper than padding.

A null text is the empty document: its end id alone. Very long documents span many windows. Repeated
rows are packed one by one; an empty table gives no piece.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import batches, table
from .idfile import in_order
from .tokens import RankEncoder, byte_alphabet, crc, ready, tokenizer_path

WINDOW = 2048
#: What a cut costs, in padded tokens.
SENTENCE_CUT, INSIDE_CUT = 6, 32
#: Ids that are cut at a time; all windows but the last are then final.
BUFFER_IDS = 1 << 19
#: Candidates inside long stretches without a sentence's end stand so far apart.
STRIDE = 64


def sentence_ends(encoder: RankEncoder) -> np.ndarray:
    """For each id, whether its text ends a sentence: it ends with . ! ? or holds a line feed."""
    vocabulary = encoder.library.library.get_vocab()
    feed, found = byte_alphabet()[10], np.zeros(max(vocabulary.values()) + 1, bool)
    for token, i in vocabulary.items():
        found[i] = token.endswith((".", "!", "?")) or feed in token
    return found


def candidates(ids: np.ndarray, doc_ends: np.ndarray, ender: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where the stream may be cut, and what a cut there costs."""
    soft = np.flatnonzero(ender[ids]) + 1
    near = np.union1d(soft, doc_ends)
    gaps = np.diff(np.concatenate([[0], near]))
    long = np.flatnonzero(gaps > STRIDE)
    inside = [np.arange(near[i] - gaps[i] + STRIDE, near[i], STRIDE) for i in long.tolist()]
    at = np.union1d(near, np.concatenate(inside)) if inside else near
    cost = np.full(len(at), INSIDE_CUT, np.int64)
    cost[np.searchsorted(at, near)] = SENTENCE_CUT
    cost[np.searchsorted(at, doc_ends)] = 0
    return at, cost


def best_cuts(at: np.ndarray, cost: np.ndarray, window: int = WINDOW) -> list[int]:
    """Ends of the windows of least padding plus cut costs; neighbours in `at` are at most `window` apart."""
    ends, costs = at.tolist(), cost.tolist()
    total, back = [0], [-1]  # of candidate i - 1; 0 is the stream's start
    where = [0, *ends]
    queue, level = deque([0]), [0]  # level: total + position, what a window that starts there carries on
    for j, (end, own) in enumerate(zip(ends, costs, strict=True), 1):
        while end - where[queue[0]] > window:
            queue.popleft()
        i = queue[0]
        best = level[i] - end + window + own
        total.append(best)
        back.append(i)
        mine = best + end
        level.append(mine)
        while queue and level[queue[-1]] >= mine:
            queue.pop()
        queue.append(j)
    cuts, j = [], len(ends)
    while j > 0:
        cuts.append(where[j])
        j = back[j]
    return cuts[::-1]


def rest_cuts(size: int, window: int = WINDOW) -> list[int]:
    """Ends of the last windows: powers of two need no padding, but each further cut has its cost."""
    powers = [1 << b for b in range(size.bit_length() - 1, -1, -1) if size >> b & 1]
    if INSIDE_CUT * (len(powers) - 1) < window - size:
        return np.cumsum(powers).tolist()
    return [size]


PIECE = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def pack(docs: DataFrame, vocabulary: str = "byte_bpe_50k.json", end_id: int = 1, window: int = WINDOW, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row a piece: its document, place there, length, checksum, and its sequence and place there."""

    def packed(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encoder = ready(RankEncoder, tokenizer_path(vocabulary))
        ender, end = sentence_ends(encoder), np.array([end_id], "<u4").tobytes()
        sequence = TaskContext.get().partitionId() << 32
        # of the documents in the buffer: key, ids, and how many of its ids are packed already
        keys: list[int | None] = []
        held: list[bytes] = []
        gone, size = 0, 0  # ids of the first document that are packed; ids in the buffer

        def cut(last: bool) -> pa.RecordBatch | None:
            nonlocal sequence, gone, size, keys, held
            raw = memoryview(b"".join(held))[4 * gone :]
            lengths = np.array([len(x) // 4 for x in held], np.int64)
            firsts = np.concatenate([[0], np.cumsum(lengths)[:-1]]) - gone
            doc_ends = firsts + lengths
            ids = np.frombuffer(raw, "<u4")
            ends = best_cuts(*candidates(ids, doc_ends, ender), window)
            if last:
                before = ends[-2] if len(ends) > 1 else 0
                ends = ends[:-1] + [before + x for x in rest_cuts(ends[-1] - before, window)]
            else:
                ends = ends[:-1]
            if not ends:
                return None
            window_ends = np.array(ends, np.int64)
            done = window_ends[-1]
            bounds = np.union1d(window_ends, doc_ends[doc_ends <= done])
            starts = np.concatenate([[0], bounds[:-1]])
            doc = np.searchsorted(doc_ends, starts, side="right")
            seq = np.searchsorted(window_ends, starts, side="right")
            sums = [crc(raw[4 * a : 4 * b]) for a, b in zip(starts.tolist(), bounds.tolist(), strict=True)]
            out = pa.record_batch([pa.array([keys[i] for i in doc.tolist()], pa.int64()), pa.array(starts - firsts[doc]), pa.array(bounds - starts), pa.array(sums, pa.int64()), pa.array(lengths[doc]), pa.array(seq + sequence), pa.array(starts - np.concatenate([[0], window_ends[:-1]])[seq])], names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])
            sequence += len(ends)
            kept = int(np.searchsorted(doc_ends, done, side="right"))
            gone = int(done - firsts[kept]) if kept < len(held) else 0
            size = int(doc_ends[-1] - done)
            keys, held = keys[kept:], held[kept:]
            return out

        for batch in batches(rows, 128, keep=True):
            for doc, ids in zip(batch.column("doc_id").to_pylist(), encoder.many(batch.column("text").to_pylist()), strict=True):
                held.append(ids + end)
                keys.append(doc)
                size += len(held[-1]) // 4
                if size >= BUFFER_IDS and (out := cut(False)) is not None:
                    yield out
        if held and (out := cut(True)) is not None:
            yield out

    return in_order(docs, key, text).mapInArrow(packed, PIECE)


def op10_packing(spark, sf_dir: str) -> DataFrame:
    """doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset of every piece of every document."""
    return pack(table(spark, sf_dir, "documents").select("doc_id", "text"))
