"""Suffix arrays by induced sorting, and permuted common prefixes, on numpy arrays.

Induced sorting classifies suffixes as smaller (S) or larger (L) than their successor, sorts the
leftmost S ones (those after an L), and induces all others from them in one scan for each type.

A scan goes over blocks of neighbouring buckets (first symbols). What a block induces in later blocks is dealt to
them, in order, with a stable sort. Suffixes that a block induces within itself follow, in their bucket, those that
came from before, in the order of the suffixes that induced them; that order is found by repeating a sort as often
as such suffixes follow one another. So each suffix is handled a few times, in array operations, whether buckets
are large or tiny. The scan for S suffixes is that for L ones with symbols turned round.

The order of the leftmost S suffixes is that of the string of their substrings' names, which is found by
the same procedure, level after level, until all names differ. A level has at most half of the symbols of the one
above. An empty string has an empty array; equal suffixes cannot occur, as a shorter one comes first.
"""

from __future__ import annotations

import numpy as np

#: Suffixes in a block of buckets, about; a bucket of more is a block of its own.
BLOCK = 1 << 15


def smaller(text: np.ndarray) -> np.ndarray:
    """Whether each suffix is smaller than its successor; the last one is larger than the empty suffix."""
    n = len(text)
    differs = np.flatnonzero(text[1:] != text[:-1])
    rises = text[differs] < text[differs + 1]
    at = np.searchsorted(differs, np.arange(n))
    return np.append(rises, False)[at]


def _join(parts: list[np.ndarray]) -> np.ndarray:
    return np.concatenate(parts) if parts else np.empty(0, np.int64)


def _narrow(values: np.ndarray, most: int) -> np.ndarray:
    """Values below `most` in a type that numpy sorts fast."""
    return values.astype(np.uint16, copy=False) if most <= 1 << 16 else values


def _blocks(text: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """The block of each symbol, and the symbols where blocks begin and the last one ends."""
    sizes = np.bincount(text, minlength=size)
    large = sizes > BLOCK
    after = np.concatenate([[False], large[:-1]])
    number = (np.cumsum(sizes) - sizes) // BLOCK
    new = np.concatenate([[True], number[1:] != number[:-1]]) | large | after
    return _narrow(np.cumsum(new) - 1, size), np.append(np.flatnonzero(new), size)


def _in_block(text: np.ndarray, low: int, high: int, mine: np.ndarray, came: np.ndarray, seeds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All suffixes of a block in the scan's order, and which of them are seeds."""
    waves, causes, slot, last, last_slots = [], [], len(came) + len(seeds), np.concatenate([came, seeds]), None
    last_slots = np.arange(slot)
    while True:
        live = last > 0
        before, cause = last[live] - 1, last_slots[live]
        live = mine[before] & (text[before] <= high - 1)
        before, cause = before[live], cause[live]
        if not len(before):
            break
        waves.append(before)
        causes.append(cause)
        last, last_slots = before, np.arange(slot, slot + len(before))
        slot += len(before)
    if high - low == 1:  # what came from before, then wave after wave; seeds induce nothing in their own bucket
        order = np.concatenate([came, *waves, seeds])
        return order, np.arange(len(order)) >= len(order) - len(seeds)
    every = np.concatenate([came, seeds, *waves])
    symbols = _narrow(text[every] - low, high - low)
    head, tail, own = np.arange(len(came)), np.arange(len(came), len(came) + len(seeds)), np.arange(len(came) + len(seeds), slot)
    cause, rank = _join(causes), np.empty(slot, np.int64)
    while True:
        slots = np.concatenate([head, own, tail])
        order = slots[np.argsort(symbols[slots], kind="stable")]
        if not len(own):
            break
        rank[order] = np.arange(slot)
        sorted_own = len(came) + len(seeds) + np.argsort(rank[cause], kind="stable")
        if (sorted_own == own).all():
            break
        own = sorted_own
    return every[order], (order >= len(came)) & (order < len(came) + len(seeds))


def _scan(text: np.ndarray, size: int, mine: np.ndarray, seeds: np.ndarray, first: int | None) -> np.ndarray:
    """The suffixes of one type in order, induced by the given seeds of the other one, which stand behind them in each bucket."""
    block_of, edges = _blocks(text, size)
    seeds = seeds[np.argsort(_narrow(text[seeds], size), kind="stable")]
    at = np.searchsorted(text[seeds], edges)
    pending: list[list[np.ndarray]] = [[] for _ in range(len(edges) - 1)]
    if first is not None:
        pending[block_of[text[first]]].append(np.array([first]))
    found = []
    for b in range(len(pending)):
        low, high = int(edges[b]), int(edges[b + 1])
        came, pending[b] = _join(pending[b]), []
        if not len(came) and at[b] == at[b + 1]:
            continue
        order, seed = _in_block(text, low, high, mine, came, seeds[at[b] : at[b + 1]])
        found.append(order[~seed])
        before = order[order > 0] - 1
        before = before[mine[before]]
        before = before[text[before] > high - 1]
        if len(before):
            where = block_of[text[before]]
            dealt = np.argsort(where, kind="stable")
            where, before = where[dealt], before[dealt]
            cuts = np.flatnonzero(np.concatenate([[True], where[1:] != where[:-1], [True]])).tolist()
            for i, j in zip(cuts[:-1], cuts[1:], strict=True):
                pending[where[i]].append(before[i:j])
    return _join(found)


def induce(text: np.ndarray, size: int, is_s: np.ndarray, leftmost: np.ndarray) -> np.ndarray:
    """All suffixes in the order that follows from the given order of the leftmost S suffixes."""
    larger = _scan(text, size, ~is_s, leftmost, len(text) - 1)
    small = _scan(size - 1 - text, size, is_s, larger[::-1], None)[::-1]
    both = np.concatenate([larger, small])  # larger ones stand first in a bucket
    return both[np.argsort(_narrow(text[both], size), kind="stable")]


def _names(text: np.ndarray, is_s: np.ndarray, places: np.ndarray, order: np.ndarray) -> tuple[np.ndarray, int]:
    """Numbers of the substrings from each leftmost S suffix to the next one, equal for equal substrings."""
    n, m = len(text), len(places)
    ends = np.append(places[1:], n)
    length = np.empty(n + 1, np.int64)
    length[places] = ends - places
    a, b = order[:-1], order[1:]
    equal = length[a] == length[b]
    equal &= (a + length[a] < n) & (b + length[b] < n)  # the last one ends with the text and is like no other
    live, k = np.flatnonzero(equal), 0
    while len(live):
        x, y = a[live] + k, b[live] + k
        same = (text[x] == text[y]) & (is_s[x] == is_s[y])
        equal[live[~same]] = False
        live = live[same & (length[a[live]] > k)]
        k += 1
    number = np.empty(n, np.int64)
    number[order] = np.concatenate([[0], np.cumsum(~equal)])
    return number[places], int(m - equal.sum())


def suffix_array(text: np.ndarray, size: int = 256) -> np.ndarray:
    """The suffixes of a string of the symbols 0 to size - 1, in order."""
    text = np.asarray(text).astype(np.min_scalar_type(size - 1))
    n = len(text)
    if n < 2:
        return np.arange(n)
    is_s = smaller(text)
    places = np.flatnonzero(is_s[1:] & ~is_s[:-1]) + 1
    order = induce(text, size, is_s, places)
    if not len(places):
        return order
    marked = np.zeros(n, bool)
    marked[places] = True
    order = order[marked[order]]
    names, count = _names(text, is_s, places, order)
    if count < len(places):
        order = places[suffix_array(names, count)]
    return induce(text, size, is_s, order)


def common_prefixes(raw: bytes, order: np.ndarray) -> np.ndarray:
    """For each place of raw, the length that its suffix shares with the one before it in `order`.

    A suffix whose predecessor in order follows that of its left neighbour shares one symbol less than it;
    so only the others are compared, eight bytes at a time.
    """
    n = len(raw)
    padded = np.frombuffer(raw + bytes(16), np.uint8)
    before = np.full(n, -1, np.int64)
    before[order[1:]] = order[:-1]
    follows = np.zeros(n, bool)
    follows[1:] = (before[1:] > 0) & (before[1:] == before[:-1] + 1) & (before[:-1] >= 0)
    follows[1:] &= padded[: n - 1] == padded[np.maximum(before[1:] - 1, 0)]
    start = np.flatnonzero(~follows & (before >= 0))
    words = np.ndarray((n + 8,), "<u8", buffer=padded, strides=(1,))
    shared = np.zeros(n, np.int64)
    live, k = start, 0
    limit = n - np.maximum(live, before[live])
    while len(live):
        x = words[np.minimum(live + k, n + 7)] ^ words[np.minimum(before[live] + k, n + 7)]
        stop = (x != 0) | (k + 8 >= limit)
        if stop.any():
            low = x[stop] & (~x[stop] + np.uint64(1))
            zeros = np.where(low == 0, 8, np.log2(np.maximum(low, 1).astype(float)).astype(np.int64) // 8)
            shared[live[stop]] = np.minimum(k + zeros, limit[stop])
        live, limit = live[~stop], limit[~stop]
        k += 8
    source = np.maximum.accumulate(np.where(follows, 0, np.arange(n)))
    return np.maximum(shared[source] - (np.arange(n) - source), 0)
