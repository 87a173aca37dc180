"""N-gram Jaccard join with prefix trees, and the groups that its links form.

A document's set holds the hashes of its distinct three-word shingles. Sets are ordered by hash, which
is one global order; equal sets are one node, whatever the number of their documents.

Finding who may link. Two sets with a Jaccard similarity of at least t differ in few shingles. Each set
is cut by ranges of the hash into so many segments that two such sets have more equal segments than
they can have empty ones, so documents that share no whole segment cannot link. Only the hashes of
segments are shuffled. A task hands on one row for each segment hash it has seen and links further
nodes of it to the first at once, so a segment that many documents share is no hot key. The links form
blocks of sets that may be similar.

At lower similarities segments get so short that a common line fills some, and blocks grow. `bands` is
the other way to find who may link: hashes of BAND_ROWS least values of the set under random orders, BANDS
of them. Two sets of similarity t miss each other with chance (1 - t^BAND_ROWS)^BANDS, at 0.8 less than
4e-9 a pair, so it is for uses that can bear that; what is found is decided exactly in either case.

Deciding who links. Within a block shingles are ordered by the number of its sets that hold them, then
by hash; sets that share too few with any other are done. The rest are put into a prefix tree, one after
the other. Each first looks for partners by walking down the tree: the overlap with a shared prefix is found once for all
sets below it, and a subtree is left when the most that can still overlap is less than its sets need, when
all its sets belong to the walker's group already, or when none of them shares one of its rarest shingles. Every similarity is decided on the sets.
A block of more than BLOCK sets is dealt by size first: partners differ in size by the threshold at most, so only sets of
the same and of neighbouring size classes are compared. Each class is dealt into parts, and pairs of parts are tasks.

Blocks and groups are connected components, found by passing on least labels along tables in the
shared folder until nothing changes.

Null and empty texts have no shingle and no link; a text of one or two words is one shingle. Repeated
rows, and rows of equal shingles, form a group. Rows with a null doc_id are not linked, as they have no
id that a group could bear. Rows that share a doc_id and have other texts are told apart by their texts. Very long
texts are read whole, one at a time, and are sets like others. Only doc_id and text are read for the groups; rows that
stay keep all their columns, whatever their names. An empty table gives an empty result. Sets are told apart by 64-bit hashes.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import batches, mixed, partitions, table, text_bytes, wrapped, written

SHINGLE, PERCENT = 3, 90
#: Ratio of the largest to the smallest set of a size class: about the best between emptier segments and more
#: sets that belong to two classes.
CLASS_RATIO = 1.5
BANDS, BAND_ROWS = 64, 6
_ORDERS = np.random.default_rng(20240229).integers(1, 1 << 32, (2, BANDS * BAND_ROWS), dtype=np.uint32)
#: Sets of one block that one task compares, and shingles in them.
BLOCK, BLOCK_SHINGLES = 2000, 1_000_000
#: Links up to which one task finds the components.
ONE_TASK = 500_000
#: Rows that a task holds before it hands them on; words that a worker remembers.
FLUSH, MEMORY = 500_000, 150_000


class WordHashes:
    """Hashes of words, remembered by the worker."""

    def __init__(self):
        self.known: dict[bytes, int] = {}

    def of(self, words: list[bytes]) -> np.ndarray:
        if len(self.known) > MEMORY:
            self.known = {}
        known = self.known
        for w in set(words).difference(known):
            known[w] = xxhash.xxh64_intdigest(w)
        return np.fromiter(map(known.__getitem__, words), np.uint64, len(words))


def shingle_sets(texts: list[bytes | None], hashes: WordHashes, k: int = SHINGLE) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text."""
    lists = [x.lower().split() if x else [] for x in texts]
    h = hashes.of([w for x in lists for w in x])
    mix = h
    for i in range(1, k):
        mix = mixed(mix[:-1] ^ np.uint64(0x5851F42D4C957F2D)) + h[i:] if len(h) > i else h[:0]
    mix = mixed(mix)
    found, at = [], 0
    for words in lists:
        n = len(words)
        if n >= k:
            s = np.sort(mix[at : at + n - k + 1])
            found.append(s[np.concatenate([[True], s[1:] != s[:-1]])])
        elif n:
            found.append(np.array([xxhash.xxh64_intdigest(b" ".join(words), n)], np.uint64))
        else:
            found.append(np.empty(0, np.uint64))
        at += n
    return found


def set_id(s: np.ndarray) -> int:
    """A signed 64-bit name of a set."""
    return int(np.uint64(xxhash.xxh64_intdigest(s.tobytes(), len(s))).astype(np.int64))


def class_edges(ratio: float = CLASS_RATIO, most: int = 1 << 40) -> np.ndarray:
    """Smallest sizes of the size classes."""
    edges = [1]
    while edges[-1] < most:
        edges.append(max(edges[-1] + 1, int(edges[-1] * ratio)))
    return np.array(edges, np.int64)


_EDGES = class_edges()


def largest_difference(largest: int, percent: int) -> int:
    """Shingles that are in one of two linked sets only, the larger of them of this size: with overlap o and
    union u, o >= u * percent / 100 and o <= the smaller set's size."""
    # for a given larger size the difference is greatest when the union is: u <= 100 * smaller / percent
    return max(a + largest - 2 * o for a in range(max(1, -(-largest * percent // 100)), largest + 1) for o in [-(-percent * (a + largest) // (100 + percent))] if o <= a)


_PLAN: dict[tuple[int, int], tuple[int, int]] = {}


def segments_of(c: int, percent: int) -> tuple[int, int]:
    """Segments of size class c, and how many may be empty before empty ones are compared as well."""
    if (c, percent) not in _PLAN:
        first, largest = int(_EDGES[c]), int(_EDGES[c + 1]) - 1
        if largest > 500:
            d = 2 * largest - 2 * -(-percent * 2 * largest // (100 + percent)) + 1
        else:
            d = max(largest_difference(x, percent) for x in range(first, largest + 1))
        # more segments than differences: enough to do without the empty ones of a usual set
        spare = 2 + math.ceil(1.5 * (d + 1) * math.exp(-first * percent / 100 / (d + 1))) if d else 0
        _PLAN[c, percent] = d + 1 + spare, spare
    return _PLAN[c, percent]


def segment_rows(s: np.ndarray, percent: int) -> np.ndarray:
    """Hashes of a set's segments, in its own size class and, where a larger partner may be in it, the next."""
    n, out = len(s), []
    own = int(np.searchsorted(_EDGES, n, side="right")) - 1
    top = n * 100 // percent  # the largest partner
    for c in range(own, int(np.searchsorted(_EDGES, top, side="right"))):
        # pairs of class c: the smaller set is in the class before or the same, the larger one in it
        m, spare = segments_of(c, percent)
        at = np.searchsorted(s, (np.arange(1, m, dtype=np.float64) * (2.0**64 / m)).astype(np.uint64)) if m > 1 else np.empty(0, np.int64)
        edges = np.concatenate([[0], at, [n]])
        # a running sum of mixed hashes tells a segment's content, its length and number the rest
        sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(mixed(s), dtype=np.uint64)])
        sizes = np.diff(edges).astype(np.uint64)
        rows = mixed(mixed(sums[edges[1:]] - sums[edges[:-1]]) + sizes + np.uint64(0x9E3779B97F4A7C15) * (np.arange(m, dtype=np.uint64) + np.uint64(1)) + (np.uint64(c) << np.uint64(40)))
        if (sizes == 0).sum() <= spare:
            rows = rows[sizes > 0]
        out.append(rows)
    return np.concatenate(out)


def band_rows(s: np.ndarray) -> np.ndarray:
    """Hashes of a set's bands."""
    flips, factors = _ORDERS[0][:, None], (_ORDERS[1] | np.uint32(1))[:, None]
    short = (s >> np.uint64(32)).astype(np.uint32)
    least = np.full(BANDS * BAND_ROWS, 0xFFFFFFFF, np.uint32)
    for at in range(0, len(short), 512):  # some shingles at a time, in the processor's cache
        least = np.minimum(least, ((short[None, at : at + 512] ^ flips) * factors).min(axis=1))
    rows, out = least.reshape(BANDS, BAND_ROWS).astype(np.uint64), np.arange(1, BANDS + 1, dtype=np.uint64)
    for j in range(BAND_ROWS):
        out = mixed(out + rows[:, j])
    return out


#: n tells the rows apart: of a segment, of a link between nodes a and b, and (0 or more) of a document b with
#: so many shingles, whose key is its text's hash. Few and narrow columns, as there is a row for each segment.
ROWS = "key long, a long, b long, n int"
SEGMENT, LINK = -1, -2
#: The seed of Spark's xxhash64, which tells the texts of rows that share a doc_id apart.
TEXT_SEED = 42


def _rows(key, a, n, b=None) -> pa.RecordBatch:
    size = len(a)
    n = np.full(size, n, np.int32) if isinstance(n, int) else n
    return pa.record_batch([pa.array(key, pa.int64()), pa.array(a, pa.int64()), pa.nulls(size, pa.int64()) if b is None else pa.array(b, pa.int64()), pa.array(n, pa.int32())], names=["key", "a", "b", "n"])


def _deal(nodes: np.ndarray) -> np.ndarray:
    return mixed(nodes.view(np.uint64)).view(np.int64)


def _firsts(keys: np.ndarray, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of rows sorted by key and node: one a key, and the distinct links of its other nodes to that one."""
    new = np.concatenate([[True], keys[1:] != keys[:-1]])
    head = nodes[np.maximum.accumulate(np.where(new, np.arange(len(keys)), 0))]
    other = head != nodes
    if other.any():
        links = np.unique(np.stack([head[other], nodes[other]]), axis=1)
    else:
        links = np.empty((2, 0), np.int64)
    return keys[new], nodes[new], links[0], links[1]


def candidates(docs: DataFrame, percent: int, k: int, doc_id: str, text: str, bands: bool = False) -> DataFrame:
    """Rows of documents (node a, doc_id b, n shingles) and of links (nodes a and b that share a segment or band)."""

    def segments(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, keys, nodes, size = WordHashes(), [], [], 0

        def flush() -> Iterator[pa.RecordBatch]:
            k, v = np.concatenate(keys).view(np.int64), np.concatenate(nodes)
            order = np.lexsort((v, k))
            k, v, a, b = _firsts(k[order], v[order])
            del order
            for at in range(0, len(k), 100_000):
                yield _rows(k[at : at + 100_000], v[at : at + 100_000], SEGMENT)
            if len(a):
                yield _rows(_deal(a), a, LINK, b)

        for batch in batches(rows, 256):
            texts = text_bytes(batch.column("text"))
            sets = shingle_sets(texts, hashes, k)
            names = np.array([set_id(s) for s in sets], np.int64)
            yield _rows(np.array([xxhash.xxh64_intdigest(t or b"", TEXT_SEED) for t in texts], np.uint64).view(np.int64), names, np.array(list(map(len, sets)), np.int32), batch.column("doc_id"))
            for i, s in enumerate(sets):
                if len(s) and batch.column("doc_id")[i].is_valid:
                    keys.append(band_rows(s) if bands else segment_rows(s, percent))
                    nodes.append(np.full(len(keys[-1]), names[i]))
                    size += len(keys[-1])
            if size >= FLUSH:
                yield from flush()
                keys, nodes, size = [], [], 0
        if size:
            yield from flush()

    def meet(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last_key, head = None, None  # of the segments before
        for batch in rows:
            segment = batch.column("n").to_numpy() == SEGMENT
            if not segment.all():
                yield batch.filter(pa.array(~segment))
            k, v = (batch.column(c).to_numpy()[segment] for c in ("key", "a"))
            if not len(k):
                continue
            if k[0] == last_key:
                k, v = np.concatenate([[last_key], k]), np.concatenate([[head], v])
            new = np.concatenate([[True], k[1:] != k[:-1]])
            last_key, head = k[-1], v[np.flatnonzero(new)[-1]]
            _, _, a, b = _firsts(k, v)
            if len(a):
                yield _rows(_deal(a), a, LINK, b)

    narrow = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text"))
    dealt = narrow.mapInArrow(segments, ROWS).repartition(partitions(docs.sparkSession), "key").sortWithinPartitions("key", "a")
    return written(dealt.mapInArrow(meet, ROWS).withColumn("key", F.when(F.col("n") >= 0, F.col("key"))), "links")


def _join_all(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    up: dict[int, int] = {}

    def find(x: int) -> int:
        while (y := up.setdefault(x, x)) != x:
            up[x] = x = up[y]
        return x

    for batch in rows:
        for a, b in zip(batch.column("a").to_pylist(), batch.column("b").to_pylist(), strict=True):
            a, b = find(a), find(b)
            if a != b:
                up[max(a, b)] = min(a, b)
    nodes = list(up)
    for at in range(0, len(nodes), 100_000):
        some = nodes[at : at + 100_000]
        yield pa.record_batch([pa.array(some, pa.int64()), pa.array([find(x) for x in some], pa.int64())], names=["node", "label"])


def components(links: DataFrame) -> DataFrame:
    """node, label: the least node that links (a, b) connect each node to. Nodes without links have no row.

    Up to ONE_TASK links, which are counted first, one task joins them; beyond, they are joined in rounds. Each round hooks nodes to their least neighbour and then shortcuts labels; links between nodes of one
    label go, so tables shrink from round to round, and the number of rounds grows with the logarithm of
    the longest path.
    """
    spark = links.sparkSession
    edges = written(links.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a <> b").distinct(), "edges")
    if edges.count() <= ONE_TASK:
        return written(edges.coalesce(1).mapInArrow(_join_all, "node long, label long"), "labels")
    labels = None
    while edges.limit(1).count():
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        hooks = both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("up"))
        hooks = written(hooks, "hooks")
        # two shortcuts: a node takes the label of the node that it is hooked to
        for _ in range(2):
            up = hooks.select(F.col("node").alias("up"), F.col("up").alias("top"))
            hooks = hooks.join(up, "up").select("node", F.col("top").alias("up"))
        hooks = written(hooks, "labels")
        step = hooks.select(F.col("node").alias("label"), "up")
        labels = hooks.withColumnRenamed("up", "label") if labels is None else labels.join(step, "label", "left").select("node", F.coalesce("up", "label").alias("label"))
        labels = written(labels, "labels")
        a = hooks.select(F.col("node").alias("a"), F.col("up").alias("la"))
        b = hooks.select(F.col("node").alias("b"), F.col("up").alias("lb"))
        moved = edges.join(a, "a").join(b, "b").select(F.least("la", "lb").alias("a"), F.greatest("la", "lb").alias("b"))
        edges = written(moved.where("a <> b").distinct(), "edges")
    return labels if labels is not None else spark.createDataFrame([], "node long, label long")


class PrefixTree:
    """Ordered sets in a compressed trie, and the groups that their links form."""

    __slots__ = ("percent", "sets", "names", "group", "root", "links", "leaf", "rare")

    class Node:
        __slots__ = ("path", "kids", "ends", "low", "high", "groups", "parent", "asked")

        def __init__(self, path: np.ndarray, parent=None):
            self.path, self.kids, self.ends, self.parent, self.asked = path, {}, [], parent, -1
            self.low, self.high, self.groups = 1 << 60, 0, set()

    def __init__(self, percent: int):
        self.percent, self.sets, self.names, self.group = percent, [], [], []
        self.root, self.links = self.Node(np.empty(0, np.uint64)), []
        self.leaf: list = []  # the node where each set ends
        self.rare: dict[int, list[int]] = {}  # sets by their first elements

    def find(self, i: int) -> int:
        while self.group[i] != i:
            self.group[i] = i = self.group[self.group[i]]
        return i

    def needs(self, a: int, b: int) -> int:
        return -(-self.percent * (a + b) // (100 + self.percent))

    def add(self, name: int, s: np.ndarray) -> None:
        """Links a set to those similar to it, then stores it."""
        me = len(self.sets)
        self.sets.append(s)
        self.names.append(name)
        self.group.append(me)
        # partners share one of their first elements; only paths to such sets are walked
        first = s[: len(s) - -(-len(s) * self.percent // 100) + 1].tolist()
        if asked := {i for x in first for i in self.rare.get(x, ())}:
            for i in asked:
                node = self.leaf[i]
                while node is not None and node.asked != me:
                    node.asked, node = me, node.parent
            self._walk(me, s)
        self._store(me, s)
        for x in first:
            self.rare.setdefault(x, []).append(me)

    def _walk(self, me: int, s: np.ndarray) -> None:
        n, stack = len(s), [(self.root, 0, 0)]
        least, most = -(-n * self.percent // 100), n * 100 // self.percent
        while stack:
            node, depth, overlap = stack.pop()
            if node.high < least or node.low > most:
                continue
            if len(node.groups) < 8:
                node.groups = {self.find(g) for g in node.groups}
                if node.groups == {self.find(me)}:
                    continue  # all below are in this group already
            if len(node.path):
                at = np.searchsorted(s, node.path)
                overlap += int((s[np.minimum(at, n - 1)] == node.path).sum())
                depth += len(node.path)
                left = n - int(np.searchsorted(s, node.path[-1], side="right"))
                # sets of some size: what overlaps so far and all that is left of either is too little
                if overlap + min(left, node.high - depth) < self.needs(n, max(node.low, least)):
                    continue
            for other in node.ends:
                size = len(self.sets[other])
                if 100 * overlap >= self.percent * (n + size - overlap):
                    a, b = self.find(me), self.find(other)
                    if a != b:
                        self.group[max(a, b)] = min(a, b)
                        self.links.append((self.names[me], self.names[other]))
            stack.extend((kid, depth, overlap) for kid in node.kids.values() if kid.asked == me)

    def _store(self, me: int, s: np.ndarray) -> None:
        node, at = self.root, 0
        while True:
            node.low, node.high = min(node.low, len(s)), max(node.high, len(s))
            node.groups.add(me)
            if len(node.groups) > 64:
                node.groups = {self.find(g) for g in node.groups}
            if at == len(s):
                node.ends.append(me)
                self.leaf.append(node)
                return
            kid = node.kids.get(first := int(s[at]))
            if kid is None:
                kid = node.kids[first] = self.Node(s[at:], node)
                kid.low = kid.high = len(s)
                kid.groups, kid.ends = {me}, [me]
                self.leaf.append(kid)
                return
            size = min(len(kid.path), len(s) - at)
            differ = np.flatnonzero(kid.path[:size] != s[at : at + size])
            same = int(differ[0]) if len(differ) else size
            if same < len(kid.path):  # split the kid's path
                upper = self.Node(kid.path[:same], node)
                upper.low, upper.high, upper.groups = kid.low, kid.high, set(kid.groups)
                kid.path = kid.path[same:]
                upper.kids[int(kid.path[0])], kid.parent = kid, upper
                node.kids[first] = kid = upper
            node, at = kid, at + same


def rare_first(sets: list[np.ndarray], percent: int) -> tuple[list[int], list[np.ndarray]]:
    """The sets that may link, as sorted ranks of their elements: rarer elements come first, ties by value.
    A set that shares too few elements with the others for any partner is left out."""
    kept = list(range(len(sets)))
    while len(kept) > 1:
        sizes = np.array([len(sets[i]) for i in kept])
        values, which, times = np.unique(np.concatenate([sets[i] for i in kept]), return_inverse=True, return_counts=True)
        ends = np.cumsum(sizes)
        shared = np.add.reduceat((times[which] > 1).astype(np.int64), ends - sizes)
        least = -(-sizes * percent // 100)
        fit = shared >= -(-percent * (sizes + least) // (100 + percent))
        if fit.all():
            rank = np.empty(len(values), np.int64)
            rank[np.lexsort((values, times))] = np.arange(len(values))
            return kept, [np.sort(x) for x in np.split(rank[which], ends[:-1])]
        kept = [i for i, f in zip(kept, fit.tolist(), strict=True) if f]
    return [], []


def _decide(percent: int):
    def decide(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, block = [], None

        def settle() -> Iterator[pa.RecordBatch]:
            kept, sets = rare_first([np.frombuffer(s, np.uint64) for _, s in held], percent)
            tree = PrefixTree(percent)
            for i, s in zip(kept, sets, strict=True):
                tree.add(held[i][0], s)
            if tree.links:
                yield pa.record_batch([pa.array([a for a, _ in tree.links], pa.int64()), pa.array([b for _, b in tree.links], pa.int64())], names=["a", "b"])

        for batch in batches(rows, 256):
            for key, part, node, s in zip(*(batch.column(c).to_pylist() for c in ("block", "part", "node", "s")), strict=True):
                if (key, part) != block:
                    yield from settle()
                    held, block = [], (key, part)
                if not held or held[-1][0] != node:  # rows that repeat a doc_id and text give the same set, one after the other
                    held.append((node, s))
        yield from settle()

    return decide


PLACED = "block long, class int, parts int, parts_before int, parts_after int"


def _sets(k: int):
    def rows(batches_: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, same = WordHashes(), [x.split()[0] for x in PLACED.split(", ")]
        for batch in batches(batches_, 256):
            sets = shingle_sets(text_bytes(batch.column("text")), hashes, k)
            yield pa.record_batch([*(batch.column(c) for c in same), batch.column("node"), pa.array([s.tobytes() for s in sets], pa.binary()), pa.array([len(s) for s in sets], pa.int32())], names=[*same, "node", "s", "n"])

    return rows


def linked(docs: DataFrame, percent: int = PERCENT, k: int = SHINGLE, doc_id: str = "doc_id", text: str = "text", bands: bool = False) -> tuple[DataFrame, DataFrame]:
    """node, doc_id, text_hash, n (shingles) of every row; and for each node with shingles and a doc_id, which is a set of
    shingles, its label, equal within a group, and its first row (doc_id, text_hash)."""
    spark = docs.sparkSession
    met = candidates(docs, percent, k, doc_id, text, bands)
    members = met.where("n >= 0").select(F.col("a").alias("node"), F.col("b").alias("doc_id"), F.col("key").alias("text_hash"), "n")
    # one document for each set: the least id, and of its texts the least hash
    named = members.where("n > 0 and doc_id is not null").groupBy("node").agg(F.min(F.struct("doc_id", "text_hash")).alias("first"), F.first("n").alias("n"))
    blocks = components(met.where(F.col("n") == LINK).select("a", "b").distinct())
    # sets of a block are dealt into size classes of which only neighbouring ones can hold partners
    within = F.floor(F.log("n") / math.log(100 / percent) + 1e-9).cast("int") if percent < 100 else F.col("n")
    placed = written(blocks.join(named, "node").select("node", F.col("label").alias("block"), F.col("first.doc_id").alias("_doc"), F.col("first.text_hash").alias("_hash"), "n", within.alias("class")), "placed")
    whole = placed.groupBy("block").agg(F.count("*").alias("all"), F.sum("n").alias("shingles")).where((F.col("all") > BLOCK) | (F.col("shingles") > BLOCK_SHINGLES))
    classes = placed.join(whole, "block").groupBy("block", "class").agg(F.ceil(F.greatest(2 * F.count("*") / BLOCK, 2 * F.sum("n") / BLOCK_SHINGLES)).cast("int").alias("parts"))
    after = classes.select("block", (F.col("class") - 1).alias("class"), F.col("parts").alias("parts_after"))
    before = classes.select("block", (F.col("class") + 1).alias("class"), F.col("parts").alias("parts_before"))
    plan = classes.join(after, ["block", "class"], "left").join(before, ["block", "class"], "left")
    # never by broadcast, as blocks grow with the corpus
    wanted = placed.join(plan.hint("merge"), ["block", "class"], "left")
    # one document for each set of a block, whose text is read again
    rows = docs.select(F.col(doc_id).cast("long").alias("_doc"), F.xxhash64(F.coalesce(F.col(text), F.lit(""))).alias("_hash"), F.col(text).alias("text")).join(written(wanted, "blocks").hint("merge"), ["_doc", "_hash"])
    sets = rows.select("block", "class", "parts", "parts_before", "parts_after", "node", "text").mapInArrow(_sets(k), f"{PLACED}, node long, s binary, n int")
    dealt = sets.withColumn("part", F.explode(_tasks())).repartition(partitions(spark), "block", "part").sortWithinPartitions("block", "part", "n", "node")
    links = written(dealt.select("block", "part", "node", "s").mapInArrow(_decide(percent), "a long, b long"), "similar")
    labels = components(links)
    return members, named.drop("n").join(labels, "node", "left").withColumn("label", F.coalesce("label", "node"))


def _tasks() -> Column:
    """The tasks that compare a set: one for a block of a single part; else those of its part with each part of its own
    size class, of the class before and of the one after. A task is named by the class of its smaller sets and two parts."""
    mine = F.pmod(F.xxhash64("node"), F.col("parts")).cast("int")
    name = lambda which, i, j, same: F.xxhash64(which, i, j, F.lit(same))
    own = F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda j: name(F.col("class"), F.least(mine, j), F.greatest(mine, j), 1))
    none = F.array().cast("array<bigint>")
    up = F.when(F.col("parts_after").isNull(), none).otherwise(F.transform(F.sequence(F.lit(0), F.col("parts_after") - 1), lambda j: name(F.col("class"), mine, j, 0)))
    down = F.when(F.col("parts_before").isNull(), none).otherwise(F.transform(F.sequence(F.lit(0), F.col("parts_before") - 1), lambda j: name(F.col("class") - 1, j, mine, 0)))
    return F.when(F.col("parts").isNull(), F.array(F.lit(0).cast("long"))).otherwise(F.concat(own, up, down))


def groups(docs: DataFrame, percent: int = PERCENT, k: int = SHINGLE, doc_id: str = "doc_id", text: str = "text", bands: bool = False) -> DataFrame:
    """doc_id, n_shingles, component_id of every row: the least doc_id of its group."""
    members, nodes = linked(docs, percent, k, doc_id, text, bands)
    least = nodes.groupBy("label").agg(F.min("first.doc_id").alias("component"))
    found = members.join(nodes.join(least, "label").select("node", "component"), "node", "left")
    component = F.when(F.col("doc_id").isNotNull(), F.when(F.col("n") > 0, F.coalesce("component", "doc_id")).otherwise(F.col("doc_id")))
    return found.select("doc_id", F.col("n").cast("long").alias("n_shingles"), component.alias("component_id"))


def one_of_each(docs: DataFrame, percent: int = PERCENT, k: int = SHINGLE, doc_id: str = "doc_id", text: str = "text", bands: bool = False) -> DataFrame:
    """The rows of docs that are the first of their group, with the columns of docs: the least doc_id, and of rows with
    that id and other texts the least text hash. Of rows that repeat that id and text the one whose row has the least hash stays.
    Rows without a shingle are in no group; repeated ones are treated in the same way. Rows with a null doc_id stay."""
    members, nodes = linked(docs, percent, k, doc_id, text, bands)
    alone = members.where("doc_id is not null and n = 0").select("doc_id", "text_hash")
    first = nodes.groupBy("label").agg(F.min("first").alias("x")).select("x.*")
    first = alone.unionByName(first).select(F.col("doc_id").alias("_first"), F.col("text_hash").alias("_first_hash")).distinct()
    mine = wrapped(docs).withColumn("_id", F.col(f"row.{doc_id}").cast("long")).withColumn("_hash", F.xxhash64(F.coalesce(F.col(f"row.{text}"), F.lit(""))))
    kept = mine.join(first, (F.col("_id") == F.col("_first")) & (F.col("_hash") == F.col("_first_hash")), "left_semi")
    # maps can't be hashed, their text can
    whole = F.xxhash64(F.to_json("row")) if "map<" in docs.schema.simpleString() else F.xxhash64("row")
    kept = kept.groupBy("_id", "_hash").agg(F.min_by("row", whole).alias("row"))
    return kept.select("row").unionByName(mine.where("_id is null").select("row")).select("row.*")


def op9_jaccard_join(spark, sf_dir: str) -> DataFrame:
    """doc_id, n_shingles, component_id of every document."""
    return groups(table(spark, sf_dir, "documents").select("doc_id", "text"))


#: Pair by pair, for small tables.
OP9_SQL = rf"""
WITH RECURSIVE d AS (
  SELECT row_number() OVER () AS id, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents
),
s AS (
  SELECT DISTINCT id, concat_ws(' ', ws[i], ws[i + 1], ws[i + 2]) AS s FROM d, unnest(range(1, greatest(len(ws) - 1, 1))) u(i)
  UNION ALL SELECT id, array_to_string(ws, ' ') FROM d WHERE len(ws) IN (1, 2)
),
n AS (SELECT id, count(*) AS n FROM s GROUP BY id),
o AS (SELECT a.id AS x, b.id AS y, count(*) AS o FROM s a JOIN s b ON a.s = b.s AND a.id < b.id GROUP BY 1, 2),
l AS (SELECT x, y FROM o JOIN n a ON a.id = x JOIN n b ON b.id = y WHERE 100 * o >= {PERCENT} * (a.n + b.n - o)),
e AS (SELECT x, y FROM l UNION ALL SELECT y, x FROM l),
r AS (SELECT id, id AS other FROM d UNION SELECT r.id, e.y FROM r JOIN e ON e.x = r.other)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, min(o.doc_id) AS component_id FROM d LEFT JOIN n USING (id) JOIN r USING (id) JOIN d o ON o.id = r.other GROUP BY d.id, d.doc_id, n.n
"""
