"""Token counts and token ids.

`HeapBpe` counts byte-pair tokens of a text without ever naming an id: symbols sit in a linked
list, a heap yields the adjacent pair of lowest rank, and each merge lowers the count by one.
`ChunkEncoder` gives the ids of the tokenizers library; it cuts a text where the library's own
pre-tokenizer is sure to cut, and asks the library once for each different chunk.

Nulls count as the empty text; texts of any length are handled whole; repeated rows are
treated one by one, and an empty table gives an empty result. Of pairs of equal rank the leftmost one is merged first.
The caller's columns stay together in the struct `row`, so none clashes.
"""

from __future__ import annotations

import heapq
import json
import re
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import KEPT, tidy, wrapped

#: Chunks that each of the two ages of a worker's memory holds; bounds memory, changes no result.
MEMORY = 200_000
CHUNK_MEMORY = 500_000
#: White space beside a blank: only there can a cut before a single blank differ from the pre-tokenizer's.
_BESIDE = re.compile(r" \s|\s ")
#: Runs of white space, of which the byte-level pre-tokenizer keeps some together.
_DOUBLE = re.compile(r"\s\s")
_SAFE = re.compile(r"(?<=\S) (?=\S)")


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def byte_alphabet() -> dict[int, str]:
    """The printable stand-in for each byte in byte-level vocabularies: itself if printable, else the next free code point from 256."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = (b for b in range(256) if b not in set(plain))
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(rest)}


class TwoAges:
    """What is known of chunks: when the young age is full it becomes the old one, whose chunks come back when asked for."""

    def __init__(self, learn):
        self.learn, self.young, self.old = learn, {}, {}

    def all(self, chunks: list[str]) -> list:
        if len(self.young) > MEMORY:
            self.young, self.old = {}, self.young
        young, old = self.young, self.old
        if new := set(chunks).difference(young):
            unknown = []
            for c in new:
                if c in old:
                    young[c] = old[c]
                else:
                    unknown.append(c)
            if unknown:
                young.update(zip(unknown, self.learn(unknown), strict=True))
        return [young[c] for c in chunks]


class HeapBpe:
    """Counts the tokens of a byte-level BPE vocabulary file (.json of the tokenizers library)."""

    def __init__(self, path: str, pattern: str | None = None):
        import public_tokenizers
        import regex

        spec = json.load(open(path, encoding="utf-8"))
        pairs = (m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"])
        raw = {c: b for b, c in byte_alphabet().items()}
        back = lambda s: bytes(raw[c] for c in s)
        self.ranks = {(back(a), back(b)): i for i, (a, b) in enumerate(pairs)}
        self.special = [t["content"] for t in spec["added_tokens"]]
        self.at_special = re.compile("|".join(map(re.escape, sorted(self.special, key=len, reverse=True)))) if self.special else None
        self.words = regex.compile(pattern or public_tokenizers.PATTERN)
        self.single = [bytes([b]) for b in range(256)]
        self.first = TwoAges(lambda chunks: [self.chunk(c) for c in chunks])
        self.after = TwoAges(lambda chunks: [self.chunk(f" {c}") for c in chunks])
        self.pieces: dict[str, int] = {}

    def merges(self, word: bytes) -> int:
        """How many merges a pre-token undergoes."""
        n = len(word)
        if n < 2:
            return 0
        ranks, symbols = self.ranks, [self.single[b] for b in word]
        heap = [(rank, i) for i in range(n - 1) if (rank := ranks.get((symbols[i], symbols[i + 1]))) is not None]
        if not heap:
            return 0
        heapq.heapify(heap)
        following, before, done = list(range(1, n + 1)), list(range(-1, n - 1)), 0
        while heap:
            rank, i = heapq.heappop(heap)
            left = symbols[i]
            if left is None or (j := following[i]) >= n or ranks.get((left, symbols[j])) != rank:
                continue  # one of the two has been merged since
            symbols[i] = joined = left + symbols[j]
            symbols[j] = None
            following[i] = k = following[j]
            done += 1
            if k < n:
                before[k] = i
                if (rank := ranks.get((joined, symbols[k]))) is not None:
                    heapq.heappush(heap, (rank, i))
            if (h := before[i]) >= 0 and (rank := ranks.get((symbols[h], joined))) is not None:
                heapq.heappush(heap, (rank, h))
        return done

    def chunk(self, chunk: str) -> int:
        total, known = 0, self.pieces
        for word in self.words.findall(chunk):
            if (n := known.get(word)) is None:
                raw = word.encode()
                n = known[word] = len(raw) - self.merges(raw)
            total += n
        return total

    def plain(self, text: str) -> int:
        """Tokens of a text without special strings."""
        if not text:
            return 0
        if len(self.pieces) > MEMORY:
            self.pieces = {}
        parts = _SAFE.split(text) if _BESIDE.search(text) else text.split(" ")
        return sum(self.first.all(parts[:1])) + sum(self.after.all(parts[1:]))

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        if self.at_special is None or not self.at_special.search(text):
            return self.plain(text)
        found = len(self.at_special.findall(text))
        return found + sum(map(self.plain, self.at_special.split(text)))


class ChunkEncoder:
    """Ids of the tokenizers library, as little-endian unsigned 32-bit integers in bytes."""

    def __init__(self, path: str):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        spec = json.loads(self.library.to_str())
        #: White space is dropped by the pre-tokenizer, so chunks can end at any blank or line feed.
        self.drops_blanks = "ByteLevel" != (spec["pre_tokenizer"] or {}).get("type")
        if self.drops_blanks:
            kinds = [p["type"] for p in spec["pre_tokenizer"].get("pretokenizers", [])]
            if kinds[:1] != ["Split"] or r"[^\s" not in json.dumps(spec["pre_tokenizer"]).replace("\\\\", "\\"):
                raise ValueError("unknown pre-tokenizer: its chunks can't be told")
        self.lowers = self.drops_blanks and "Lowercase" in json.dumps(spec["normalizer"])
        self.stand_ins = byte_alphabet()
        # between chunks that are asked for together stands what makes one token, and joins none beside it
        self.between = " \x01 " if self.drops_blanks else "\n"
        (self.mark,) = self.library.encode(self.between.strip(" "), add_special_tokens=False).ids
        self.lead = "" if self.drops_blanks else " "
        self.stops = {c: self._alone([c])[0] for c in ".,;:!?"}
        #: Chunks stand for what follows a blank; those that begin with a line feed, for it and what follows.
        self.young: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}

    def _alone(self, chunks: list[str]) -> list[bytes]:
        return [np.array(e.ids, "<u4").tobytes() for e in self.library.encode_batch_fast(chunks, add_special_tokens=False)]

    def _ask(self, chunks: list[str]) -> list[bytes]:
        """Ids of chunks, each after its lead."""
        out: list[bytes] = []
        for at in range(0, len(chunks), 2000):
            some = [c[1:] if c[:1] == "\n" else self.lead + c for c in chunks[at : at + 2000]]
            (found,) = self.library.encode_batch_fast([self.between.join(some)], add_special_tokens=False)
            ids = np.array(found.ids, "<u4")
            ends = np.flatnonzero(ids == self.mark)
            if len(ends) != len(some) - 1:  # a chunk holds the mark itself
                out += self._alone(some)
                continue
            raw = ids.tobytes()
            out += [raw[a:b] for a, b in zip([0, *(4 * ends + 4).tolist()], [*(4 * ends).tolist(), len(raw)], strict=True)]
        return out

    def _stem(self, chunk: str) -> tuple[str, bytes]:
        """A chunk that shares its ids with this one but for a stop at the end; the pre-tokenizer parts letters from stops."""
        if chunk[-1:] in self.stops and chunk[chunk[:1] == "\n" : -1].isalpha():
            return chunk[:-1], self.stops[chunk[-1]]
        return chunk, b""

    def _learn_words(self, chunks: list[str]) -> None:
        """_learn for vocabularies of lower-case words. A word of letters, but for a stop at its end, is a single
        pre-token; if its letters are plain Latin ones, which normal forms leave as they are and whose lower case is
        one letter, it goes straight to the library's model."""
        young, old, stops, model, rest = self.young, self.old, self.stops, self.library.model.tokenize, []
        for c in chunks:
            if (ids := old.get(c)) is not None:
                young[c] = ids
                continue
            stem, stop = c, b""
            if c[-1:] in stops:
                stem, stop = c[:-1], stops[c[-1]]
            if not stem.isalpha() or not stem.isascii() and (max(stem) >= "\u0180" or "\u0130" in stem):
                rest.append(c)
                continue
            stem = stem.lower()
            if (ids := young.get(stem)) is None:
                if (ids := old.get(stem)) is None:
                    shown = stem if stem.isascii() else stem.encode().decode("latin-1").translate(self.stand_ins)
                    ids = array("I", [t.id for t in model(shown)]).tobytes()
                young[stem] = ids
            if c is not stem:
                young[c] = ids + stop
        young.update(zip(rest, self._ask(rest), strict=True))

    def _learn(self, chunks: list[str]) -> None:
        """Puts chunks that the young age lacks there, from the old age or the library."""
        young, old, stems, ask = self.young, self.old, [], {}
        for c in chunks:
            if (ids := old.get(c)) is not None:
                young[c] = ids
                continue
            stem, stop = self._stem(c)
            if stem is not c:
                stems.append((c, stem, stop))
            if stem not in young:
                if (ids := old.get(stem)) is not None:
                    young[stem] = ids
                else:
                    ask[stem] = None
        feed = np.array([self.mark], "<u4").tobytes()
        for stem, ids in zip(ask, self._ask(list(ask)), strict=True):
            young[stem] = feed + ids if stem[:1] == "\n" else ids
        for c, stem, stop in stems:
            young[c] = young[stem] + stop

    def many(self, texts: list[str | None]) -> list[bytes]:
        """Ids of texts, each as one run of bytes."""
        if len(self.young) > CHUNK_MEMORY:
            self.young, self.old = {}, self.young
        if self.drops_blanks:
            cuts = [x.replace("\n", " ").split(" ") if x else [] for x in texts]
        else:
            # single blanks and line feeds: each blank goes with what follows, each feed is a token of its own
            cuts = [f"\n{x}".replace("\n", " \n").split(" ")[1:] if x and not _DOUBLE.search(x) else [] for x in texts]
        distinct: set[str] = set()
        for x in cuts:
            distinct.update(x)
        young, skip, new, local = self.young, 0 if self.drops_blanks else 4, [], {}
        for c in distinct:
            if (ids := young.get(c)) is None:
                new.append(c)
            else:
                local[c] = ids  # small enough to stay in the processor's cache
        if new:
            (self._learn_words if self.lowers else self._learn)(new)
            local.update((c, young[c]) for c in new)
        get = local.__getitem__
        whole = iter(self._alone([t for t, x in zip(texts, cuts, strict=True) if t and not x]))
        return [b"".join(map(get, x))[skip:] if x else next(whole) if text else b"" for text, x in zip(texts, cuts, strict=True)]

    def ids(self, text: str | None) -> bytes:
        return self.many([text])[0]


#: Pre-tokens of more bytes go to the tokenizers library, whose time on them grows more slowly.
LONG_WORD = 20_000


class RankEncoder:
    """The same ids as ChunkEncoder gives for a byte-level vocabulary file, by tiktoken's merger, which is several
    times as fast. It takes tokens for ranks, so it is only built if each merge makes the next id. The first
    text of each call is encoded by the tokenizers library too, and the two must agree."""

    def __init__(self, path: str):
        import public_tokenizers
        import tiktoken

        self.library = ChunkEncoder(path)
        spec = json.load(open(path, encoding="utf-8"))
        vocabulary, raw = spec["model"]["vocab"], {c: b for b, c in byte_alphabet().items()}
        for i, m in enumerate(spec["model"]["merges"]):
            if vocabulary["".join(m if isinstance(m, list) else m.split(" "))] != 256 + i:
                raise ValueError("merges are not in the order of ids")
        special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        ranks = {bytes(raw[c] for c in token): i for token, i in vocabulary.items() if token not in special}
        self.merger = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=special)
        self.long = re.compile(rf"\S{{{LONG_WORD}}}|\s{{{LONG_WORD}}}")

    def many(self, texts: list[str | None]) -> list[bytes]:
        out = []
        for text in texts:
            if not text:
                out.append(b"")
            elif len(text) >= LONG_WORD and self.long.search(text):
                out.append(self.library.ids(text))
            else:
                out.append(self.merger.encode_to_numpy(text, allowed_special="all").astype("<u4").tobytes())
        if texts and out[0] != self.library.ids(texts[0]):
            raise ValueError("the two encoders differ")
        return out


def ready(kind: type, path: str):
    """One counter or encoder for each worker process and file."""
    if (kind, path) not in KEPT:
        KEPT[kind, path] = kind(path)
    return KEPT[kind, path]


def crc(ids: bytes) -> int:
    return zlib.crc32(ids)


def count_tokens(docs: DataFrame, vocabulary: str = "byte_bpe_50k.json", text: str = "text") -> DataFrame:
    """`row` (docs' columns) and n_tokens, the exact token count; other columns stay in the JVM, and nothing is shuffled."""

    @F.arrow_udf(T.LongType())
    def counted(rows: Iterator[pa.Array]) -> Iterator[pa.Array]:
        bpe = ready(HeapBpe, tokenizer_path(vocabulary))
        for texts in rows:
            yield pa.array([bpe.count(x.as_py()) for x in texts], pa.int64())
        tidy()

    return wrapped(docs).select("row", counted(F.col(f"row.{text}")).alias("n_tokens"))


def op4_token_counts(spark, sf_dir: str) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for every document; a null text counts as the empty one."""
    from .common import table

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    n = F.col("n_tokens")
    return count_tokens(docs).select("row.doc_id", F.coalesce(F.octet_length("row.text"), F.lit(0)).cast("long").alias("n_bytes"), n, (n > 512).alias("over_limit"))
