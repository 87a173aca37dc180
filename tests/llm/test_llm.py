"""The corpus operators against brute force, on small made cases."""

import hashlib
import math
import random
import time
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from mistcount.llm import common, idfile, jaccard, langmodel, licenses, mixing, packing, quality, substrings, suffixes, tokens, topk

random.seed(5)
WORDS = [f"{a}{b}" for a in ("ka", "lo", "mi", "ru", "te", "zo") for b in ("n", "s", "ra", "vel", "dor", "x")]


def prose(n, seed):
    r = random.Random(seed)
    return " ".join(r.choice(WORDS) + r.choice(["", "", "", ".", ","]) for _ in range(n))


LONG = prose(4000, 99)
CASES = [
    None, "", " ", "\n\n", "one", "two words", "a  b   c \n d", "<|endoftext|>x <|startoftext|> y", prose(80, 1), prose(80, 1), prose(80, 1) + " tail", prose(120, 2) + "\n" + prose(60, 1), LONG,
    "same line here\n" * 30, "aaaa " * 200, "é" * 300 + " 漢字 İstanbul K", "Released under the MIT License. See CC BY 4.0 and cc-by; Apache License!", prose(300, 7), prose(300, 7).replace("kan", "kon", 3), "x" * 3000,
]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, f"src{i % 3}" if i % 5 else None, "extra", i) for i, t in enumerate(CASES)]
    # clashing and extra columns, which must do no harm
    return spark.createDataFrame(rows, "doc_id long, text string, source string, kind string, size long").cache()


@pytest.fixture(scope="module")
def empty(docs):
    return docs.where("doc_id < 0")


def texts():
    return {i: t or "" for i, t in enumerate(CASES)}


def library(name):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(tokens.tokenizer_path(name))


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_chunked_encoding_is_the_librarys(name):
    lib, mine = library(name), tokens.ChunkEncoder(tokens.tokenizer_path(name))
    got = mine.many(list(CASES))
    for t, ids in zip(CASES, got, strict=True):
        assert np.frombuffer(ids, "<u4").tolist() == lib.encode(t or "", add_special_tokens=False).ids


def test_rank_encoder_and_heap_counts_are_the_librarys():
    lib = library("byte_bpe_50k.json")
    path = tokens.tokenizer_path("byte_bpe_50k.json")
    ranks, heap = tokens.RankEncoder(path), tokens.HeapBpe(path)
    for t, ids in zip(CASES, ranks.many(list(CASES)), strict=True):
        want = lib.encode(t or "", add_special_tokens=False).ids
        assert np.frombuffer(ids, "<u4").tolist() == want
        assert heap.count(t) == len(want)


def test_memory_that_overflows_changes_nothing(monkeypatch):
    monkeypatch.setattr(tokens, "CHUNK_MEMORY", 3)
    lib, mine = library("word_bpe_49k.json"), tokens.ChunkEncoder(tokens.tokenizer_path("word_bpe_49k.json"))
    for t in CASES * 2:
        assert np.frombuffer(mine.ids(t), "<u4").tolist() == lib.encode(t or "", add_special_tokens=False).ids


def test_token_counts(docs, empty):
    lib = library("byte_bpe_50k.json")
    clashing = docs.withColumns({"n_tokens": F.lit("x"), "row": F.lit("y")})
    rows = tokens.count_tokens(clashing).collect()
    assert {(r["row"]["n_tokens"], r["row"]["row"]) for r in rows} == {("x", "y")}
    got = {r["row"]["doc_id"]: r["n_tokens"] for r in rows}
    assert got == {i: len(lib.encode(t, add_special_tokens=False).ids) for i, t in texts().items()}
    assert tokens.count_tokens(empty).count() == 0


# --- 1


def test_top_k_with_ties_repeats_and_bad_vectors(spark):
    r = random.Random(3)
    rows = [(i, [float(r.randrange(-3, 4)) for _ in range(6)]) for i in range(120)]
    rows += [(200 + i, [1.0] * 6) for i in range(40)] + [(5, rows[5][1]), (300, None), (301, [1.0, None, 0.0, 0.0, 0.0, 0.0]), (302, [math.inf] * 6), (None, [1.0] * 6), (303, [1.0])] + [(250, [3.0] * 6)] * 30
    df = spark.createDataFrame(rows, "vec_id long, vec array<double>").repartition(5)
    got = defaultdict(list)
    for x in topk.top_k(df, df.where("vec_id % 10 = 0")).orderBy("query_id", "rank").collect():
        got[x["query_id"]].append((x["vec_id"], x["score"]))
    good = {i: v for i, v in rows if i is not None and v and len(v) == 6 and all(x is not None and math.isfinite(x) for x in v)}
    for q in [i for i in good if i % 10 == 0]:
        want = sorted(((i, int(np.dot(v, good[q]))) for i, v in good.items() if i != q), key=lambda x: (-x[1], x[0]))[:5]
        assert got[q] == want
    assert set(got) == {i for i in good if i % 10 == 0}
    assert topk.top_k(df.where("vec_id < 0"), df.where("vec_id < 0")).count() == 0
    few = df.where("vec_id in (0, 1, 10)")
    assert topk.top_k(few, few.where("vec_id = 0")).count() == 2


@pytest.mark.parametrize("spread", [0.0, 1.0, 3.0])
def test_survivors_hold_all_answers(spread):
    """Rows that may be answers are scored exactly; where norms differ much, later lists are read for fewer rows."""
    r = np.random.default_rng(6)
    v = np.floor(r.normal(size=(900, 32)) * 256 * np.exp(spread * r.normal(size=(900, 1))))
    q, edges = v[::100], np.array([0, 8, 16, 24, 32])
    parts = np.stack([q[:, a:b] @ v[:, a:b].T for a, b in zip(edges[:-1], edges[1:], strict=True)])
    low, exact = parts.min(axis=2).T, parts.sum(axis=0)
    fifth = np.sort(exact, axis=1)[:, -5]
    total, alive, read = topk.survivors(q, v, edges, low, fifth - low.sum(axis=1), np.ones(exact.shape, bool))
    assert (alive >= (exact >= fifth[:, None])).all() and (total[alive] == exact[alive]).all()
    assert read[0] == 1 and (read[-1] < 0.5 if spread == 3.0 else True)


@pytest.mark.parametrize("block", [3, 4096])
def test_blocks_of_queries_change_no_result(spark, monkeypatch, block):
    monkeypatch.setattr(topk, "QUERY_BLOCK", block)
    r = random.Random(4)
    rows = [(i, [float(r.randrange(-9, 9)) for _ in range(8)]) for i in range(60)]
    df = spark.createDataFrame(rows, "vec_id long, vec array<double>").repartition(3)
    got = sorted(tuple(x) for x in topk.top_k(df, df.where("vec_id % 5 = 0")).collect())
    want = []
    for q in range(0, 60, 5):
        best = sorted(((i, int(np.dot(v, rows[q][1]))) for i, v in rows if i != q), key=lambda x: (-x[1], x[0]))[:5]
        want += [(q, n, i, s) for n, (i, s) in enumerate(best, 1)]
    assert got == sorted(want)


# --- 2


def plain_stats(t):
    words = (t or "").encode().split()
    again, n = Counter(zip(words, words[1:], words[2:], strict=False)), len(words)
    covered = {j for i in range(n - 2) if again[tuple(words[i : i + 3])] > 1 for j in range(i, i + 3)}
    lines = [x for x in (t or "").split("\n") if x.encode().split()]
    return n, sum(len(w.decode()) for w in words), sum((t or "").count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(covered)


def test_quality_measures_and_verdicts(docs, empty):
    names = ("_host", "_stats", "stats", "host", "host_rate", "host_verdict", "kept", "row", "_salt")
    for r in quality.judge(docs.withColumns({c: F.lit(c) for c in names})).collect():
        assert all(r["row"][c] == c for c in names)
        s = r["stats"]
        want = plain_stats(CASES[r["row"]["doc_id"]])
        assert (s["n_words"], s["word_chars"], s["n_symbols"], s["n_dup_lines"], s["n_repeat_words"]) == want
        if want[0] < 50 or 100 * want[4] > 50 * want[0]:
            assert not r["kept"]
    assert quality.quality_filter(empty).count() == 0
    assert quality.quality_filter(docs).columns == docs.columns


@pytest.mark.parametrize("limit", [0, 200_000])
def test_verdicts_by_broadcast_and_by_salted_join(spark, monkeypatch, limit):
    """The registered query over a whole table, against brute force."""
    monkeypatch.setattr(quality, "BROADCAST_HOSTS", limit)
    sf = "/root/testdata/sf0.001"
    rows = common.table(spark, sf, "documents").collect()
    kept = set(brute_quality({r["doc_id"]: r["text"] for r in rows}, {r["doc_id"]: r["source"] for r in rows}))
    got = quality.op2_quality_rules(spark, sf).collect()
    assert len(got) == len(rows) and {r["doc_id"] for r in got if r["kept"]} == kept
    for r in got:
        want = plain_stats(next(x["text"] for x in rows if x["doc_id"] == r["doc_id"]))
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == want


def test_hosts_are_shrunk_and_bad_ones_blocked(spark):
    rows = [("bad", True)] * 400 + [("good", False)] * 395 + [("good", True)] * 5 + [("tiny", True)] + [(None, False)] * 50
    got = {r["host"]: r for r in quality.host_verdicts(spark.createDataFrame(rows, "host string, failed boolean")).collect()}
    assert got["bad"]["host_verdict"] == "blocked" and got["good"]["host_verdict"] == "trusted" and got[None]["host_verdict"] == "trusted"
    assert 0.3 < got["tiny"]["host_rate"] < 1.0  # one failure is shrunk towards the rest
    assert got["tiny"]["host_verdict"] != "blocked"


# --- 3


def test_license_scan(spark, docs, empty):
    r = {x["doc_id"]: x for x in licenses.scan(docs).collect()}[16]
    assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"]) == (15, 4, 3, 13, "apache,cc-by,mit")
    assert "mit-release" in r["labels"].split(",") and r["score"] == 1.0
    grant = "permission is hereby granted, free of any charge, to any person obtaining a copy of this software and the associated documentation files"
    twice = spark.createDataFrame([(1, grant), (1, grant), (1, "other"), (None, None), (2, "cc by cc by"), (3, "gnu general publicK license")], "doc_id long, text string")
    got = licenses.scan(twice).collect()
    assert sorted((x["doc_id"] or 0, x["labels"]) for x in got) == [(0, ""), (1, ""), (1, "mit-grant"), (1, "mit-grant"), (2, "cc-by"), (3, "")]
    assert [x["n_base"] for x in got if x["doc_id"] == 2] == [2]
    assert licenses.scan(empty).count() == 0 and licenses.scan(docs).count() == len(CASES)


def test_whole_license_texts_are_found(spark):
    texts_ = dict(licenses.TEXTS)
    assert min(len(t.split()) for t in texts_.values()) > 65
    rows = [(i, f"{prose(30, i)} {t.title()} {prose(20, i)}") for i, t in enumerate(texts_.values())]
    words = texts_["mit-text"].split()
    rows.append((10, " ".join(words[:60] + ["added"] + words[60:100] + words[102:])))  # a word more and two fewer
    rows.append((11, " ".join(words[: len(words) // 2])))  # half of it is not the license
    rows.append((12, " ".join(words[:70] + ["x"] * 400 + words[70:])))
    long = tuple((True, "all", t) for label, t in licenses.TEXTS if label == "mit-text")
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: r for r in licenses.scan(df).collect()}
    for i, label in enumerate(texts_):
        assert label in got[i]["labels"].split(",") and got[i]["score"] == 1.0
        assert {x for x in got[i]["labels"].split(",") if x.endswith("-text")} == {label}
    assert "mit-text" in got[10]["labels"] and 0.9 < got[10]["score"] <= 1
    assert "mit-text" not in got[11]["labels"] and "mit-text" not in got[12]["labels"]
    # a phrase of over 65 words: all places, on one diagonal
    bases = {r["doc_id"]: (r["n_base"], r["first_word"]) for r in licenses.scan(df, known=long).collect()}
    assert bases[list(texts_).index("mit-text")] == (1, 30) and bases[10] == (0, None) and bases[11] == (0, None)


# --- 5


def test_elias_fano():
    for values in ([], [0], [0, 0, 0], [5], list(range(0, 3000, 3)), [1, 1, 2, 1000000, 1000000], sorted(random.choices(range(1 << 33), k=700))):
        x = idfile.EliasFano.from_bytes(idfile.EliasFano.of(np.array(values, np.uint64)).to_bytes())
        assert x.all().tolist() == values
        assert [x.select(i) for i in range(len(values))] == values
    dense = np.sort(np.random.default_rng(1).integers(0, 200_000, 100_000)).astype(np.uint64)  # of several pieces of the directory
    assert [idfile.EliasFano.of(dense).select(i) for i in range(0, 100_000, 97)] == dense[::97].tolist()
    for values in ([], [7], [1, 1, 2, 1000000, 1000000], sorted(random.choices(range(1 << 33), k=700))):
        x = idfile.EliasFano.of(np.array(values, np.uint64))
        if len(values) > 100:
            assert len(x.to_bytes()) < 8 * len(values)


def test_id_files_read_back(spark, docs, empty):
    lib, start = library("word_bpe_49k.json"), 0
    for small in (1, 1 << 20):
        segments = common.written(idfile.encode_segments(docs, "word_bpe_49k.json", 2, small), "t")
        start = 0
        for r in sorted(idfile.read_documents(segments).collect(), key=lambda r: r["doc_id"]):
            ids = lib.encode(CASES[r["doc_id"]] or "", add_special_tokens=False).ids + [2]
            assert (r["start"], r["n_tokens"], r["ids_crc32"]) == (start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
            start += len(ids)
    assert idfile.read_documents(common.written(idfile.encode_segments(empty, "word_bpe_49k.json", 2), "t")).count() == 0
    wide = idfile.export_segment([np.array([70000, 1], "<u4").tobytes()])
    assert idfile.parse_segment(wide)[1].tolist() == [70000, 1]
    null_ids = spark.createDataFrame([(None, "a"), (None, "b"), (3, "a")], "doc_id long, text string")
    assert idfile.read_documents(common.written(idfile.encode_segments(null_ids, "word_bpe_49k.json", 2), "t")).count() == 3


# --- 6


def test_suffix_arrays_and_common_prefixes(monkeypatch):
    rng = np.random.default_rng(1)
    for trial in range(150):
        t = rng.integers(0, int(rng.integers(1, 5)), int(rng.integers(1, 60))).astype(np.uint8)
        t = np.tile(t, 3) if trial % 3 == 0 else t
        monkeypatch.setattr(suffixes, "BLOCK", (1, 2, 5, 1 << 15)[trial % 4])  # buckets alone, in blocks of a few, in one
        raw, want = t.tobytes(), sorted(range(len(t)), key=lambda i: t.tobytes()[i:])
        order = suffixes.suffix_array(t)
        assert order.tolist() == want
        shared = suffixes.common_prefixes(raw, order)
        for a, b in zip(want, want[1:], strict=False):
            n = next((k for k in range(len(raw)) if raw[a + k : a + k + 1] != raw[b + k : b + k + 1] or a + k >= len(raw) or b + k >= len(raw)), len(raw))
            assert shared[b] == n


def brute_removal(cases, n=200):
    count = Counter(t[i : i + n] for t in cases for i in range(len(t) - n + 1))
    out = []
    for t in cases:
        hit = np.zeros(len(t), bool)
        for i in range(len(t) - n + 1):
            if count[t[i : i + n]] > 1:
                hit[i : i + n] = True
        kept = bytes(np.frombuffer(t, np.uint8)[~hit])
        out.append((len(t), int(hit.sum()), len(substrings.spans(hit)), hashlib.sha256(kept).hexdigest()))
    return out


PASSAGES = [prose(70, 11), prose(55, 12)]
SHARED = [prose(100, 20) + PASSAGES[0] + prose(90, 21), PASSAGES[0] + prose(30, 22) + PASSAGES[1], "é" + PASSAGES[1] + prose(40, 23), "ab" * 500, "ab" * 320, prose(60, 24) * 3, prose(150, 25), prose(150, 25), "x\x00" * 150, "short"]


@pytest.mark.parametrize("hot", [1 << 24, 400])
def test_repeated_substrings_go(spark, monkeypatch, hot):
    monkeypatch.setattr(substrings, "HOT_BYTES", hot)
    cases = [*CASES, *SHARED]
    df = spark.createDataFrame(list(enumerate(cases)), "doc_id long, text string").repartition(3)
    want = brute_removal([(t or "").encode() for t in cases])
    raw = F.coalesce("text", F.lit(""))
    rows = df.select("doc_id", substrings.text_key(F.col("text")).alias("th"), F.octet_length(raw).alias("n"), F.sha2(raw.cast("binary"), 256).alias("sha"))
    found = rows.join(substrings._by_text(df, "text", False), "th", "left")
    for r in found.collect():
        assert (r["n"], r["removed"] or 0, r["parts"] or 0, r["out"] or r["sha"]) == want[r["doc_id"]], r["doc_id"]


def test_removal_keeps_rows_and_columns(docs, empty):
    out = substrings.remove_repeated(docs)
    assert out.columns == docs.columns and out.count() == docs.count()
    assert substrings.remove_repeated(empty).count() == 0


# --- 7


def test_mixing_hits_targets(spark, docs, empty):
    rows = [(i, prose(5 + i % 40, i), f"s{0 if i % 3 == 0 else i % 7}") for i in range(400)] + [(900, None, "nothing"), (901, "a b c", None), (17, prose(22, 17), "s3"), (17, prose(22, 17), "s3")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    run = lambda: mixing.mix(df, mixing.word_count(F.col("text"))).collect()
    got = run()
    by = defaultdict(list)
    for r in got:
        by[r["row"]["source"]].append(r)
        assert 0 <= r["taken"] <= 3 * r["size"]
    total = sum(r["size"] for r in got)
    for rs in by.values():
        assert rs[0]["source_size"] == sum(r["size"] for r in rs)
        assert rs[0]["target"] <= 3 * rs[0]["source_size"] + 1e-6
        assert abs(sum(r["taken"] for r in rs) - rs[0]["target"]) <= 1
        # the line of the source, in closed form, is what the one queue of all sources comes to
        line = math.floor(rs[0]["target"] + 1e-6)
        for r in rs:
            assert r["taken"] == sum(max(0, min(r["size"], line - e * r["source_size"] - r["before"])) for e in range(3))
    assert sum(rs[0]["target"] for rs in by.values()) == pytest.approx(total)
    mixed = mixing.mixed_documents(df)
    assert mixed.columns == df.columns
    assert mixed.agg(F.sum(mixing.word_count(F.col("text")))).first()[0] == sum(r["taken"] for r in got)
    assert sorted(map(str, got)) == sorted(map(str, run()))
    assert mixing.mixed_documents(empty).count() == 0 and mixing.mix(empty, F.lit(1)).count() == 0
    assert mixing.mixed_documents(docs).columns == docs.columns


@pytest.mark.parametrize("broadcast", [0, 200_000])
def test_mixing_by_slices_and_joins_changes_no_result(spark, monkeypatch, broadcast):
    df = spark.createDataFrame([(i, i % 9, f"s{i % 5 % 3}") for i in range(300)], "doc_id long, w long, source string")
    run = lambda: sorted((r["row"]["doc_id"], r["before"], r["taken"]) for r in mixing.mix(df, F.col("w")).collect())
    whole = run()
    monkeypatch.setattr(mixing, "SLICE", 7)
    monkeypatch.setattr(mixing, "BROADCAST_SOURCES", broadcast)
    assert run() == whole


def test_mixing_leaves_columns_of_any_name_alone(spark):
    names = ["doc_id", "source", "w", "target", "source_size", "size", "before", "taken", "_slice", "_offset", "_u", "_source", "row", "rounds"]
    df = spark.createDataFrame([(i, "a", 5, *[f"{c}{i}" for c in names[3:]]) for i in range(9)], f"doc_id long, source string, w long, {', '.join(f'{c} string' for c in names[3:])}")
    for r in mixing.mix(df, F.col("w")).collect():
        assert [r["row"][c] for c in names[3:]] == [f"{c}{r['row']['doc_id']}" for c in names[3:]] and r["taken"] == 5


def test_running_sums_follow_one_order(spark):
    df = spark.createDataFrame([(i * 7919 % 1000, i % 4) for i in range(1000)], "k long, x long").repartition(3)
    got = sorted(common.running(df, [F.col("k")], {"ahead": F.col("x")}).collect())
    total = 0
    for r in got:
        assert r["ahead"] == total
        total += r["x"]


# --- 8


def lm_cases():
    return texts() | {i: prose(60, i % 25) for i in range(100, 400)}


def unseen(i):
    return zlib.crc32(str(i).encode()) % 7 == 2


def brute_score(lists, rate_middle):
    """Scores from dictionaries of exact counts, read through their levels' middles."""
    train = [x for i, x in lists.items() if not unseen(i)]
    words, pairs = Counter(w for x in train for w in x), Counter(p for x in train for p in zip([langmodel.END, *x], x, strict=False))
    threes = Counter(t for x in train for t in zip([langmodel.END, *x], x, x[1:], strict=False))
    scale, (k, m) = sum(words.values()) + len(words) + 1, langmodel.PRIORS
    found = {}
    for i, x in lists.items():
        before, total = [langmodel.END, *x], 0.0
        for j, w in enumerate(x):
            p = rate_middle(pairs[before[j], w])
            chance = (p + k * (rate_middle(words[w]) + 1) / scale) / (max(rate_middle(words[before[j]]), p) + k)
            if j:
                t = rate_middle(threes[before[j - 1], before[j], w])
                chance = (t + m * chance) / (max(rate_middle(pairs[before[j - 1], before[j]]), t) + m)
            total += math.log10(chance)
        found[i] = total
    return words, found


@pytest.mark.parametrize(("size", "grams", "together"), [(1, 1 << 21, True), (2000, 500, False), (10**9, 500, True)])
def test_scores_are_those_of_a_brute_force_model(spark, docs, empty, monkeypatch, size, grams, together):
    """By chunks of one batch, some and all texts, with few and many slices, filled apart from and together with the
    answers; at a false rate of 1e-12 nothing stands between, at the usual one a little."""
    monkeypatch.setattr(langmodel, "CHUNK_BYTES", size)
    monkeypatch.setattr(langmodel, "SLICE_GRAMS", grams)
    cases = lm_cases()
    df = docs.select("doc_id", "text").unionByName(spark.createDataFrame([(i, t) for i, t in cases.items() if i >= 100], "doc_id long, text string"))
    lists = {i: langmodel.tokens(t.encode()) for i, t in cases.items()}
    words, want = brute_score(lists, lambda n: (3 * 2 ** math.floor(math.log2(n)) - 1) / 2 if n else 0.0)
    n, v, out = sum(words.values()), len(words), langmodel.held_out(F.col("doc_id"))
    held = [0.0, 0.0]
    for rate in (1e-12, langmodel.FALSE_RATE):
        if together:
            rows = langmodel.fit_and_score(df, ~out, false_rate=rate).collect()
        else:
            model = langmodel.fit(df.where(~out), false_rate=rate)
            rows = langmodel.score(df, model).collect()
        assert sorted(r["doc_id"] for r in rows) == sorted(cases)
        wrong = []
        for r in rows:
            x = lists[r["doc_id"]]
            assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (unseen(r["doc_id"]), len(x), sum(words[w] > 0 for w in x), n)
            assert r["base_score"] == pytest.approx(sum(math.log10((words[w] + 1) / (n + v + 1)) for w in x))
            wrong.append(abs(r["score"] - want[r["doc_id"]]) / len(x))
            if r["held_out"]:
                held = [held[0] + r["base_score"], held[1] + r["score"]]
        assert max(wrong) < 1e-9 if rate < 1e-9 else np.mean(wrong) < 0.02
    assert held[1] > held[0]  # texts that weren't seen are likelier under the model than under the base
    assert langmodel.fit_and_score(empty, ~out).count() == 0
    nothing = langmodel.fit_and_score(df, F.lit(False)).collect()
    assert len(nothing) == len(cases) and all(r["n_known"] == 0 and r["train_tokens"] == 0 and r["base_score"] == 0 for r in nothing)
    if not together:
        assert langmodel.score(empty, model).count() == 0


def test_registered_scores_on_whole_tables(spark, sf):
    """The query itself, over all documents of a table, against the brute-force model."""
    rows = {r["doc_id"]: r["text"] or "" for r in common.table(spark, sf, "documents").collect()}
    lists = {i: langmodel.tokens(t.encode()) for i, t in rows.items()}
    _, want = brute_score(lists, lambda n: (3 * 2 ** math.floor(math.log2(n)) - 1) / 2 if n else 0.0)
    wrong = [abs(r["score"] - want[r["doc_id"]]) / r["n_tokens"] for r in langmodel.op8_lm_scoring(spark, sf).collect()]
    assert len(wrong) == len(rows) and np.mean(wrong) < 0.02


def test_counts_of_255_and_more_are_kept_whole():
    counts = np.array([0, 1, 254, 255, 256, 70_000, 3, 1 << 31])
    a, b = langmodel._packed(counts[:4]), langmodel._packed(counts[4:])
    assert langmodel._unpacked([a[0], b[0]], [a[1], b[1]]).tolist() == counts.tolist()


@pytest.mark.parametrize("n", [1000, 400_000])
def test_slices_keep_their_false_rate_at_any_load(n):
    r = np.random.default_rng(4)
    h = np.unique(r.integers(0, 1 << 32, n + n // 8).astype(np.uint32))
    missing, h = h[::9], np.delete(h, np.s_[::9])
    counts = np.minimum(r.zipf(1.8, len(h)), 10**6)
    bits = np.frombuffer(langmodel.fill_slice(h, counts, langmodel.slice_size(int(langmodel.levels_of(counts).sum()))), np.uint8)
    assert np.unpackbits(bits).mean() == pytest.approx(langmodel.FALSE_RATE ** (1 / langmodel.PROBES), rel=0.1)
    assert (langmodel.probe_slice(bits, missing) > 0).mean() < 0.02 + 3 / len(missing)
    exact = np.floor(np.log2(counts)) + 1
    told = langmodel.probe_slice(bits, h)
    assert (told >= exact).all() and (told == exact).mean() > 0.97


# --- 9


def brute_groups(cases, k, percent):
    sets = {}
    for i, t in cases.items():
        w = (t or "").encode().lower().split()
        sets[i] = {tuple(w[j : j + k]) for j in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())
    parent = {i: i for i in cases}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for a in cases:
        for b in cases:
            if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                parent[y] = x
    return {i: (len(sets[i]), find(i)) for i in cases}


def test_bands_miss_no_pair_of_ten_thousand(spark):
    """Recall of the pipeline's candidates: pairs of texts of a similarity of 0.8 and little more."""
    rows, r, wanted = [], np.random.default_rng(12), 0
    for g in range(10_000):
        n = int(r.integers(30, 90))
        base = [f"w{g}x{j}" for j in range(n + 4)]
        # a word changed in the middle takes five shingles from each side: so many that 0.8 is just reached
        other, most = list(base), int((n - 0.8 * n) / 1.8 / 5)
        for j in r.permutation(np.arange(5, n - 2, 6))[:most]:
            other[j] = "z"
        rows += [(2 * g, " ".join(base)), (2 * g + 1, " ".join(other))]
        a, b = ({tuple(w[j : j + 5]) for j in range(n)} for w in (base, other))
        wanted += 100 * len(a & b) >= 80 * len(a | b)
    assert wanted == 10_000
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(8)
    found = jaccard.groups(df, 80, 5, bands=True).where("component_id % 2 = 0 and doc_id % 2 = 1 and component_id = doc_id - 1").count()
    assert found == wanted


def near_copies():
    out, r = {}, random.Random(8)
    for g in range(25):
        base = prose(r.choice([4, 8, 14, 30, 60, 200, 500]), 1000 + g).split()
        for c in range(6):
            w = list(base)
            for _ in range(r.randrange(0, max(2, len(w) // 20))):
                at, what = r.randrange(len(w)), r.randrange(3)
                if what == 0:
                    w[at] = r.choice(WORDS)
                elif what == 1:
                    w.insert(at, r.choice(WORDS))
                else:
                    w.pop(at)
            out[100 * g + c] = " ".join(w)
    return out


@pytest.mark.parametrize(("k", "percent", "block", "bands"), [(3, 90, 4000, False), (5, 80, 4000, False), (3, 90, 3, False), (5, 80, 4000, True)])
def test_groups_of_near_copies(spark, monkeypatch, k, percent, block, bands):
    monkeypatch.setattr(jaccard, "BLOCK", block)
    monkeypatch.setattr(jaccard, "ONE_TASK", 0 if block == 3 else 500_000)
    cases = {**{5000 + i: t for i, t in enumerate(CASES)}, **near_copies()}
    df = spark.createDataFrame(list(cases.items()), "doc_id long, text string").repartition(3)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard.groups(df, percent, k, bands=bands).collect()}
    assert got == brute_groups(cases, k, percent)


def test_one_of_each_group_stays(spark, docs, empty):
    rows = [(1, "a b c d"), (1, "a b c d"), (2, "a b c d"), (None, "a b c d"), (3, None), (4, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted((r["doc_id"] or 0) for r in jaccard.one_of_each(df).collect()) == [0, 1, 3, 4]
    # rows that share a doc_id and nothing else all stay, whichever comes first
    shared = [(1, prose(30, 61), "x"), (1, prose(30, 62), "y"), (1, prose(30, 62), "z"), (2, prose(30, 63), "x"), (2, prose(30, 61), "y"), (5, "", "x"), (5, None, "x"), (5, "", "y")]
    for rows in (shared, shared[::-1]):
        got = jaccard.one_of_each(spark.createDataFrame(rows, "doc_id long, text string, kind string").repartition(3)).collect()
        assert sorted((r["doc_id"], r["text"] or "") for r in got) == sorted({(1, shared[0][1]), (1, shared[1][1]), (2, shared[3][1]), (5, "")})
    maps = spark.createDataFrame([(1, "a b c d", {"k": i}) for i in (3, 1, 2)], "doc_id long, text string, m map<string, int>")
    assert jaccard.one_of_each(maps).collect() == jaccard.one_of_each(maps.repartition(3)).collect() and jaccard.one_of_each(maps).count() == 1
    by_id = {(r["doc_id"], r["component_id"]) for r in jaccard.groups(spark.createDataFrame(shared, "doc_id long, text string, kind string")).collect()}
    assert by_id == {(1, 1), (2, 2), (2, 1), (5, 5)}
    assert jaccard.one_of_each(empty).count() == 0 and jaccard.one_of_each(docs).columns == docs.columns


@pytest.mark.parametrize("one_task", [500_000, 0])
def test_components_of_a_long_path(spark, monkeypatch, one_task):
    monkeypatch.setattr(jaccard, "ONE_TASK", one_task)
    path = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 200)], "a long, b long")
    got = {r["node"]: r["label"] for r in jaccard.components(path).collect()}
    assert got == {**dict.fromkeys(range(41), 0), 100: 100, 200: 100}


# --- 10


def test_packing(docs, empty):
    lib = library("byte_bpe_50k.json")
    rows = packing.pack(docs).collect()
    by_doc, by_seq = defaultdict(list), defaultdict(list)
    for r in rows:
        by_doc[r["doc_id"]].append(r)
        by_seq[r["sequence_id"]].append(r)
    for i, t in texts().items():
        ids, at = lib.encode(t, add_special_tokens=False).ids + [1], 0
        for r in sorted(by_doc[i], key=lambda r: r["start"]):
            assert (r["start"], r["doc_tokens"]) == (at, len(ids)) and r["length"] > 0
            assert r["ids_crc32"] == zlib.crc32(np.array(ids[at : at + r["length"]], "<u4").tobytes())
            at += r["length"]
        assert at == len(ids)
    for rs in by_seq.values():
        at = 0
        for r in sorted(rs, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= 2048
    assert packing.pack(empty).count() == 0


@pytest.mark.parametrize(("buffer", "word"), [(3000, 1 << 30), (1 << 19, 50)])
def test_small_buffers_and_long_words_lose_no_id(docs, monkeypatch, buffer, word):
    """Windows cut from few ids at a time, and texts with long words given to the library: the same ids, each once."""
    monkeypatch.setattr(packing, "BUFFER_IDS", buffer)
    monkeypatch.setattr(tokens, "LONG_WORD", word)  # for encoders of this process
    encoder = tokens.RankEncoder(tokens.tokenizer_path("byte_bpe_50k.json"))
    assert encoder.many(list(CASES)) == [encoder.library.ids(t) if t else b"" for t in CASES]
    lib, by_doc, by_seq = library("byte_bpe_50k.json"), defaultdict(list), defaultdict(list)
    for r in packing.pack(docs).collect():
        by_doc[r["doc_id"]].append(r)
        by_seq[r["sequence_id"]].append(r)
    for i, t in texts().items():
        ids = np.array([*lib.encode(t, add_special_tokens=False).ids, 1], "<u4")
        at = 0
        for r in sorted(by_doc[i], key=lambda r: r["start"]):
            assert r["start"] == at and r["ids_crc32"] == zlib.crc32(ids[at : at + r["length"]].tobytes()) and r["doc_tokens"] == len(ids)
            at += r["length"]
        assert at == len(ids)
    for rs in by_seq.values():
        at = 0
        for r in sorted(rs, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= 2048


def test_cuts_are_the_cheapest():
    r = np.random.default_rng(4)
    for _ in range(40):
        at = np.cumsum(r.integers(1, 9, 14))
        cost = r.integers(0, 6, 14)
        best = {0: 0.0}
        for j in range(1, 15):
            end = at[j - 1]
            best[j] = min((best[i] + 16 - (end - (at[i - 1] if i else 0)) + cost[j - 1] for i in range(j) if end - (at[i - 1] if i else 0) <= 16), default=math.inf)
        cuts = packing.best_cuts(at, cost, 16)
        total, last = 0, 0
        for c in cuts:
            total += 16 - (c - last) + cost[int(np.searchsorted(at, c))]
            last = c
        assert cuts[-1] == at[-1] and total == best[14]
    assert packing.rest_cuts(1024) == [1024] and sum(np.diff([0, *packing.rest_cuts(1025)])) == 1025


CLASHING = ["size", "th", "_stats", "target", "taken", "before", "_u", "_host", "h", "_first", "_id", "node", "out", "kept", "_out", "_t"]


def test_columns_of_any_name_pass_the_stages(spark, docs):
    import corpus_pipeline

    rows = docs.drop("size").withColumns({c: F.concat(F.lit(f"{c}-"), F.col("doc_id").cast("string")) for c in CLASHING})
    for _, stage in corpus_pipeline.STAGES[:-1]:
        rows = stage(spark, rows, "")
        for r in rows.collect():
            assert all(r[c] == f"{c}-{r['doc_id']}" for c in CLASHING)
    assert corpus_pipeline.STAGES[-1][1](spark, rows, "").count() > 0


def test_pipeline_stages(spark, docs, empty):
    import corpus_pipeline

    for start in (docs, empty):
        rows = start
        for name, stage in corpus_pipeline.STAGES[:-1]:
            rows = common.written(stage(spark, rows, ""), name)
            assert rows.columns == docs.columns
        assert corpus_pipeline.STAGES[-1][1](spark, rows, "").count() == (0 if start is empty else pytest.approx(rows.count(), abs=40))


def brute_quality(cases, hosts):
    """Ids that the rules keep."""
    stats, base, soft = {}, {}, {}
    for i, t in cases.items():
        n, chars, symbols, dups, again = plain_stats(t)
        lines = len([x for x in (t or "").split("\n") if x.encode().split()])
        base[i] = n < 50 or 100 * again > 50 * n
        soft[i] = 100 * symbols > quality.SYMBOL_PERCENT * chars or 100 * dups > quality.LINE_PERCENT * lines
    by = defaultdict(list)
    for i in cases:
        by[hosts[i]].append(base[i] or soft[i])
    rates = [sum(x) / len(x) for x in by.values()]
    m = sum(rates) / len(rates)
    v = sum((r - m) ** 2 for r in rates) / (len(rates) - 1) if len(rates) > 1 else 0
    w = min(1000, m * (1 - m) / v - 1 if 0 < v < m * (1 - m) else 1)
    verdict = {}
    for h, x in by.items():
        r = (sum(x) + m * w) / (len(x) + w)
        low = r - 2 * math.sqrt(r * (1 - r) / (len(x) + w + 1))
        verdict[h] = "blocked" if low > quality.BLOCKED else "suspect" if r > quality.SUSPECT else "trusted"
    return [i for i in cases if not base[i] and verdict[hosts[i]] != "blocked" and (verdict[hosts[i]] == "trusted" or not soft[i])]


def test_pipeline_against_brute_force(spark):
    import corpus_pipeline

    cases = {**{5000 + i: t for i, t in enumerate([*CASES, *SHARED])}, **near_copies()}
    hosts = {i: None if i % 11 == 0 else f"h{i % 4}" for i in cases}
    rows = spark.createDataFrame([(i, t, "en", hosts[i], len(t or "")) for i, t in cases.items()], "doc_id long, text string, lang string, source string, n_chars long").repartition(3)
    stages, seen = dict(corpus_pipeline.STAGES), {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        rows = common.written(stage(spark, rows, ""), name)
        seen[name] = rows.collect()
    kept = brute_quality(cases, hosts)
    assert sorted(r["doc_id"] for r in seen["quality_rules"]) == sorted(kept)
    groups = brute_groups({i: cases[i] for i in kept}, 5, 80)
    first = sorted(i for i in kept if groups[i][1] == i)
    assert sorted(r["doc_id"] for r in seen["jaccard_join"]) == first
    raws = [cases[i].encode() for i in first]
    count = Counter(t[i : i + 200] for t in raws for i in range(len(t) - 199))
    for i, raw in zip(first, raws, strict=True):
        hit = np.zeros(len(raw), bool)
        for j in range(len(raw) - 199):
            if count[raw[j : j + 200]] > 1:
                hit[j : j + 200] = True
        left = bytes(np.frombuffer(raw, np.uint8)[~hit]).decode("utf-8", "ignore")
        assert [r["text"] for r in seen["suffix_dedup"] if r["doc_id"] == i] == [left]
    words = lambda t: len(t.encode().split())
    size = Counter()
    for r in seen["suffix_dedup"]:
        size[r["source"]] += words(r["text"])
    names = sorted(size, key=lambda x: (x is None, x or ""))
    weight, total = {x: 1 + j % 3 for j, x in enumerate(names)}, sum(size.values())
    target, full = {}, set()
    while True:
        rest = total - sum(3 * size[x] for x in full)
        target = {x: 3 * size[x] if x in full else rest * weight[x] / sum(weight[y] for y in names if y not in full) for x in names}
        more = {x for x in names if x not in full and target[x] > 3 * size[x]}
        if not more:
            break
        full |= more
    got = Counter()
    for r in seen["mixing"]:
        got[r["source"]] += words(r["text"])
    assert all(abs(got[x] - target[x]) <= 1 for x in names)
    lib = library("byte_bpe_50k.json")
    pieces = stages["packing"](spark, rows, "").collect()
    assert sum(r["length"] for r in pieces) == sum(len(lib.encode(r["text"], add_special_tokens=False).ids) + 1 for r in seen["mixing"])


def test_written_tables_can_be_deleted(spark):
    df = common.written(spark.range(3).toDF("x"), "t")
    path = df.inputFiles()[0]
    assert common.clean(spark) > 0 and common.clean(spark) == 0
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        spark.read.parquet(path).count()


def test_answers_leave_no_shuffle_behind(spark, docs, monkeypatch):
    """The files of the shuffle that asks the slices go when the answers are written, not at the driver's next garbage collection."""
    disk, left, writes = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager(), [], common.written

    def held():
        found = disk.getAllFiles()
        return {found.apply(i).getName() for i in range(found.size()) if found.apply(i).getName().startswith("shuffle")}

    def watched(df, what, *args, **more):
        before, out = held(), writes(df, what, *args, **more)
        end = time.time() + 10
        while held() - before and time.time() < end:
            time.sleep(0.1)
        left.append((what, held() - before))
        return out

    monkeypatch.setattr(langmodel, "written", watched)
    langmodel.fit_and_score(docs, F.lit(True))
    assert left == [("chunks", set()), ("answers", set())]
    assert spark.conf.get("spark.sql.classic.shuffleDependency.fileCleanup.enabled") == "false"
