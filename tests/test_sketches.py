"""Building, flipping, merging and fitting sketches on Spark."""

import math

import pytest
from pyspark.sql import functions as F

from mistcount.functions import budget as bd
from mistcount.functions import likelihood as lk
from mistcount.functions.hashing import cell_of, level_of
from mistcount.layout import Layout
from mistcount.operators import merge as mg
from mistcount.operators.build import level_counts, packed, set_cells, sketch, unpack
from mistcount.operators.estimate import cardinality
from mistcount.operators.privatize import flip
from mistcount.plans import arrow, engine, experiments
from mistcount.sources import io
from mistcount.streaming import windows as st

L = Layout(64, 12)


def items(spark, n, lo=0):
    return spark.range(lo, lo + n).select(F.col("id").cast("string").alias("item"))


def ones(df, layout=L):
    return level_counts(df, layout).first()["ones"]


def test_levels_are_trailing_zeros_plus_one(spark):
    got = spark.createDataFrame([(1,), (2,), (12,), (0,), (1 << 40,)], "b long").select(level_of(F.col("b"), 10).alias("l")).collect()
    assert [r["l"] for r in got] == [1, 2, 3, 10, 10]


def test_repetition_order_and_nulls_do_not_matter(spark):
    a = items(spark, 500)
    b = a.unionByName(a).unionByName(spark.createDataFrame([(None,)], "item string")).orderBy(F.desc("item"))
    assert set_cells(a, F.col("item"), L).subtract(set_cells(b, F.col("item"), L)).count() == 0
    assert set_cells(b, F.col("item"), L).subtract(set_cells(a, F.col("item"), L)).count() == 0


def test_neighbours_differ_in_one_bit_at_most(spark):
    a, b = sketch(items(spark, 300), F.col("item"), L), sketch(items(spark, 301), F.col("item"), L)
    assert a.join(b.withColumnRenamed("bit", "other"), "cell").where("bit <> other").count() <= 1


def test_union_of_parts_is_the_sketch_of_the_whole(spark):
    parts = set_cells(items(spark, 300), F.col("item"), L).unionByName(set_cells(items(spark, 300, 200), F.col("item"), L)).withColumn("bit", F.lit(1))
    assert mg.union_plain(parts).count() == set_cells(items(spark, 500), F.col("item"), L).count()


def test_packed_form_holds_the_same_bits(spark):
    layout = Layout(4096, 24)
    rows = items(spark, 2000)
    bitmaps = packed(rows, F.col("item"), layout)
    assert ones(unpack(bitmaps, layout, []), layout) == ones(sketch(rows, F.col("item"), layout), layout)
    assert ones(unpack(bitmaps, layout, []), layout) == arrow.level_counts_packed(bitmaps.withColumn("g", F.lit(1)), layout, ["g"]).first()["ones"]


def test_an_empty_table_gives_an_empty_dense_sketch(spark):
    none = items(spark, 0)
    cells = sketch(none, F.col("item"), L)
    assert cells.count() == L.cells and cells.agg(F.sum("bit")).first()[0] == 0
    fitted = cardinality(level_counts(cells, L), L, 1.0, 0.0).first()
    assert fitted["n_hat"] == 0 and fitted["status"] == "zero"


def test_a_full_sketch_is_saturated(spark):
    full = spark.range(L.cells).select(F.col("id").cast("int").alias("cell"), F.lit(1).alias("bit"))
    row = cardinality(level_counts(full, L), L, 1.0, 0.0).first()
    assert row["n_hat"] is None and row["status"] == "saturated"


def test_no_budget_no_information(spark):
    f = bd.symmetric(1e-10)
    row = cardinality(level_counts(flip(sketch(items(spark, 100), F.col("item"), L), f, "k", "r"), L), L, f.p, f.q).first()
    assert row["status"] == "no_information" and row["n_hat"] is None


def test_noise_is_the_same_on_retry_and_new_for_each_release(spark):
    bits, f = sketch(items(spark, 400), F.col("item"), L), bd.symmetric(1.0)
    a, b, c = (flip(bits, f, "k", r).orderBy("cell").select("bit").collect() for r in ("r1", "r1", "r2"))
    assert a == b and a != c


def test_infinite_budget_changes_nothing(spark):
    bits = sketch(items(spark, 400), F.col("item"), L)
    assert flip(bits, bd.symmetric(math.inf), "k", "r").join(bits.withColumnRenamed("bit", "x"), "cell").where("bit <> x").count() == 0


def _noisy(spark, eps, lo, n, name, layout=L):
    return flip(sketch(items(spark, n, lo), F.col("item"), layout), bd.symmetric(eps), "k", name).withColumn("eps", F.lit(eps))


def test_randomized_union_of_one_sketch_is_itself(spark):
    one = _noisy(spark, 1.5, 0, 300, "a")
    merged = mg.union_randomized(one, "s")
    assert merged.join(one.withColumnRenamed("bit", "x"), "cell").where("bit <> x").count() == 0


def test_randomized_union_without_noise_is_the_plain_one(spark):
    parts = _noisy(spark, math.inf, 0, 200, "a").unionByName(_noisy(spark, math.inf, 100, 200, "b"))
    merged = mg.union_randomized(parts, "s")
    assert ones(merged) == ones(sketch(items(spark, 300), F.col("item"), L))


def test_union_estimate_lies_within_its_error(spark):
    layout = Layout(1024, 20)
    parts = None
    for i in range(3):
        part = _noisy(spark, 3.0, 4000 * i, 8000, f"p{i}", layout).withColumn("party", F.lit(i))
        parts = part if parts is None else parts.unionByName(part)
    row = engine.union_of_released(parts, layout, "s", io.described(parts, layout, "symmetric", "party", "r")).first()
    assert row["n_sources"] == 3 and row["eps_effective"] == pytest.approx(bd.combine_or([3.0] * 3))
    assert abs(row["n_hat"] - 16000) < 4 * row["stderr"]


def test_xor_union_estimate_lies_within_its_error(spark):
    layout, f = Layout(1024, 20), bd.half_flip(3.0)
    parts = None
    for i in range(2):
        part = flip(sketch(items(spark, 8000, 4000 * i), F.col("item"), layout), f, "k", f"x{i}").withColumn("eps", F.lit(3.0)).withColumn("party", F.lit(i))
        parts = part if parts is None else parts.unionByName(part)
    row = engine.union_of_released(parts, layout, "s", io.described(parts, layout, "half", "party", "r"), method="xor").first()
    assert abs(row["n_hat"] - 12000) < 4 * row["stderr"]


def test_packed_noisy_merge_follows_the_same_law(spark):
    layout = Layout(4096, 24)
    cells = _noisy(spark, 2.0, 0, 3000, "a", layout).withColumn("party", F.lit(0)).unionByName(_noisy(spark, 2.0, 1500, 3000, "b", layout).withColumn("party", F.lit(1)))
    at = F.col("cell").cast("long") + 1
    bitmaps = cells.where("bit = 1").groupBy(F.lit(1).alias("g"), "party", F.bitmap_bucket_number(at).alias("bucket_no")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(at)).alias("bits")).withColumn("eps", F.lit(2.0))
    merged = arrow.merge_packed(bitmaps, layout, ["g"], "s")
    assert merged.first()["eps_effective"] == pytest.approx(bd.combine_or([2.0, 2.0]))
    f = bd.symmetric(bd.combine_or([2.0, 2.0]))
    row = cardinality(arrow.level_counts_packed(merged, layout, ["g"]), layout, f.p, f.q).first()
    assert abs(row["n_hat"] - 4500) < 4 * row["stderr"]


KNOWN = [3488, 3431, 3475, 3407, 3358, 2958, 2238, 1687, 1143, 957, 795, 689, 667, 643, 625, 652, 668, 622, 636, 668, 666, 638, 673, 596]


def test_known_counts_give_the_known_estimate_with_every_solver(spark):
    f = bd.symmetric(1.6886799738766947)
    levels = spark.createDataFrame([(KNOWN,)], "ones array<long>")
    for solver in ("bisect", "safe", "newton"):
        assert cardinality(levels, Layout(), f.p, f.q, solver).first()["n_hat"] == pytest.approx(452151.4658, abs=0.01)
    assert arrow.fit_udf(Layout(), f.p, f.q) is not None
    assert levels.select(arrow.fit_udf(Layout(), f.p, f.q)(F.col("ones"))).first()[0] == pytest.approx(452151.4658, abs=0.01)


def test_derivatives_match_differences(spark):
    f, levels = bd.symmetric(1.5), spark.createDataFrame([(KNOWN,)], "ones array<long>")
    o, n, h = F.col("ones"), 400000.0, 50.0
    at = lambda x: lk.loglik(o, Layout(), x, f.p, f.q)
    row = levels.select((at(n + h) - at(n - h)).alias("d"), lk.score(o, Layout(), n, f.p, f.q).alias("s"), (lk.score(o, Layout(), n + h, f.p, f.q) - lk.score(o, Layout(), n - h, f.p, f.q)).alias("dd"), lk.hessian(o, Layout(), n, f.p, f.q).alias("h")).first()
    assert row["d"] / (2 * h) == pytest.approx(row["s"], rel=1e-3)
    assert row["dd"] / (2 * h) == pytest.approx(row["h"], rel=1e-3)


def test_simulated_error_is_the_formula_and_methods_rank_as_published(spark):
    layout, trials = Layout(256, 18), 60
    runs = experiments.simulated(spark, layout, ["randomized", "xor", "interval_tight", "interval_loose"], [1.0], [50000.0], trials)
    got = {r["method"]: (r["rmse"], r["se"]) for r in runs.groupBy("method").agg(F.sqrt(F.avg(F.pow(F.col("n_hat") - F.col("n"), 2))).alias("rmse"), F.avg("stderr").alias("se")).collect()}
    for m in ("randomized", "xor"):
        assert got[m][0] == pytest.approx(got[m][1], rel=4 / math.sqrt(2 * trials))
    assert got["randomized"][0] < got["xor"][0] < got["interval_tight"][0] < got["interval_loose"][0]


def _catalogued(spark, name, release="r", layout=L, lineage=None):
    cells = _noisy(spark, 2.0, 0, 50, name, layout).withColumn("g", F.lit(name))
    f = bd.symmetric(2.0)
    return io.heads(io.catalogued(cells, layout, 2.0, f.kind, f.p, f.q, "g", release, lineage))


def test_only_independent_sketches_of_one_kind_can_be_merged(spark):
    a, b = _catalogued(spark, "a"), _catalogued(spark, "b")
    assert mg.check_mergeable(a.unionByName(b)).count() == 2
    for bad, why in ((a.unionByName(a), "twice"), (a.unionByName(_catalogued(spark, "c", layout=Layout(64, 12, seed=1))), "layouts"), (a.unionByName(_catalogued(spark, "d", lineage=F.array(F.lit("r/a")))), "ancestor")):
        with pytest.raises(Exception, match=why):
            mg.check_mergeable(bad).collect()
        # each group is judged by itself
        grouped = bad.withColumn("x", F.col("sketch_id"))
        if why != "twice":
            assert mg.check_mergeable(grouped, ["x"]).count() == 2


def test_unions_refuse_shared_lineage_other_layouts_and_lacking_cells(spark):
    parts = [_noisy(spark, 2.0, 100 * i, 200, f"p{i}").withColumn("party", F.lit(i)) for i in range(2)]
    cells = parts[0].unionByName(parts[1])
    known = io.described(cells, L, "symmetric", "party", "r")
    assert engine.union_of_released(cells, L, "s", known).first()["n_sources"] == 2
    same = known.withColumn("lineage", F.array(F.lit("r/0")))
    other = known.withColumn("layout", F.when(F.col("sketch_id") == "r/0", F.col("layout")).otherwise(io.layout_column(Layout(64, 12, seed=3))))
    for sketches, rows, why in ((same, cells, "ancestor"), (other, cells, "layouts"), (known.unionByName(known), cells, "twice"), (known, cells.where("party = 0 or cell > 5"), "different numbers"), (known.limit(1), cells, "different numbers")):
        with pytest.raises(Exception, match=why):
            engine.union_of_released(rows, L, "s", sketches).collect()


def test_packed_flips_are_the_long_ones_and_streamed_noise_has_their_law(spark):
    layout, f = Layout(1024, 20), bd.symmetric(1.0)
    rows = items(spark, 3000).withColumn("g", F.when(F.col("item").cast("int") % 3 == 0, None).otherwise(F.col("item").cast("int") % 2)).unionByName(spark.createDataFrame([(None, 7)], "item string, g int"))
    bitmaps = arrow.sketch_packed(rows, F.col("item"), layout, ["g"])
    assert bitmaps.count() == 4  # a bitmap for each group, that of null items only included
    long = flip(sketch(rows.fillna({"g": -1}), F.col("item"), layout, ["g"]), f, "k", "r", ["g"])
    named = bitmaps.fillna({"g": -1})
    counts = lambda df: sorted((r["g"], r["ones"]) for r in df.collect())
    assert counts(arrow.level_counts_packed(arrow.flip_packed(named, f, layout, "k", "r", ["g"], "cell"), layout, ["g"])) == counts(level_counts(long, layout, ["g"]))
    streamed = {r: counts(arrow.level_counts_packed(arrow.flip_packed(named, f, layout, "k", r, ["g"]), layout, ["g"])) for r in ("a", "b")}
    assert streamed["a"] != streamed["b"]  # another release, other noise
    assert streamed["a"] == counts(arrow.level_counts_packed(arrow.flip_packed(named.repartition(3), f, layout, "k", "a", ["g"]), layout, ["g"]))
    for g, ones_ in streamed["a"]:  # the highest level has no items, so its bits are 1 with chance q
        assert abs(ones_[-2] - 1024 * f.q) < 5 * math.sqrt(1024 * f.q * (1 - f.q)), g


def test_packed_private_sketches_of_a_hundred_thousand_groups(spark):
    layout, f, n = Layout(16, 12), bd.symmetric(2.0), 100_000
    rows = spark.range(n * 3).select((F.col("id") % n).alias("g"), F.col("id").cast("string").alias("item"))
    found = engine.count_private(rows, F.col("item"), 2.0, layout, "k", "many", ["g"], solver="newton")
    got = found.agg(F.count("*").alias("n"), F.avg(F.expr("aggregate(ones, 0L, (a, x) -> a + x)")).alias("ones")).first()
    # three items set a little less than three of 192 cells
    assert got["n"] == n and abs(got["ones"] - (192 * f.q + 2.95 * (f.p - f.q))) < 0.2


def test_merges_of_packed_sketches_refuse_lacking_bitmaps(spark):
    layout = Layout(4096, 24)
    rows = items(spark, 2000).withColumn("g", F.lit(1)).withColumn("party", F.col("item").cast("int") % 2)
    whole = arrow.sketch_packed(rows, F.col("item"), layout, ["g", "party"]).withColumn("eps", F.lit(math.inf))
    merged = arrow.level_counts_packed(arrow.merge_packed(whole, layout, ["g"], "s"), layout, ["g"]).first()["ones"]
    assert merged == ones(sketch(rows, F.col("item"), layout), layout)
    with pytest.raises(Exception, match="lacks"):
        arrow.merge_packed(whole.where("party = 0 or bucket_no > 1"), layout, ["g"], "s").collect()


def test_releases_of_one_key_differ_in_noise(spark):
    from mistcount.layout import Bloom
    from mistcount.operators import baselines as bl

    rows = items(spark, 400)
    a, b, c = (bl.noisy_estimate(rows, F.col("item"), L, 1.0, 10.0, "k", r).first()["n_hat"] for r in ("r1", "r1", "r2"))
    assert a == b != c
    with pytest.raises(ValueError):
        bl.bloom_union(rows, rows, F.col("item"), Bloom(256, k=2), 2.0, "k", ("a", "a"))
    x, y = (bl.bloom_union(rows, rows, F.col("item"), Bloom(1024, k=2), 2.0, "k", r).first()["empty"] for r in (("a", "b"), ("a", "c")))
    assert x != y


def test_ledger_books_each_release_once(spark, tmp_path):
    path, ledger, f = str(tmp_path / "s"), str(tmp_path / "l"), bd.symmetric(2.0)
    for release, eps in (("r1", 2.0), ("r1", 2.0), ("r2", 2.0)):
        cells = _noisy(spark, eps, 0, 50, release).withColumn("g", F.lit("users"))
        io.write_sketches(io.catalogued(cells, L, eps, f.kind, f.p, f.q, "g", release), path, release, ledger)
    (row,) = io.spent(io.read_ledger(spark, ledger)).collect()
    assert (row["scope"], row["eps_spent"], row["releases"]) == ("users", 4.0, 2)


def test_private_windows_keep_their_groups(spark, sf):
    e = io.read_table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    batch = st.window_bitmaps(e, F.col("user_id").cast("string"), L, "7 days", by=["event_type"])
    noisy = st.private_windows(batch, L, bd.symmetric(math.inf), "k", "r", ["event_type"])
    want = sorted((str(r["window"]["start"]), r["event_type"], r["n"]) for r in batch.select("window", "event_type", F.bitmap_count("bits").alias("n")).collect())
    assert sorted((r["window_start"], r["event_type"], r["n"]) for r in noisy.select("window_start", "event_type", F.bitmap_count("bits").alias("n")).collect()) == want
    assert len({x[1] for x in want}) > 1
    one = st.private_windows(batch, L, bd.symmetric(1.0), "k", "r", ["event_type"]).collect()
    two = st.private_windows(batch, L, bd.symmetric(1.0), "k", "r2", ["event_type"]).collect()
    assert sorted(map(str, one)) != sorted(map(str, two)) and len({(r["window_start"], r["event_type"]) for r in one}) == len(one)


def test_vectorised_estimators_are_the_expressions(spark):
    import numpy as np

    from mistcount.functions import vectorised
    from mistcount.operators import baselines as bl

    layout = Layout(256, 18)
    runs = experiments.settings(spark, ["randomized", "xor", "interval_loose"], [0.5, 3.0], [10.0, 1e3, 1e6], 5)
    levels = experiments.level_draws(runs, layout, "k")
    found = levels.withColumn("a", lk.estimate(F.col("ones"), layout, F.col("p"), F.col("q"), "bisect")[0]).withColumn("b", bl.interval_estimate(F.col("ones"), layout, F.col("p"), F.col("q"))).collect()
    ones_, p, q = (np.array([r[c] for r in found]) for c in ("ones", "p", "q"))
    nan = lambda xs: np.array([math.nan if x is None else x for x in xs])
    assert np.allclose(vectorised.fit(ones_, layout, p, q), nan([r["a"] for r in found]), rtol=1e-9, equal_nan=True)
    betas = bl.BETA_LEAST * np.exp(np.arange(bl.BETA_GRID + 1) * math.log(1 / bl.BETA_LEAST) / bl.BETA_GRID)
    assert np.allclose(vectorised.interval(ones_, layout, p, q, betas), nan([r["b"] for r in found]), rtol=1e-9, equal_nan=True)
    full = np.full((1, 18), 256)
    assert math.isnan(vectorised.fit(full, layout, 1.0, 0.0)[0]) and vectorised.fit(0 * full, layout, 1.0, 0.0)[0] == 0


def test_level_draws_have_the_law_of_cells(spark):
    """Means of level counts by either simulation lie within their error of what the law says."""
    from mistcount.operators.simulate import private_levels

    layout, f, n, trials = Layout(64, 10), bd.symmetric(1.0), 500.0, 200
    grid = spark.range(trials).select(F.col("id").cast("int").alias("trial"), F.lit(n).alias("n"), F.lit(f.p).alias("p"), F.lit(f.q).alias("q"))
    for levels in (experiments.level_draws(grid, layout, "k"), private_levels(grid, layout, "k", ["trial"])):
        rows = [r["ones"] for r in levels.collect()]
        for j, rho in enumerate(layout.rho()):
            chance = f.q + (f.p - f.q) * -math.expm1(n * math.log1p(-rho))
            mean = sum(r[j] for r in rows) / trials
            assert abs(mean - 64 * chance) < 5 * math.sqrt(64 * chance * (1 - chance) / trials) + 1e-9


def test_merged_sketches_err_as_the_formula_says(spark):
    levels = experiments.merged_trials(spark, Layout(512, 20), [1, 2, 8], [2.0, 4.0], 100_000, 80)
    got = experiments.relative_error(experiments.fitted_unions(levels, Layout(512, 20)), ["k", "eps"]).collect()
    assert len(got) == 6
    for r in got:
        assert r["rrmse"] == pytest.approx(r["rel_stderr"], rel=5 / math.sqrt(160))


def test_errors_fall_with_the_root_of_the_buckets_for_every_method(spark):
    from mistcount.operators import measures as ms

    runs = None
    for b in (256, 512, 1024, 2048):
        part = experiments.simulated_counts(spark, Layout(b, 24), ["randomized", "xor"], [2.0], [1e6], 1000, f"b{b}").withColumn("buckets", F.lit(b)).select("method", "buckets", "n", "n_hat")
        runs = part if runs is None else runs.unionByName(part)
    runs = runs.unionByName(experiments.register_trials(spark, [256, 512, 1024, 2048], 1_000_000, 1000).withColumn("method", F.lit("hll")).select("method", "buckets", "n", "n_hat"))
    for r in ms.loglog_slope(experiments.relative_error(runs, ["method", "buckets"]), "buckets", "rrmse", ["method"]).collect():
        assert r["slope"] == pytest.approx(-0.5, abs=0.05), r


def test_cells_of_composite_items_keep_null_parts_apart(spark):
    from mistcount.functions.hashing import joined

    rows = spark.createDataFrame([("a", None), (None, "a"), ("a", "a")], "x string, y string").select(joined(F.col("x"), F.col("y")).alias("item"))
    assert rows.distinct().count() == 3
    assert rows.select(cell_of(F.col("item"), Layout())).count() == 3


def test_stream_windows_hold_what_the_table_holds(spark, sf, tmp_path):
    e = io.read_table(spark, sf, "events")
    e.repartitionByRange(3, "ts").write.parquet(str(tmp_path / "in"))
    s = st.window_bitmaps(st.event_stream(spark, str(tmp_path / "in"), e.schema), F.col("user_id").cast("string"), L, "7 days")
    q = s.writeStream.outputMode("complete").format("memory").queryName("w").option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    q.awaitTermination()
    table = st.window_bitmaps(e.withColumn("ts", F.col("ts").cast("timestamp")), F.col("user_id").cast("string"), L, "7 days")
    n = lambda df: sorted((str(r[0]), r[1]) for r in df.select(F.col("window.start"), F.bitmap_count("bits")).collect())
    assert n(spark.table("w")) == n(table)
    with pytest.raises(ValueError):
        st.release_stream(s, L, bd.symmetric(1.0), "k", "r", str(tmp_path / "out"), str(tmp_path / "l"), str(tmp_path / "cp2"), mode="update")
    with pytest.raises(ValueError):
        st.release_stream(s, L, bd.symmetric(1.0), "k", "", str(tmp_path / "out"), str(tmp_path / "l"), str(tmp_path / "cp2"))


@pytest.mark.parametrize("last_first", [False, True])
def test_release_has_every_window_and_row_whatever_the_order_of_files(spark, sf, tmp_path, last_first):
    from mistcount.catalog import companions as co

    e, path = io.read_table(spark, sf, "events"), str(tmp_path / "in")
    edge = e.agg(F.percentile_approx(F.col("ts").cast("timestamp").cast("long"), [0.4, 0.7])).first()[0]
    at = F.col("ts").cast("timestamp").cast("long")
    parts = [e.where(at < edge[0]), e.where((at >= edge[0]) & (at < edge[1])), e.where(at >= edge[1])]
    for part in reversed(parts) if last_first else parts:
        part.coalesce(1).write.mode("append").parquet(path)
    item, f = F.col("user_id").cast("string"), bd.symmetric(3.0)
    # the noise is a function of key, release, window and cell, so equal bits mean equal sketches
    batch = st.window_bitmaps(e.withColumn("ts", F.col("ts").cast("timestamp")), item, co.SMALL, "7 days")
    want = st.private_windows(batch, co.SMALL, f, co.KEY, "run 1")
    rows = lambda df: sorted((r["window_start"], r["bucket_no"], bytes(r["bits"])) for r in df.collect())
    bitmaps, ledger = co.released(spark, e, path, "run 1")
    got = rows(bitmaps)
    assert len({r[0] for r in got}) == batch.select("window").distinct().count() > 3
    assert got == rows(want)
    assert ledger.count() == len(got) and ledger.agg(F.sum("eps")).first()[0] == pytest.approx(3.0 * len(got))


def _in_any_order(spark, epsilons):
    """Every order of these budgets, as a group each; a group's rows are read in that order."""
    import itertools

    rows = [(i, e) for i, order in enumerate(itertools.permutations(epsilons)) for e in order]
    return spark.createDataFrame(rows, "g int, eps double").coalesce(1)


def test_combined_budgets_do_not_depend_on_the_order_of_rows(spark):
    rows = _in_any_order(spark, [3.0, 2.0, 2.5, 4.0])
    found = rows.groupBy("g").agg(bd.combine_or_column(F.col("eps")).alias("o"), bd.combine_xor_column(F.col("eps")).alias("x"))
    (one,) = found.select("o", "x").distinct().collect()
    assert one["o"] == pytest.approx(bd.combine_or([3.0, 2.0, 2.5, 4.0]), rel=1e-12) and one["x"] == pytest.approx(bd.combine_xor([3.0, 2.0, 2.5, 4.0]), rel=1e-12)


def test_unions_of_many_budgets_are_one_sketch(spark):
    """Cells whose rows come in different orders are still cells of one union, in the long form and in the packed one."""
    layout, budgets = Layout(4096, 24), [3.0, 2.0, 2.5, 4.0, 1.75, 2.25]
    rows = items(spark, 3000).withColumn("party", F.col("item").cast("int") % 6)
    eps = F.element_at(F.array(*[F.lit(e) for e in budgets]), F.col("party") + 1)
    cells = sketch(rows, F.col("item"), L, ["party"]).withColumn("eps", eps).withColumn("g", F.lit("all"))
    shuffled = cells.coalesce(1).sortWithinPartitions("cell", F.xxhash64("cell", "party"))
    found = engine.union_of_released(shuffled, L, "s", io.described(cells, L, "symmetric", "party", "r", ["g"]), ["g"]).select("eps_effective", "n_sources").collect()
    assert len(found) == 1 and found[0]["n_sources"] == 6 and found[0]["eps_effective"] == pytest.approx(bd.combine_or(budgets), rel=1e-12)
    packed_ = arrow.sketch_packed(rows, F.col("item"), layout, ["party"]).withColumn("eps", eps).withColumn("g", F.lit("all"))
    merged = arrow.merge_packed(packed_, layout, ["g"], "s").select("eps_effective").distinct().collect()
    assert len(merged) == 1 and merged[0]["eps_effective"] == pytest.approx(bd.combine_or(budgets), rel=1e-12)
