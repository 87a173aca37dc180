"""Registered queries against their SQL, on the smallest tables."""

import duckdb
import pytest

import __spark_entry__ as entry
from verify import TABLES, plain

CORE = [n for n in entry.catalog.ORACLES]


@pytest.fixture(scope="module")
def db(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", CORE)
def test_query_gives_what_its_sql_gives(spark, sf, db, name):
    df = entry.catalog.QUERIES[name](spark, sf)
    rows = sorted((tuple(plain(x) for x in r) for r in df.collect()), key=str)
    found = db.sql(entry.catalog.ORACLES[name])
    at = [found.columns.index(c) for c in df.columns]
    assert rows == sorted((tuple(plain(r[i]) for i in at) for r in found.fetchall()), key=str)


def test_entry(spark):
    assert entry.entry(spark).count() == 1


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_two_parties_hold_all_line_items(spark, sf, db):
    n = db.sql("SELECT count(DISTINCT (l_orderkey, l_linenumber)) FROM lineitem").fetchall()[0][0]
    (row,) = entry.catalog.QUERIES["x01_intersection_size"](spark, sf).collect()
    assert row["union_n"] == pytest.approx(n, rel=0.15)


def test_groups_without_both_intervals_have_no_row(spark):
    """A full sketch's shares of empty cells are half below zero, where a relative interval ends nowhere."""
    from mistcount.catalog import comparisons as c

    f = c._HALF
    share = lambda n, j: f.q + (f.p - f.q) * (1 - (1 - c.WIDE.rho()[j]) ** n)
    exact = [round(4096 * share(30000, j)) for j in range(24)]
    full = [2100 if j < 8 else k for j, k in enumerate(exact)]  # 2048 is the most that a level has on average
    rows = spark.createDataFrame([("some", [min(k, 2047) for k in exact]), ("full", full)], "g string, ones array<long>")
    assert [r["g"] for r in c.both_intervals(rows, c.WIDE, f).collect()] == ["some"]


@pytest.mark.parametrize("name", ["a01_accuracy", "a02_relative_efficiency", "a03_variance_ratio", "a04_calibration", "a05_failure_rate", "a06_space", "a10_coverage", "b01e_equivalent_budgets", "m05_dp_verifier", "m09g_transition", "m13_budget_algebra", "m15_stderr_formula"])
def test_measures_and_formulas_read_a_table(spark, sf, name):
    df = entry.catalog.QUERIES[name](spark, sf)
    assert [f.split("/")[-1] for f in df.inputFiles()] == ["lineitem.parquet"]
