"""Every query with SQL gives what DuckDB gives on the smallest tables; the entry point works."""

import os

import duckdb
import pytest

import __spark_entry__
from privq import queries
from privq.plans.ranks import GapTooSmall

SF = "/root/testdata/sf0.01"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
pytestmark = pytest.mark.skipif(not os.path.isdir(SF), reason="no test tables")


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


def plain(v):
    return round(v, 6) if isinstance(v, float) else v


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_query_matches_sql(spark, duck, name):
    df = queries.queries()[name](spark, SF)
    columns = sorted(df.columns)
    ours = sorted((tuple(plain(r[c]) for c in columns) for r in df.collect()), key=repr)
    found = duck.sql(queries.oracle_sql()[name])
    theirs = sorted((tuple(plain(dict(zip(found.columns, r, strict=True))[c]) for c in columns) for r in found.fetchall()), key=repr)
    assert ours == theirs and ours


def test_entry(spark):
    assert __spark_entry__.entry(spark).count() == 9


def test_small_tables_refuse(spark):
    with pytest.raises(GapTooSmall):
        queries.RELEASES["private_deciles_price_substitute"].run(spark, "/root/testdata/sf0.001").collect()


def test_workloads_are_whole(spark):
    for name in ("w1_age_substitute", "w2_hours_substitute", "w3_age_addremove", "w4_hours_addremove"):
        _, settings, trials = queries.WORKLOADS[name]
        assert trials == 200 and sorted({s.m for s in settings()}) == list(range(10, 201, 10)) and len(settings()) == 60
    grid = [(s.eps, s.delta) for s in queries.WORKLOADS["w7_budgets"][1]()]
    assert len(set(grid)) == 15 and queries.WORKLOADS["w7_budgets"][2] == 200
    assert sorted(s.split for s in queries.WORKLOADS["w10_budget_split"][1]()) == [k / 10 for k in range(1, 10)]
    assert len(queries.WORKLOADS["w8_histogram"][0]) == 5
    assert {queries.WORKLOADS[w][2] for w in ("w8_histogram", "w10_budget_split", "w13_headline")} == {200}
    columns, settings, _ = queries.WORKLOADS["w8_histogram"]
    rows = queries.workload(columns, settings, 2)(spark, "/root/testdata/sf0.001").collect()
    assert len(rows) == 35 and {r["column"] for r in rows} == set(columns) and all(r["ci_low"] <= r["mean_max_error"] <= r["ci_high"] for r in rows)


def test_headline_at_a_small_scale(spark):
    """m = 200 under substitution: the slices win, the approximate rival is last, the factor is near 2."""
    rows = queries.workload("age", lambda: queries.experiments.sweep_m("substitute", [200]), 6)(spark, SF).collect()
    means = {r["method"]: r["mean_max_error"] for r in rows}
    assert means["slices"] * 1.4 < means["bisection_pure"] < means["bisection_zcdp"] and all(r["refused"] == 0 for r in rows)


@pytest.mark.parametrize("name", ["bootstrap_ci", "bounds_table", "failure_rate", "gap_sweep", "improvement_ratio", "noise_sup_norm", "outer_alignment", "paired_trials", "pivot_report", "pure_worked_example", "random_release", "rank_noise_binary"])
def test_query_depends_on_its_table(spark, name):
    """It reads a given table: rows differ between table sizes, or the plan names files."""
    small, large = (queries.queries()[name](spark, f"/root/testdata/{sf}") for sf in ("sf0.001", "sf0.01"))
    assert large.inputFiles() or sorted(map(str, small.collect())) != sorted(map(str, large.collect()))
