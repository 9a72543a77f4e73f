"""Queries that take whole tables and whole streams."""

import os

import duckdb
import pytest

import __spark_entry__ as entry
from tests.test_queries import plain
from tsproof import catalogue
from tsproof import experiments as ex


def database(sf):
    db = duckdb.connect()
    for t in os.listdir(sf):
        db.execute(f"create view {t.removesuffix('.parquet')} as select * from '{sf}/{t}'")
    return db


def equals_sql(spark, sf, name):
    df, cur = entry.queries()[name](spark, sf), database(sf).execute(entry.oracle_sql()[name])
    cols = [c[0] for c in cur.description]
    rows = df.collect()
    assert sorted(cols) == sorted(df.columns)
    assert plain(tuple(r[c] for c in cols) for r in rows) == plain(cur.fetchall())
    return rows


@pytest.mark.parametrize(("name", "op", "pick"), [("join_asof_backward", "<=", "max"), ("join_asof_forward", ">=", "min")])
def test_asof_takes_every_order(spark, sf, name, op, pick):
    rows, db = equals_sql(spark, sf, name), database(sf)
    assert len(rows) == db.execute("select count(*) from orders").fetchone()[0]
    slow = db.execute(f"select o_orderkey, (select {pick}(l_shipdate) from lineitem where l_suppkey = o_custkey and l_shipdate {op} o_orderdate) from orders").fetchall()
    assert plain((r["o_orderkey"], r["at"]) for r in rows) == plain(slow)
    assert any(r["at"] is None for r in rows) and any(r["at"] for r in rows)


@pytest.mark.parametrize("how", ["left", "right", "full"])
def test_outer_joins_take_every_row(spark, sf, how):
    rows, db = equals_sql(spark, sf, f"join_{how}"), database(sf)
    assert sum(r["n"] for r in rows) == db.execute("select count(*) from orders").fetchone()[0]
    if how != "right":
        assert len({r["c_custkey"] for r in rows} - {None}) == db.execute("select count(*) from customer").fetchone()[0]


def test_value_blindness_takes_whole_streams(spark):
    db = database("/root/testdata/sf0.01")
    n = db.execute("select count(*) from events").fetchone()[0]
    blocks = db.execute("select count(distinct event_id // 10) from events").fetchone()[0]
    rows = entry.queries()["experiment_value_blindness"](spark, "/root/testdata/sf0.01").collect()
    assert {r["n"] for r in rows if r["stream"] == "rate_block"} == {blocks}
    events = [r for r in rows if r["stream"] != "rate_block"]
    assert {r["n"] for r in events} == {n} and len({r["stream"] for r in events}) == 5
    longest = [r["bytes"] for r in events if r["k"] == 2000]
    assert len(longest) == 5 and max(longest) == min(longest)


FULL = {"halve": ex.halve, "boundary": ex.boundary, "encoders": ex.encoder_study, "range_size": ex.range_size, "agg_bytes": ex.agg_vo, "percentile_budget": ex.percentile_contrast, "tamper": ex.tamper, "construction": ex.construction}


@pytest.mark.parametrize("name", FULL)
def test_experiments_are_registered_with_their_defaults(name):
    assert catalogue.QUERIES[f"experiment_{name}"] is FULL[name]


def test_encoder_study_reports_unmatched_counts(spark, sf):
    rows = ex.encoder_study(spark, sf, ("rate_block",), (0.9,), rounds=1).collect()
    assert {r["policy"] for r in rows} == {"uniform", "learned", "adversarial", "edge_aware"}
    assert all(r["matched"] == (abs(r["s"] - r["target"]) <= 0.02 * r["target"]) for r in rows)
    assert all(r["matched"] for r in rows if r["policy"] == "uniform")


@pytest.mark.parametrize("name", ["arrival_inversion", "line_closed_forms", "maths_integer", "planner_choice", "worked_example"])
def test_small_jobs_read_a_given_table(spark, sf, name):
    rows, db = equals_sql(spark, sf, name), database(sf)
    per = "distinct user_id" if name == "worked_example" else "*"
    assert len(rows) == db.execute(f"select count({per}) from events").fetchone()[0]
    assert entry.queries()[name](spark, sf).inputFiles()
    if name == "planner_choice":
        assert {r["path"] for r in rows} == {"exact", "approximate"}
    if name == "line_closed_forms":
        assert min(r["a"] for r in rows) < 0 < max(r["a"] for r in rows)
