"""Registered queries against their SQL on the smallest tables."""

import os

import duckdb
import pytest

import __spark_entry__ as entry

FAST = ["stream_records", "stream_stats", "block_headers", "positions_with_ties", "tree_root_fanout4", "cover_keys", "locate_fence", "agg_order_price", "agg_edge_cases", "verify_agg_event_amt", "tagged_in", "approx_avg", "baseline_paths", "approx_range_rate_block", "tagged_or", "udf_verify", "baseline_paths_verified", "join_asof_backward", "join_full", "win_frames", "window_session", "set_except_all", "json_tags", "roundtrip_orc", "worked_example", "stream_enrich", "windows_by_time", "seg_external_encoder"]


def plain(rows):
    def one(x):
        return "N" if x is None or x != x else repr(round(float(x), 6)) if isinstance(x, (int, float)) and not isinstance(x, bool) else str(x)

    return sorted(tuple(one(x) for x in r) for r in rows)


@pytest.mark.parametrize("name", FAST)
def test_query_equals_sql(spark, sf, name):
    db = duckdb.connect()
    for t in os.listdir(sf):
        db.execute(f"create view {t.removesuffix('.parquet')} as select * from '{sf}/{t}'")
    df = entry.queries()[name](spark, sf)
    cur = db.execute(entry.oracle_sql()[name])
    cols = [c[0] for c in cur.description]
    assert sorted(cols) == sorted(df.columns)
    assert plain(tuple(r[c] for c in cols) for r in df.collect()) == plain(cur.fetchall())


def test_entry_has_rows(spark):
    assert entry.entry(spark).where("accepted").count() > 0


def test_library_stands_without_the_training_subpackage():
    root = os.path.dirname(os.path.abspath(entry.__file__))
    for folder, _, files in os.walk(os.path.join(root, "tsproof")):
        if os.sep + "llm" not in folder:
            for f in files:
                if f.endswith(".py"):
                    assert "tsproof.llm" not in open(os.path.join(folder, f)).read()
