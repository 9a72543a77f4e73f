"""Several budgets of a stream in one batch."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from tsproof import experiments as ex
from tsproof.operators import aggtree, budget, segments
from tsproof.plans import streams
from tsproof.sources import written


@pytest.fixture
def encodings(monkeypatch):
    made, greedy = [], segments.greedy
    monkeypatch.setattr(segments, "greedy", lambda *a, **k: made.append(1) or greedy(*a, **k))
    return made


def test_variants_equal_encodings_apart(spark, sf, encodings):
    p = ex.prepare(spark, sf, "rate_block")
    q = ex.queries_of(p, 5, only=[20])
    b = {"half": budget.defaults(p.stats, 0.05, 0.5), "base": p.budgets}
    encodings.clear()
    x = ex.with_variants(p, b)
    assert len(encodings) == 1
    key = lambda rows: sorted((r["qid"], r["f"], r["accepted"], r["lo"], r["hi"], r["width"], r["exact"], r["inside"], r["undecided"]) for r in rows)
    got = ex.variant_intervals(p, x, ex._asked(q, list(b))).collect()
    assert all(r["accepted"] and r["inside"] for r in got)
    for i, (v, budgets) in enumerate(b.items()):
        alone = ex.intervals(ex.with_segments(p.records, p.nodes, p.stats, written(budgets)), q).collect()
        mine = [r.asDict() | {"qid": (r["qid"] - i) // len(b)} for r in got if r["variant"] == v]
        assert key(mine) == key(alone)


@pytest.mark.parametrize(("run", "most"), [("boundary", 1), ("halve", 1), ("percentile_contrast", 1)])
def test_one_encoding_a_stream(spark, sf, encodings, run, most):
    ex.prepare(spark, sf, "rate_block")
    encodings.clear()
    assert getattr(ex, run)(spark, sf, names=("rate_block",)).count() > 0
    assert len(encodings) == most


def test_all_policies_are_matched_in_few_batches(spark, sf, encodings):
    ex.prepare(spark, sf, "rate_block")
    encodings.clear()
    rows = ex.encoder_study(spark, sf, ("rate_block",), (0.5, 0.9)).collect()
    assert len(rows) == 8 and all(r["inside"] for r in rows) and len(encodings) <= 14  # target, 12 rounds, the measure
    assert all(r["vs_uniform"] is not None for r in rows if r["policy"] == "uniform")


def test_fold_equals_window_pass(spark, sf):
    leaves = aggtree.record_leaves(ex.prepare(spark, sf, "event_amt").records)
    a = written(aggtree.fold(leaves, 2, 4)).select("sid", "lvl", "idx", "s", "n", "mn", "mx", "t_lo", "t_hi", "w", "eta")
    b = written(aggtree.lift(leaves, 2, 4)).where("lvl > 0").select(*a.columns)
    assert a.exceptAll(b).count() == 0 and b.exceptAll(a).count() == 0


@pytest.mark.parametrize("f", [2, 3])
def test_a_shortened_tree_is_the_tree_of_the_prefix(spark, f):
    sizes = {f"{n}-{m}": (n, m) for n, m in ((1, 1), (9, 1), (9, 8), (30, 17), (30, 27), (100, 64), (100, 99), (100, 100))}
    rows = [(sid, i, 10 * i, i, 0, i * 7 % 13 - 5, {"a": "b"}) for sid, (n, _) in sizes.items() for i in range(n)]
    r = spark.createDataFrame(rows, "sid string, pos long, t long, height long, i int, v long, tags map<string,string>")
    of = spark.createDataFrame([(sid, m) for sid, (_, m) in sizes.items()], "sid string, n long")
    got = aggtree.shortened(aggtree.build(aggtree.record_leaves(r), f), of, f)
    true = aggtree.build(aggtree.record_leaves(r.join(of, "sid").where("pos < n").drop("n")), f)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, true.collect()))


def test_tamper_builds_all_streams_in_one_batch(spark, sf, monkeypatch):
    built, build = [], aggtree.build
    monkeypatch.setattr(aggtree, "build", lambda *a, **k: built.append(1) or build(*a, **k))
    rows = ex.tamper(spark, sf, ("event_amt", "const_unit"), 2).collect()
    assert len(built) == 2  # records and segments of both streams; their past isn't built again
    assert {r["stream"] for r in rows} == {"event_amt", "const_unit"} and len(rows) == 2 * 20
    assert all(r["attempts"] == r["rejected"] == r["as_expected"] == 2 for r in rows)


@pytest.mark.parametrize(("gaps", "eps_t"), [((1, 20), 2.5), ((0, 3), 30.0), ((0, 1), 0.0)])
def test_side_by_side_growth_equals_growth_alone(gaps, eps_t, monkeypatch):
    rng = np.random.default_rng(5)
    for n in (1, 2, 300):
        t = np.cumsum(rng.integers(*gaps, n))
        for v in (rng.integers(-50, 50, n), np.cumsum(rng.integers(-5, 6, n)), np.ones(n, np.int64)):
            args = (t, v, np.full(n, 3.0), np.full(n, eps_t), 5.0, "hull")
            both = segments.encode_chunk(*args)
            with monkeypatch.context() as m:
                m.setattr(segments, "_grow_all", lambda t, *_: (np.zeros(len(t), np.int64), *[np.zeros(len(t))] * 4))
                assert both == segments.encode_chunk(*args)
            assert sum(x[1] for x in both) == n


def test_growth_side_by_side_takes_all_short_segments():
    t = np.arange(5000) * 10 + np.arange(5000) % 7
    v = np.where(np.arange(5000) % 3, 0, 100)
    assert segments._grow_all(t, v, np.full(5000, 1.0), np.full(5000, 5.0))[0].all()


def test_counts_are_those_of_the_segments(spark, sf):
    p = ex.prepare(spark, sf, "event_amt")
    b = written(ex._marked(p.budgets, ["a"]).unionByName(ex._marked(budget.scaled(p.budgets, 3.0), ["b"])))
    made = {r["sid"]: r["count"] for r in segments.greedy(p.records, b, variants=True).groupBy("sid").count().collect()}
    assert made == {r["sid"]: r["count"] for r in segments.counts(p.records, b, variants=True).collect()} and len(made) == 2


def test_encoder_study_matches_all_streams_in_the_same_rounds(spark, sf, monkeypatch):
    rounds, built, counts, build = [], [], segments.counts, aggtree.build
    monkeypatch.setattr(segments, "counts", lambda *a, **k: rounds.append(1) or counts(*a, **k))
    monkeypatch.setattr(aggtree, "build", lambda *a, **k: built.append(1) or build(*a, **k))
    rows = ex.encoder_study(spark, sf, ("rate_block", "const_unit"), (0.5, 0.9), rounds=3).collect()
    assert {r["stream"] for r in rows} == {"rate_block", "const_unit"} and len(rows) == 16
    assert all(r["inside"] for r in rows) and len(rounds) <= 4 and len(built) <= 2


def test_fold_by_columns_equals_fold_by_rows():
    for f, levels in ((2, 3), (4, 2)):
        rows = [(sid, i, 10**e * (i - 3), 1, i % 5 - 2, i % 7, i, i + 1, i, f"h{i}") for sid, n, e in (("a", 1, 0), ("b", 37, 0), ("c", 9, 18)) for i in range(n)]
        names = ["sid", "idx", "s", "n", "mn", "mx", "t_lo", "t_hi", "w", "eta"]
        table = pa.table({c: pa.array([str(x) for x in v] if c in ("s", "w") else list(v)) for c, v in zip(names, zip(*rows))})
        want = [tuple(r.values()) for r in aggtree._batch(list(aggtree._fold_chunks(rows, f, levels))).to_pylist()]
        assert [tuple(r.values()) for r in aggtree._fold_table(table, f, levels).to_pylist()] == want


def test_several_streams_are_the_streams(spark, sf):
    names = ("rate_block", "event_tail", "event_amt", "state_balance", "const_unit")
    got = streams.several(spark, sf, names)
    for x in names:
        one = streams.stream(spark, sf, x).select(F.concat_ws("|", F.lit(x), "sid"), "pos", "t", "height", "i", "v", F.to_json("tags"))
        mine = got.where(F.col("stream") == x).select("sid", "pos", "t", "height", "i", "v", F.to_json("tags"))
        assert sorted(map(tuple, mine.collect())) == sorted(map(tuple, one.collect()))


def test_boundary_builds_all_streams_in_one_batch(spark, sf, encodings, monkeypatch):
    built, build = [], aggtree.build
    monkeypatch.setattr(aggtree, "build", lambda *a, **k: built.append(1) or build(*a, **k))
    encodings.clear()
    rows = ex.boundary(spark, sf, ("event_amt", "const_unit"), (0.5, 2.0), 5).collect()
    assert len(rows) == 4 and all(r["inside"] for r in rows)
    assert len(encodings) == 1 and len(built) == 2  # records and segments of both streams under both budgets
