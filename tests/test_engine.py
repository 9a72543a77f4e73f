"""Trees, proofs, client checks, segments and streaming on small streams."""

import random

import pytest
from pyspark.sql import functions as F

from tsproof import experiments as ex
from tsproof import streaming
from tsproof.functions import lines
from tsproof.operators import aggtree, approx, attacks, baselines, budget, client, exact, segments, sliding
from tsproof.plans import ordering, streams, workload
from tsproof.sources import scratch, written

REC = "sid string, t long, height long, i int, v long, tags map<string,string>"


def made(spark, values, times=None, sid="a"):
    times = times or list(range(1, len(values) + 1))
    df = spark.createDataFrame([(sid, t, t, k, v, {"k": str(v % 3)}) for k, (t, v) in enumerate(zip(times, values))], REC)
    return written(ordering.assign_positions(df).withColumn("stream", F.lit(sid)))


def prepared(spark, r, fanout=2, **b):
    nodes = written(aggtree.build(aggtree.record_leaves(r), fanout))
    stats = written(streams.statistics(r))
    return ex.with_segments(r, nodes, stats, written(budget.defaults(stats, **b)), fanout)


def ask(spark, *spans, sid="a"):
    return spark.createDataFrame([(q, sid, s, e, e - s + 1) for q, (s, e) in enumerate(spans)], "qid long, sid string, t_s long, t_e long, k long")


@pytest.mark.parametrize("fanout,chunk", [(2, 10), (2, 3), (4, 2), (3, 4)])
def test_window_build_equals_group_build(spark, sf, fanout, chunk):
    leaves = aggtree.record_leaves(streams.stream(spark, sf, "by_type"))
    a, b = written(aggtree.build(leaves, fanout, chunk)), aggtree.build_by_groups(leaves, fanout)
    assert a.exceptAll(b).count() == 0 and b.exceptAll(a).count() == 0


def test_root_ignores_partitioning(spark, sf):
    r = streams.stream(spark, sf, "event_amt")
    roots = {aggtree.roots(aggtree.build(aggtree.record_leaves(x))).first()["eta"] for x in (r, r.repartition(7), r.orderBy(F.desc("v")))}
    assert len(roots) == 1


def test_range_positions_equal_window_positions(spark, sf):
    a, b = (streams.stream(spark, sf, "line_price", mode=m).select("sid", "t", "v", "pos") for m in ("window", "range"))
    assert a.exceptAll(b).count() == 0


def test_one_shuffle_per_pass(spark, sf):
    leaves = aggtree.record_leaves(streams.stream(spark, sf, "event_amt")).select("sid", "idx", "s", "n", "mn", "mx", "t_lo", "t_hi", "w", "eta")
    plan = aggtree.lift(written(leaves), 2, 10)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and plan.count("Sort [") == 1 and plan.count("Window [") >= 10


def test_cover_fetch_has_no_nested_loop(spark, sf):
    p = ex.prepare(spark, sf, "event_amt")
    located = written(exact.locate(ex.queries_of(p, 3), p.records, p.anchors))
    plan = exact.aggregate(located, p.nodes)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "Cartesian" not in plan and "NestedLoop" not in plan


def test_scan_prunes_columns_and_pushes_filters(spark, sf):
    from tsproof.catalogue import scan_filter

    plan = scan_filter(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [" in plan and "GreaterThanOrEqual(ts" in plan and "props" not in plan


def test_small_streams_and_special_windows(spark):
    for n in (1, 2, 3, 5, 9):
        r = made(spark, list(range(10, 10 + n)))
        p = prepared(spark, r)
        spans = [(s, e) for s in range(-1, n + 3) for e in range(s, n + 3)]
        got = {v["qid"]: v for v in client.batch_verify(ex.wire(p, ask(spark, *spans))).collect()}
        for q, (s, e) in enumerate(spans):
            inside = [9 + t for t in range(1, n + 1) if s <= t <= e]
            assert got[q]["accepted"] and (got[q]["s"], got[q]["n"]) == (sum(inside), len(inside)), (n, s, e)


def test_unknown_stream_is_rejected(spark):
    p = prepared(spark, made(spark, [1, 2, 3]))
    assert client.batch_verify(ex.wire(p, ask(spark, (1, 2), sid="zz"))).first()["reason"] == "anchor"


def test_append_equals_rebuild(spark):
    r = made(spark, [x * x % 17 for x in range(41)])
    for f in (2, 3):
        whole = aggtree.build(aggtree.record_leaves(r), f)
        for cut in (1, 8, 31, 40):
            nodes = written(aggtree.build(aggtree.record_leaves(r.where(F.col("pos") < cut)), f))
            grown = aggtree.append(nodes, aggtree.record_leaves(r.where(F.col("pos") >= cut)), f)
            assert grown.exceptAll(whole).count() == 0 and whole.exceptAll(grown).count() == 0
            edge = written(aggtree.spine(nodes, spark.createDataFrame([("a", cut)], "sid string, n long"), f))
            assert edge.groupBy("lvl").count().where(F.col("count") >= f).count() == 0 and edge.agg(F.sum("n")).first()[0] == cut
            grown = aggtree.grow(edge, aggtree.record_leaves(r.where(F.col("pos") >= cut)), f)
            assert grown.exceptAll(whole).count() == 0


def _proof(p, q, approximate=False):
    w = ex.approx_wire(p, q) if approximate else ex.wire(p, q)
    return w.first().asDict(recursive=True)


def test_every_forgery_is_caught_as_expected(spark):
    p = prepared(spark, made(spark, [100 + x * x % 37 for x in range(80)], [10 * x for x in range(80)]))
    q = ask(spark, (200, 600))
    o = prepared(spark, made(spark, [7 + x for x in range(80)], [10 * x for x in range(80)], sid="b"))
    past = p.records.where("pos < 70")
    older = exact.to_wire(exact.prove_aggregate(exact.locate(q, past), aggtree.build(aggtree.record_leaves(past)), past), q, p.anchors).first().asDict(recursive=True)["proof"]
    r = _proof(p, q) | {"other_proof": _proof(o, ask(spark, (200, 600), sid="b"))["proof"], "older_proof": older}
    for kind, expected in attacks.EXACT.items():
        v = attacks.forge_exact(kind, r, r["proof"], r["anchor"])
        assert not v.accepted and v.reason in expected, kind
    full = exact.to_wire(exact.prove_range(exact.locate(q, p.records, p.anchors), p.nodes, p.records), q, p.anchors).first().asDict(recursive=True)
    for kind, expected in attacks.RANGE.items():
        assert attacks.forge_range(kind, full, full["proof"], full["anchor"]).reason in expected
    opened = ex.range_wire(p, q).first().asDict(recursive=True)
    for kind, expected in attacks.APPROX_RANGE.items():
        assert attacks.forge_approx_range(kind, opened, opened["proof"], opened["anchor"]).reason in expected
    a = _proof(p, q, True)
    for kind, expected in attacks.APPROX.items():
        v = attacks.forge_approx(kind, a, a["proof"], a["anchor"])
        assert not v.accepted and v.reason in expected, kind


def test_negative_controls(spark):
    """Without time extents a stretched cover passes; with a reported cap instead of the anchored one MAX can be wrong."""
    p = prepared(spark, made(spark, [5] * 30 + [9] * 30, [10 * x for x in range(60)]), v_frac=0.5)
    r = _proof(p, ask(spark, (100, 400)))
    stretched = {**r, "t_s": r["t_s"] + 1}
    assert client.verify(stretched, r["proof"], r["anchor"]).reason == "covering"
    assert client.verify(stretched, r["proof"], r["anchor"], extent=False).accepted
    pieces = lines.Pieces(total=0, sure=1, lo=0, hi=0, any_lo=0, any_hi=0)
    truth = 3 * lines.V  # within the anchored bound of 4, outside a reported one of 2
    assert lines.bounds(pieces, "MAX", 4 * lines.V)[1] * lines.V >= truth > lines.bounds(pieces, "MAX", 2 * lines.V)[1] * lines.V


def test_bit_flips_are_rejected(spark):
    rng = random.Random(0)
    p = prepared(spark, made(spark, [x * 7 % 23 for x in range(50)]))
    r = _proof(p, ask(spark, (11, 37)))
    assert client.verify(r, r["proof"], r["anchor"]).accepted
    for _ in range(150):
        items = [client.plain(dict(x)) for x in r["proof"]]
        x = rng.choice(items)
        field = rng.choice(["eta", "idx", "lvl", "alpha", "rec"])
        if x.get(field) is None:
            continue
        if field == "eta":
            k = rng.randrange(64)
            x["eta"] = x["eta"][:k] + ("0" if x["eta"][k] != "0" else "1") + x["eta"][k + 1 :]
        elif field in ("idx", "lvl"):
            x[field] += rng.choice([-1, 1])
        elif field == "alpha":
            x["alpha"][rng.choice(list(x["alpha"]))] += rng.choice([-1, 1])
        else:
            x["rec"][rng.choice(["t", "height", "i", "v"])] += rng.choice([-1, 1])
        assert not client.verify(r, items, r["anchor"]).accepted


def test_greedy_lines_are_minimal():
    rng = random.Random(1)
    for _ in range(15):
        v = [rng.randint(0, 30) for _ in range(60)]
        import numpy as np

        found = segments.encode_chunk(np.arange(60) * 10, np.array(v), np.full(60, 3.0), np.full(60, 1.0), 10.0, "hull")
        assert len(found) == segments.minimal_count(v, 3.0)
        assert sum(x[1] for x in found) == 60


def test_certification(spark):
    rng = random.Random(2)
    p = prepared(spark, made(spark, [rng.randint(0, 100) for _ in range(200)], sorted(rng.sample(range(5000), 200))))
    assert segments.replay(p.segments, p.records).where("not valid").count() == 0
    for kind in segments.CORRUPTIONS:
        assert segments.replay(segments.bad_encoder(p.segments, kind), p.records).where("not valid").count() > 0, kind


@pytest.mark.parametrize("shape", ["ties", "signed", "one_line", "constant_jitter", "spike", "regular"])
def test_intervals_hold_the_exact_answer(spark, shape):
    rng = random.Random(3)
    n = 120
    times, values = [100 * x for x in range(n)], [rng.randint(0, 50) for _ in range(n)]
    if shape == "ties":
        times = sorted(rng.choice(range(0, 4000, 100)) for _ in range(n))
    elif shape == "signed":
        values = [(-1) ** k * rng.randint(1, 60) for k in range(n)]
    elif shape == "one_line":
        values = [3 * k + 7 for k in range(n)]
    elif shape == "constant_jitter":
        times, values = [100 * x + rng.randint(-40, 40) for x in range(n)], [7] * n
    elif shape == "spike":
        values = [5] * 60 + [500] + [5] * 59
    r = made(spark, values, times)
    p = prepared(spark, r, t_units=1.0)
    spans = [sorted((rng.randint(-50, times[-1] + 50), rng.randint(-50, times[-1] + 50))) for _ in range(60)]
    out = ex.intervals(p, ask(spark, *spans)).collect()
    assert len(out) == 300 and all(x["accepted"] and x["inside"] for x in out)
    assert all(x["undecided"] <= x["k_formula"] + 2 for x in out)
    if shape == "one_line":
        assert p.segments.count() == 1 and p.segments.first()["eps_v"] == 0


def test_edges_by_brute_force():
    rng = random.Random(4)
    for _ in range(300):
        mu, beta, c = rng.randint(1, 40) * lines.T, rng.randint(-5, 5) * lines.T, rng.randint(1, 40)
        eps = rng.randint(0, 60)
        t = []
        for p in range(c):
            t.append(max(100 + (mu * p + beta) // lines.T + rng.randint(-eps, eps), t[-1] if t else 100))
        bound = max(abs(mu * p + beta - (x - 100) * lines.T) for p, x in enumerate(t))
        g = {"c": c, "mu": mu, "beta": beta, "eps_t": bound, "tau_lo": min(100, t[0]), "tau_hi": t[-1] + 1}
        if g["tau_lo"] != 100:
            continue
        s = rng.randint(90, t[-1] + 10)
        e = rng.randint(s, t[-1] + 20)
        run = lines.resolve(g, s, e)
        inside = {p for p, x in enumerate(t) if s <= x <= e}
        assert set(range(run.p0, run.p1 + 1)) <= inside <= set(range(run.q0, run.q1 + 1))


def test_sliding_caches(spark):
    p = prepared(spark, made(spark, [x % 11 for x in range(200)]))
    seq = spark.createDataFrame([(1, "a", 20, 60, 4, 20), (2, "a", 10, 90, 25, 4)], "seq_id long, sid string, t_s long, t_e long, delta long, count long")
    w = written(workload.sliding(spark, seq))
    vo = written(exact.prove_aggregate(exact.locate(w, p.records, p.anchors), p.nodes, p.records))
    fresh = {}
    for cache in ("all", "current"):
        out = sliding.verify_sequence(vo, w, p.anchors, cache).collect()
        assert all(x["accepted"] for x in out) and len(out) == 24
        starts = {1: (20, 60, 4), 2: (10, 90, 25)}
        for x in out:
            s, e, dlt = starts[x["seq_id"]]
            assert x["s"] == sum((t - 1) % 11 for t in range(s + dlt * x["i"], min(e + dlt * x["i"], 200) + 1))
        fresh[cache] = sliding.delta_proofs(vo, w, cache).where("fresh").count()
    assert fresh["all"] < fresh["current"] < vo.count()


def test_reconstruction_and_edge_sets(spark):
    p = prepared(spark, made(spark, [x * x % 29 for x in range(100)], [10 * x for x in range(100)]))
    r = approx.reconstruct(p.segments).join(p.records, ["sid", "pos"])
    assert r.count() == 100 and r.where(f"v * {lines.V} not between v_lo and v_hi or t * cast({lines.T} as decimal(19,0)) not between t_lo and t_hi").count() == 0
    q = ask(spark, (95, 605))
    padded, tau = (approx.edge_set(p.segments, q, rule).first()["edge"] for rule in ("padded", "tau"))
    assert tau <= 2 and padded >= tau


def test_policies_order(spark, sf):
    p = ex.prepare(spark, sf, "event_amt")
    found = ex.policies(p, 0.9, 20)
    hot = {k: b.where("region = 5").first()["eps_v"] for k, (b, _) in found.items()}
    assert hot["learned"] < hot["uniform"] < hot["adversarial"]


def test_streamed_tree_quarantine_and_restart(spark, sf):
    source, target = scratch(spark), scratch(spark)
    r = streams.STREAMS["by_type"](spark, sf)
    r.where("height < 20").coalesce(1).write.parquet(source)
    streaming.ingest(spark, source, target)
    r.where("height >= 20 and height < 40 and sid != 'click'").coalesce(1).write.mode("append").parquet(source)
    streaming.ingest(spark, source, target)
    r = r.where("height < 20 or height >= 40 or sid != 'click'")
    late = r.where("height = 3").limit(2)
    r.where("height >= 40").unionByName(late).coalesce(1).write.mode("append").parquet(source)
    batches = streaming.ingest(spark, source, target)  # restarts from the checkpoint
    expected = aggtree.roots(aggtree.build(aggtree.record_leaves(ordering.assign_positions(r))))
    got = aggtree.roots(streaming.TreeSink(target).nodes(spark, batches))
    assert got.exceptAll(expected).count() == 0 and got.count() == expected.count()
    assert spark.read.parquet(*[f"{target}/quarantine/batch_id={b}" for b in range(batches)]).count() == 2


def test_stateful_frontier_equals_batch(spark, sf):
    source = scratch(spark)
    r = streams.STREAMS["by_type"](spark, sf)
    for lo, hi in ((0, 30), (31, 60), (61, 10**9)):
        r.where(F.col("height").between(lo, hi)).coalesce(1).write.mode("append").parquet(source)
    roots = streaming.append_frontier(streaming.read_blocks(spark, source))
    name = "frontier_roots"
    q = roots.writeStream.format("memory").queryName(name).outputMode("update").trigger(availableNow=True).start()
    q.awaitTermination()
    last = spark.table(name).groupBy("sid").agg(F.max_by("root", "n").alias("root"))
    expected = aggtree.roots(aggtree.build(aggtree.record_leaves(ordering.assign_positions(r)))).select("sid", F.col("eta").alias("root"))
    assert last.exceptAll(expected).count() == 0 and last.count() == 5


def test_streaming_dedup_and_windows(spark, sf):
    source = scratch(spark)
    e = spark.read.parquet(f"{sf}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"), streams.cents("value").alias("v"))
    e.unionByName(e.limit(50)).coalesce(1).write.parquet(source)
    s = streaming.with_late_policy(spark.readStream.schema(e.schema).parquet(source), "ts", "40 days")
    q = streaming.dedup(s, "event_id").writeStream.format("memory").queryName("deduped").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("deduped").count() == e.count()
    assert streaming.window_agg(e, "ts", "v").agg(F.sum("n")).first()[0] == e.count()


def _plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_no_stream_in_one_task(spark, sf):
    """Records are never gathered or windowed by stream alone, nor sent to one partition."""
    import re

    r = streams.stream(spark, sf, "state_balance")
    seg = segments.greedy(r, written(budget.defaults(written(streams.statistics(r)))))
    for df in (r, ordering.before(r, "t", "before"), seg, segments.replay(written(seg), r), ordering.ranks(ask(spark, (1, 2), sid="all").select(F.col("qid").cast("string").alias("key"), "sid", F.col("t_s").alias("x")), r, "t")):
        plan = _plan(df)
        assert "SinglePartition" not in plan
        # windows by sid alone run over tables of one row per chunk or partition only
        assert not re.search(r"windowspecdefinition\(sid#\d+, (pos|t|j|pos_lo)#", plan)


def test_order_helpers_are_brute_force(spark):
    rng = random.Random(3)
    rows = [(rng.choice(["a", "b", None]), rng.randint(0, 40), k) for k in range(300)]
    df = spark.createDataFrame(rows, "sid string, x long, k long")
    got = {r["k"]: r["pos"] for r in ordering.number(df, ["sid"], ["x", "k"]).collect()}
    want = {}
    for sid in ("a", "b", None):
        want |= {k: n for n, (_, k) in enumerate(sorted((x, k) for s, x, k in rows if s == sid))}
    assert got == want
    q = {r["sid"]: (r["m"], r["h"]) for r in ordering.quantiles(df.where("sid is not null"), ["sid"], {"m": ("x", 0.5), "h": ("k", 0.99)}).collect()}
    import numpy as np

    for sid in ("a", "b"):
        assert q[sid] == pytest.approx((np.quantile([x for s, x, _ in rows if s == sid], 0.5), np.quantile([k for s, _, k in rows if s == sid], 0.99)))
    edges = [(str(n), rng.choice("ab"), rng.randint(-5, 50)) for n in range(30)]
    ranks = ordering.ranks(spark.createDataFrame(edges, "key string, sid string, x long"), df.where("sid is not null"), "x")
    assert {r["key"]: r["rank"] for r in ranks.collect()} == {k: sum(s == sid and y < x for s, y, _ in rows) for k, sid, x in edges}


def test_replay_is_exact_beyond_64_bits(spark):
    """A slope whose products leave 64 bits (and would wrap to a small residual) is replayed in whole numbers."""
    p = prepared(spark, made(spark, [100] * 40, [10 * x for x in range(40)]))
    assert segments.replay(p.segments, p.records).where("not valid").count() == 0
    wrapped = p.segments.withColumn("a", F.lit(1 << 62))  # 4 * 2**62 is 0 in 64 bits
    assert {r["reason"] for r in segments.replay(wrapped, p.records).collect()} == {"value"}


def test_approximate_retrieval_and_paths(spark):
    p = prepared(spark, made(spark, [100 + x * x % 37 for x in range(80)], [10 * x + x % 3 for x in range(80)]))
    q = ask(spark, (200, 600), (-50, -1), (0, 5000), (205, 206))
    got = ex.retrieved(p, q).collect()
    assert all(r["accepted"] for r in got) and all(r["v_inside"] and r["t_inside"] for r in got if r["pos"] is not None)
    w = exact.prove_range(exact.locate(q, p.records, p.anchors), p.nodes, p.records).where("role = 'record'")
    assert {(r["qid"], r["idx"]) for r in w.collect()} == {(r["qid"], r["pos"]) for r in got if r["pos"] is not None}
    located = exact.locate(q, p.records, p.anchors)
    wire = baselines.paths_wire(baselines.prove_paths(located, p.nodes, p.records), q, p.anchors)
    paths, folded = ({r["qid"]: (r["accepted"], r["s"], r["n"]) for r in df.collect()} for df in (client.batch_paths(wire), client.batch_verify(ex.wire(p, q))))
    assert paths == folded
    one = next(r.asDict(recursive=True) for r in wire.collect() if r["qid"] == 0)
    one["entries"][3]["rec"]["v"] += 1
    assert client.verify_paths(one, one["entries"], one["anchor"]).reason == "root"
    del one["entries"][3]
    assert client.verify_paths(one, one["entries"], one["anchor"]).reason == "covering"


def test_release_deletes_scratch(spark):
    from tsproof import sources

    made_by = dict(sources._made)
    sources._made.clear()
    df = written(spark.range(5))
    assert df.count() == 5 and sources.release(spark) == 1
    sources._made.update(made_by)
