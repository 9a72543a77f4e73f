"""Experiment workloads over the given tables; each returns one tidy DataFrame."""

from __future__ import annotations

import time
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tsproof.operators import aggtree, approx, attacks, baselines, budget, client, costs, exact, segments, sliding
from tsproof.plans import ordering, planner, streams, workload
from tsproof.sources import fingerprint, written

LENGTHS = [100, 200, 500, 1000, 2000]
SMALL = [20, 50, 100, 200, 500]


@dataclass
class Prepared:
    """Written tables of one stream: records, tree, statistics, budgets, segments, segment tree, anchors."""

    records: DataFrame
    nodes: DataFrame
    stats: DataFrame
    budgets: DataFrame
    segments: DataFrame
    seg_nodes: DataFrame
    anchors: DataFrame
    n: int


_held: dict[tuple, Prepared] = {}


def prepare(spark: SparkSession, d: str, name: str, fanout: int = 2, limit: int | None = None) -> Prepared:
    """Builds a stream's tables once per session and state of the input's files."""
    key = (spark.sparkContext.applicationId, d, fingerprint(spark, d), name, fanout, limit)
    if key not in _held:
        r = streams.stream(spark, d, name)
        r = written(streams.prefix(r, limit) if limit else r)
        nodes = written(aggtree.build(aggtree.record_leaves(r), fanout))
        stats = written(streams.statistics(r))
        b = written(budget.defaults(stats))
        _held[key] = with_segments(r, nodes, stats, b, fanout)
    return _held[key]


def with_segments(r: DataFrame, nodes: DataFrame, stats: DataFrame, b: DataFrame, fanout: int = 2, fit: str = "hull") -> Prepared:
    seg = written(segments.greedy(r, b, fit))
    seg_nodes = written(aggtree.build(aggtree.segment_leaves(seg), fanout))
    anchors = written(aggtree.anchor(nodes, seg_nodes, seg, fanout))
    return Prepared(r, nodes, stats, b, seg, seg_nodes, anchors, r.count())


def _marked(df: DataFrame, variants: list[str]) -> DataFrame:
    """Every row once per variant, as rows of the stream ``variant|sid``."""
    each = F.explode(F.array(*[F.lit(x) for x in variants]))
    return df.withColumn("_variant", each).withColumn("sid", F.concat_ws("|", "_variant", "sid")).drop("_variant")


def _base() -> Column:
    """The sid of a variant's stream."""
    return F.expr("substring(sid, instr(sid, '|') + 1)")


def with_variants(p: Prepared, budgets: dict[str, DataFrame]) -> Prepared:
    """A stream's segments under several budgets, encoded, hashed and anchored in one batch: a variant is a stream of its own
    (``variant|sid``).  Records and nodes stay those of the stream."""
    return with_marked(p, written(_all([_marked(x, [v]) for v, x in budgets.items()])))


def with_marked(p: Prepared, b: DataFrame) -> Prepared:
    """The same for budgets whose sids are ``variant|sid`` already, of one stream or of several that were built together."""
    seg = written(segments.greedy(p.records, b, variants=True))
    seg_nodes = written(aggtree.build(aggtree.segment_leaves(seg)))
    asked = b.select("sid", _base().alias("_of")).distinct()
    roots = aggtree.roots(p.nodes).withColumnRenamed("sid", "_of").join(asked, "_of").drop("_of").withColumn("lvl", F.lit(0))
    return Prepared(p.records, p.nodes, p.stats, b, seg, seg_nodes, written(aggtree.anchor(roots, seg_nodes, seg)), p.n)


def _asked(q: DataFrame, variants: list[str]) -> DataFrame:
    """Windows once per variant: qid * variants + i, with the variant and its window's own ``base``."""
    each = F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(x).alias("variant")) for i, x in enumerate(variants)]))
    out = q.withColumn("_x", each).withColumns({"base": F.col("qid"), "variant": F.col("_x.variant"), "qid": F.col("qid") * len(variants) + F.col("_x.i")})
    return out.withColumn("sid", F.concat_ws("|", "variant", "sid")).drop("_x")


def variant_intervals(p: Prepared, x: Prepared, asked: DataFrame) -> DataFrame:
    """Derived intervals of all variants ``x`` of a stream ``p`` beside exact answers; ``asked`` comes from ``_asked``."""
    asked = written(asked)
    base = asked.select(F.col("base").alias("qid"), _base().alias("sid"), "t_s", "t_e").dropDuplicates(["qid"])
    answers = exact.aggregate(exact.locate(base, p.records, p.anchors), p.nodes).drop("sid").withColumnRenamed("qid", "base")
    answers = answers.join(asked.select("qid", "base", "sid"), "base").drop("base")
    found = client.batch_approx(approx_wire(x, asked)).join(asked.select("qid", "sid", "k", "variant"), "qid")
    return costs.width_units(costs.containment(found, answers), x.budgets)


def _counts(x: Prepared) -> DataFrame:
    """Segments per variant."""
    return x.segments.groupBy(F.substring_index("sid", "|", 1).alias("variant")).agg(F.count("*").alias("s"))


def _all(frames: list[DataFrame]) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), frames)


def lengths(n: int) -> list[int]:
    return [k for k in (LENGTHS if n > 2000 else SMALL) if k < n]


def queries_of(p: Prepared, count: int = 20, seed: int = 1, only: list[int] | None = None) -> DataFrame:
    return written(workload.windows(p.records, only or lengths(p.n), count, seed))


def wire(p: Prepared, q: DataFrame, located: DataFrame | None = None) -> DataFrame:
    located = exact.locate(q, p.records, p.anchors) if located is None else located
    return exact.to_wire(exact.prove_aggregate(located, p.nodes, p.records), q, p.anchors)


def approx_wire(p: Prepared, q: DataFrame) -> DataFrame:
    return exact.to_wire(approx.prove_aggregate(approx.locate(q, p.segments), p.seg_nodes, p.segments), q, p.anchors)


def range_wire(p: Prepared, q: DataFrame) -> DataFrame:
    """Range retrieval over segments: every covering segment opened."""
    return exact.to_wire(approx.prove_range(approx.locate(q, p.segments), p.seg_nodes, p.segments), q, p.anchors)


def retrieved(p: Prepared, q: DataFrame) -> DataFrame:
    """Per record of the windows: what the client rebuilt from segment proofs alone holds its value and time; and any
    record that the client takes for certain though it isn't in the window (null flags)."""
    located = exact.locate(q, p.records, p.anchors)
    true = exact.prove_range(located, p.nodes, p.records).where("role = 'record'").select("qid", F.col("idx").alias("pos"), "rec.t", "rec.v", F.lit(True).alias("real"))
    got = client.batch_approx_range(range_wire(p, q))
    both = true.join(got, ["qid", "pos"], "full").where("real or certain or not accepted")
    inside = lambda x: F.coalesce(F.col(x).between(F.col(f"{x}_lo"), F.col(f"{x}_hi")), F.lit(False)).alias(f"{x}_inside")
    return both.select("qid", "pos", F.coalesce("accepted", F.lit(False)).alias("accepted"), inside("v"), inside("t"))


def intervals(p: Prepared, q: DataFrame) -> DataFrame:
    """Derived intervals beside exact answers."""
    answers = exact.aggregate(exact.locate(q, p.records, p.anchors), p.nodes)
    found = client.batch_approx(approx_wire(p, q)).join(q.select("qid", "sid", "k"), "qid")
    return costs.width_units(costs.containment(found, answers), p.budgets)


def stream_table(spark: SparkSession, d: str, names: tuple[str, ...] = streams.MAIN) -> DataFrame:
    """Records, gaps, variation and records per segment of each stream."""
    return _all([streams.statistics(p.records, p.segments).select("stream", "n", "mean_gap", "median_gap", "cv", "s", "per_segment") for p in (prepare(spark, d, x) for x in names)])


def touched(spark: SparkSession, d: str, names: tuple[str, ...] = ("rate_block", "event_amt")) -> DataFrame:
    """Tree nodes against records per window length."""
    out = []
    for name in names:
        p = prepare(spark, d, name)
        q = queries_of(p)
        a = exact.aggregate(exact.locate(q, p.records, p.anchors), p.nodes).join(q.select("qid", "k"), "qid")
        out.append(a.groupBy("k").agg(F.avg("touched").alias("nodes"), F.avg("n").alias("records")).select(F.lit(name).alias("stream"), "k", "nodes", "records", (F.col("records") / F.col("nodes")).alias("fewer")))
    return _all(out)


def latency(spark: SparkSession, d: str, name: str = "rate_block", batches: tuple[int, ...] = (40, 2000)) -> DataFrame:
    """Seconds per batch of windows, folded and scanned."""
    p = prepare(spark, d, name)
    k = lengths(p.n)[-1]
    rows = []
    for count in batches:
        located = written(exact.locate(queries_of(p, count, only=[k]), p.records, p.anchors))
        rows.append((name, count, k, costs.timer(lambda x=located: exact.aggregate(x, p.nodes)), costs.timer(lambda x=located: baselines.scan(x, p.records))))
    return spark.createDataFrame(rows, "stream string, windows int, k int, fold_s double, scan_s double")


def proof_size(spark: SparkSession, d: str, names: tuple[str, ...] = ("rate_block", "event_amt"), count: int = 20) -> DataFrame:
    """Bytes per window length: folded proof, download, authenticated leaves, a path per record."""
    out = []
    for name in names:
        p = prepare(spark, d, name)
        q = queries_of(p, count)
        located = written(exact.locate(q, p.records, p.anchors))
        size = lambda df, m: df.select("qid", F.lit(m).alias("method"), "bytes")
        rows = _all([
            size(costs.vo_bytes(exact.prove_aggregate(located, p.nodes, p.records)), "fold"),
            size(baselines.redownload(located, p.records), "download"),
            size(costs.vo_bytes(baselines.leaf_fold(located, p.nodes, p.records)), "leaves"),
            size(baselines.per_record_paths(located), "paths"),
        ])
        out.append(rows.join(q.select("qid", "k"), "qid").groupBy("k").pivot("method", ["fold", "download", "leaves", "paths"]).agg(F.avg("bytes")).withColumn("stream", F.lit(name)))
    return _all(out)


def client_time(spark: SparkSession, d: str, name: str = "rate_block") -> DataFrame:
    """Hashes and milliseconds per verification: folded proof against opened leaves."""
    p = prepare(spark, d, name)
    q = queries_of(p, 5, only=[lengths(p.n)[-1]])
    located = written(exact.locate(q, p.records, p.anchors))
    rows = []
    for method, vo in (("fold", exact.prove_aggregate(located, p.nodes, p.records)), ("leaves", exact.prove_range(located, p.nodes, p.records))):
        proofs = exact.to_wire(vo, q, p.anchors).collect()  # a handful of proofs, checked as a client would
        start = time.perf_counter()
        verdicts = [client.verify(r.asDict(recursive=True), r.asDict(recursive=True)["proof"], r.asDict(recursive=True)["anchor"]) for r in proofs]
        took = (time.perf_counter() - start) * 1000 / max(len(proofs), 1)
        rows.append((name, method, float(sum(v.hashes for v in verdicts)) / max(len(verdicts), 1), took, all(v.accepted for v in verdicts)))
    return spark.createDataFrame(rows, "stream string, method string, hashes double, millis double, accepted boolean")


def sliding_sequences(p: Prepared, k: int, slides: tuple[int, ...] = (10, 20, 30, 40, 50), count: int = 40) -> DataFrame:
    """Sequences of ``count`` windows of about k records, one per slide percentage, within the stream."""
    span = p.records.groupBy("sid").agg(F.min("t").alias("a"), ((F.max("t") - F.min("t")) / F.count("*") * k).cast("long").alias("w"))
    s = span.withColumn("slide", F.explode(F.array(*[F.lit(x) for x in slides])))
    return s.select(F.col("slide").cast("long").alias("seq_id"), "sid", (F.col("a") + F.col("w")).alias("t_s"), (F.col("a") + 2 * F.col("w") - 1).alias("t_e"), (F.col("w") * F.col("slide") / 100).cast("long").alias("delta"), F.lit(count).cast("long").alias("count"))


def sliding_cost(spark: SparkSession, d: str, name: str = "rate_block") -> DataFrame:
    """Independent bytes over delta bytes for both cache scopes."""
    p = prepare(spark, d, name)
    seq = sliding_sequences(p, min(2000, p.n // 40))
    w = written(workload.sliding(spark, seq))
    vo = written(exact.prove_aggregate(exact.locate(w, p.records, p.anchors), p.nodes, p.records))
    return _all([costs.delta_ratio(sliding.delta_proofs(vo, w, c)).withColumn("cache", F.lit(c)) for c in ("all", "current")]).withColumnRenamed("seq_id", "slide")


def together(spark: SparkSession, d: str, names: tuple[str, ...]) -> Prepared:
    """Several streams as one batch, of the sids ``stream|sid``: each step of building runs once for all of them."""
    key = (spark.sparkContext.applicationId, d, fingerprint(spark, d), names, "together")
    if key not in _held:
        p = unsegmented(spark, d, names)
        _held[key] = with_segments(p.records, p.nodes, p.stats, p.budgets)
    return _held[key]


def unsegmented(spark: SparkSession, d: str, names: tuple[str, ...]) -> Prepared:
    """The same without segments, for experiments that encode under budgets of their own; anchors bind the records only."""
    key = (spark.sparkContext.applicationId, d, fingerprint(spark, d), names, "unsegmented")
    if key not in _held:
        r = written(streams.several(spark, d, names))
        nodes = written(aggtree.build(aggtree.record_leaves(r)))
        stats = written(streams.statistics(r))
        _held[key] = Prepared(r, nodes, stats, written(budget.defaults(stats)), None, None, written(aggtree.anchor(nodes)), r.count())
    return _held[key]


def _sizes(p: Prepared) -> dict[str, int]:
    """Records of the longest source of each stream."""
    return {r["stream"]: r["n"] for r in p.stats.groupBy("stream").agg(F.max("n").alias("n")).collect()}


def tamper(spark: SparkSession, d: str, names: tuple[str, ...] = streams.MAIN, count: int = 20) -> DataFrame:
    """Forgeries per stream and kind; all must be rejected.  Streams of one source each, built, cut back to their past,
    asked and forged in one batch."""
    other = {x: o if o != x else next(y for y in streams.MAIN if y != x) for x, o in zip(names, (*names[1:], names[0]))}
    p = together(spark, d, tuple(dict.fromkeys([*names, *other.values()])))
    n = {r["stream"]: r["n"] for r in p.stats.select("stream", "n").collect()}
    k = {x: min(lengths(n[x])[0], lengths(n[o])[0]) for x, o in other.items()}
    stream = F.substring_index("sid", "|", 1)

    def windows(records: DataFrame, asked: dict[str, str]) -> DataFrame:
        """Windows of the streams ``asked`` (stream -> the one whose proofs are forged); ids are unique over the batch."""
        ks = sorted({k[x] for x in asked.values()})
        parts = [workload.windows(records.where(F.col("stream").isin([s for s, x in asked.items() if k[x] == y])), [y], count) for y in ks]
        place = F.create_map(*[F.lit(y) for s, x in asked.items() for y in (s, names.index(x))])[stream]
        return written(_all(parts).withColumn("qid", F.col("qid") * len(names) + place))

    sizes = p.stats.select("sid", F.expr("n - n div 10").alias("n"))  # the past: all but the last tenth
    old = p.records.join(F.broadcast(sizes.select("sid", F.col("n").alias("_n"))), "sid").where("pos < _n").drop("_n")
    q = windows(old, {x: x for x in names})  # windows that the past holds too
    located, near = written(exact.locate(q, p.records, p.anchors)), written(approx.locate(q, p.segments))
    mark = lambda w: w.withColumn("stream", stream)
    proofs = lambda vo, c: vo.groupBy("qid").agg(F.collect_list(F.struct("role", "lvl", "idx", "eta", "alpha", "rec")).alias(c))
    elsewhere = written(exact.locate(windows(p.records, {o: x for x, o in other.items()}), p.records, p.anchors))
    theirs = proofs(exact.prove_aggregate(elsewhere, p.nodes, p.records), "other_proof")
    past = proofs(exact.prove_aggregate(written(exact.locate(q, old)), aggtree.shortened(p.nodes, sizes), old), "older_proof")
    return _all([
        attacks.tamper(mark(wire(p, q, located).join(theirs, "qid").join(past, "qid")), attacks.EXACT, attacks.forge_exact),
        attacks.tamper(mark(exact.to_wire(exact.prove_range(located, p.nodes, p.records), q, p.anchors)), attacks.RANGE, attacks.forge_range),
        attacks.tamper(mark(exact.to_wire(approx.prove_aggregate(near, p.seg_nodes, p.segments), q, p.anchors)), attacks.APPROX, attacks.forge_approx),
        attacks.tamper(mark(exact.to_wire(approx.prove_range(near, p.seg_nodes, p.segments), q, p.anchors)), attacks.APPROX_RANGE, attacks.forge_approx_range),
    ])


def scale(spark: SparkSession, d: str, name: str = "const_unit", sizes: tuple[int, ...] = (1000, 2000, 5000, 10_000, 20_000, 50_000, 100_000), k: int = 500) -> DataFrame:
    """Proof bytes and hashes for prefixes at one window length."""
    whole = prepare(spark, d, name)
    out = []
    for n in (x for x in sizes if x <= whole.n):
        r = written(streams.prefix(whole.records, n))
        nodes = written(aggtree.build(aggtree.record_leaves(r)))
        anchors = aggtree.anchor(nodes)
        q = written(workload.windows(r, [min(k, n // 2)], 20))
        located = exact.locate(q, r, anchors)
        vo = written(exact.prove_aggregate(located, nodes, r))
        v = client.batch_verify(exact.to_wire(vo, q, anchors))
        out.append(costs.vo_bytes(vo).join(v.select("qid", "hashes", "accepted"), "qid").agg(F.lit(n).alias("n"), F.avg("bytes").alias("bytes"), F.avg("hashes").alias("hashes"), F.bool_and("accepted").alias("accepted")))
    return _all(out)


def construction(spark: SparkSession, d: str, names: tuple[str, ...] = streams.MAIN) -> DataFrame:
    """Seconds to encode and to certify by replay."""
    rows = []
    for name in names:
        p = prepare(spark, d, name)
        enc, rep = costs.timer(lambda x=p: segments.greedy(x.records, x.budgets)), costs.timer(lambda x=p: segments.replay(x.segments, x.records))
        rows.append((name, p.n, enc, rep))
    return spark.createDataFrame(rows, "stream string, n long, encode_s double, certify_s double")


def break_even(spark: SparkSession, d: str, names: tuple[str, ...] = streams.MAIN, count: int = 10) -> DataFrame:
    """Range and aggregation proof bytes, exact over approximate, beside the predicted saving."""
    out = []
    for name in names:
        p = prepare(spark, d, name)
        q = queries_of(p, count, only=[lengths(p.n)[-1]])
        located, near = written(exact.locate(q, p.records, p.anchors)), written(approx.locate(q, p.segments))
        mean = lambda vo, c: costs.vo_bytes(vo).agg(F.avg("bytes").alias(c))
        row = mean(exact.prove_range(located, p.nodes, p.records), "range_exact").join(mean(approx.prove_range(near, p.seg_nodes, p.segments), "range_approx")).join(mean(exact.prove_aggregate(located, p.nodes, p.records), "agg_exact")).join(mean(approx.prove_aggregate(near, p.seg_nodes, p.segments), "agg_approx"))
        pred = planner.break_even(streams.statistics(p.records, p.segments))
        out.append(pred.join(row).withColumns({"measured": F.col("range_exact") / F.col("range_approx"), "agg_ratio": F.col("agg_exact") / F.col("agg_approx")}))
    return _all(out)


def _by_length(spark: SparkSession, d: str, names: tuple[str, ...], count: int, exact_vo, approx_vo) -> DataFrame:
    """Mean bytes of an exact and an approximate proof, and their ratio, per stream and window length."""
    out = []
    for name in names:
        p = prepare(spark, d, name)
        q = queries_of(p, count)
        located, near = written(exact.locate(q, p.records, p.anchors)), written(approx.locate(q, p.segments))
        both = costs.vo_bytes(exact_vo(p, located)).select("qid", F.col("bytes").alias("exact")).join(costs.vo_bytes(approx_vo(p, near)).select("qid", F.col("bytes").alias("approx")), "qid")
        mean = both.join(q.select("qid", "k"), "qid").groupBy("k").agg(F.avg("exact").alias("exact_bytes"), F.avg("approx").alias("approx_bytes"))
        out.append(mean.select(F.lit(name).alias("stream"), "k", "exact_bytes", "approx_bytes", (F.col("exact_bytes") / F.col("approx_bytes")).alias("saving")))
    return _all(out)


def range_size(spark: SparkSession, d: str, names: tuple[str, ...] = streams.MAIN, count: int = 20) -> DataFrame:
    """Bytes of range retrieval, exact and over segments, by window length."""
    return _by_length(spark, d, names, count, lambda p, x: exact.prove_range(x, p.nodes, p.records), lambda p, x: approx.prove_range(x, p.seg_nodes, p.segments))


def agg_vo(spark: SparkSession, d: str, names: tuple[str, ...] = streams.MAIN, count: int = 20) -> DataFrame:
    """Bytes of aggregation proofs, exact and over segments, by window length: only a few levels apart."""
    return _by_length(spark, d, names, count, lambda p, x: exact.prove_aggregate(x, p.nodes, p.records), lambda p, x: approx.prove_aggregate(x, p.seg_nodes, p.segments))


def repeats(spark: SparkSession, d: str, name: str = "rate_block", seeds: tuple[int, ...] = (1, 2, 3, 4, 5), count: int = 20) -> DataFrame:
    """The repetition protocol: nodes and bytes per window length, mean over seeds and deviation between their means."""
    p = prepare(spark, d, name)
    # one batch for all seeds: window ids of different seeds don't meet
    q = written(_all([workload.windows(p.records, lengths(p.n), count, s).withColumn("seed", F.lit(s)) for s in seeds]))
    vo = written(exact.prove_aggregate(exact.locate(q, p.records, p.anchors), p.nodes, p.records))
    one = costs.vo_bytes(vo).join(costs.touched(vo), "qid").join(q.select("qid", "k", "seed"), "qid").groupBy("k", "seed").agg(F.avg("touched").alias("nodes"), F.avg("bytes").alias("bytes"), F.count("*").alias("windows"))
    return one.groupBy("k").agg(F.avg("nodes").alias("nodes"), F.stddev_pop("nodes").alias("nodes_dev"), F.avg("bytes").alias("bytes"), F.stddev_pop("bytes").alias("bytes_dev"), F.sum("windows").alias("windows"), F.count("*").alias("seeds")).withColumn("stream", F.lit(name))


def percentile_contrast(spark: SparkSession, d: str, names: tuple[str, ...] = streams.MAIN) -> DataFrame:
    """Budgets from the median against budgets from a high percentile: records per segment and SUM width."""
    out = []
    for name in names:
        p = prepare(spark, d, name)
        q = queries_of(p, 10, only=[lengths(p.n)[1]])
        x = with_variants(p, {"median": p.budgets, "p99": budget.percentile_budget(p.stats)})
        got = variant_intervals(p, x, _asked(q, ["median", "p99"])).where("f = 'SUM'").groupBy("variant").agg(F.avg(F.col("hi") - F.col("lo")).alias("sum_width"), F.bool_and("inside").alias("inside"))
        out.append(got.join(_counts(x), "variant").select("sum_width", "inside", F.lit(name).alias("stream"), F.col("variant").alias("rule"), (F.lit(p.n) / F.col("s")).alias("per_segment")))
    return _all(out)


def boundary(spark: SparkSession, d: str, names: tuple[str, ...] = streams.MAIN, units: tuple[float, ...] = (0.25, 0.5, 1.0, 2.0, 4.0), count: int = 40) -> DataFrame:
    """Undecided records per window over a sweep of the arrival budget."""
    names = tuple(dict.fromkeys(names))
    p = unsegmented(spark, d, names)
    n = _sizes(p)
    of = {k: [x for x in names if lengths(n[x])[0] == k] for k in sorted({lengths(x)[0] for x in n.values()})}
    place = F.create_map(*[F.lit(y) for i, x in enumerate(names) for y in (x, i)])[F.substring_index("sid", "|", 1)]
    q = _all([workload.windows(p.records.where(F.col("stream").isin(x)), [k], count) for k, x in of.items()])
    q = written(q.withColumn("qid", F.col("qid") * len(names) + place))  # ids are unique over the streams
    names_of = {str(u): u for u in units}
    x = with_variants(p, {v: budget.defaults(p.stats, t_units=u) for v, u in names_of.items()})
    asked = written(_asked(q, list(names_of)))
    mine = asked.select("qid", F.split("sid", r"\|")[1].alias("stream"))
    keys = ["stream", "variant"]
    edge = approx.edge_set(x.segments, asked).join(asked.select("qid", "variant").join(mine, "qid"), "qid").groupBy(*keys).agg(F.avg("edge").alias("edge_segments"))
    got = variant_intervals(p, x, asked).where("f in ('SUM', 'COUNT')").join(mine, "qid").groupBy(*keys).agg(F.avg("undecided").alias("k_actual"), F.avg("k_formula").alias("k_formula"), F.bool_and("inside").alias("inside"))
    s = x.segments.groupBy("stream", F.substring_index("sid", "|", 1).alias("variant")).agg(F.count("*").alias("s"))
    one = got.join(s, keys).join(edge, keys)
    return one.select("k_actual", "k_formula", "inside", F.col("s").cast("int").alias("s"), "edge_segments", "stream", F.col("variant").cast("double").alias("units"))


def widths(spark: SparkSession, d: str, names: tuple[str, ...] = streams.MAIN, count: int = 20) -> DataFrame:
    """Interval widths of the five aggregates, in value budgets or records."""
    out = []
    for name in names:
        p = prepare(spark, d, name)
        out.append(intervals(p, queries_of(p, count)).groupBy("k", "f").agg(F.avg("width").alias("width"), F.count("*").alias("checks"), F.bool_and("inside").alias("inside")).withColumn("stream", F.lit(name)))
    return _all(out)


def policies(p: Prepared, skew: float, k: int, count: int = 200) -> dict[str, tuple[DataFrame, DataFrame]]:
    """Budgets of each policy fitted on one half of a skewed workload, and the other half to measure on."""
    q = written(workload.skewed(p.records, skew, count, k))
    train, test = workload.split(q)
    freq = written(workload.touch_counts(train, p.n))
    base = written(budget.defaults(p.stats, regions=budget.REGIONS))
    fill = lambda e: budget.water_fill(base, freq, e)
    return {"uniform": (budget.uniform(base), test), "learned": (fill(-2 / 3), test), "adversarial": (fill(2 / 3), test), "edge_aware": (budget.edge_aware(base, freq), test)}


#: Share by which a policy's segment count may differ from uniform's.
TOLERANCE = 0.02
SKEWS = (0.0, 0.25, 0.5, 0.75, 0.9, 0.95)


def encoder_study(spark: SparkSession, d: str, names: tuple[str, ...] = streams.MAIN, skews: tuple[float, ...] = SKEWS, rounds: int = 12) -> DataFrame:
    """Width of SUM intervals by policy and skew, relative to uniform; containment of all.  ``matched`` says whether the
    segment count came within the tolerance of uniform's; widths of other rows don't compare."""
    rows = written(_encoders(spark, d, tuple(dict.fromkeys(names)), tuple(dict.fromkeys(skews)), rounds))
    base = rows.where("policy = 'uniform'").select("stream", "skew", F.col("sum_width").alias("_u"))
    return rows.join(base, ["stream", "skew"]).withColumn("vs_uniform", F.try_divide("sum_width", "_u")).drop("_u")


def _encoders(spark: SparkSession, d: str, names: tuple[str, ...], skews: tuple[float, ...], rounds: int) -> DataFrame:
    """All streams, skews and policies as variants (``stream/policy:skew``) of one batch, in every round of matching and in
    the measure.  Uniform budgets know no skew and are encoded once a stream."""
    p = unsegmented(spark, d, names)
    q = written(workload.skewed_each(p.records, skews, 200, F.greatest(F.lit(10), F.expr("_n div 50"))))
    train, test = workload.split(q)
    stream = F.substring_index("sid", "|", 1)
    base = written(budget.defaults(p.stats, regions=budget.REGIONS))
    each = written(_marked(base, [str(float(x)) for x in skews]))
    sized = train.join(F.broadcast(p.stats.select("sid", "n")), "sid").withColumn("sid", F.concat_ws("|", F.col("skew").cast("string"), "sid"))
    freq = written(workload.touch_counts(sized, "n"))
    found = {"learned": budget.water_fill(each, freq, -2 / 3), "adversarial": budget.water_fill(each, freq, 2 / 3), "edge_aware": budget.edge_aware(each, freq)}
    name = lambda s, policy, skew: F.concat(s, F.lit("/"), policy, F.lit(":"), skew)
    own = lambda b, policy: b.withColumn("sid", F.concat(name(F.split("sid", r"\|")[1], F.lit(policy), stream), F.lit("|"), _base()))
    uniform = written(base.withColumn("sid", F.concat(name(stream, F.lit("uniform"), F.lit("all")), F.lit("|"), F.col("sid"))))
    budgets = written(_all([own(b, policy) for policy, b in found.items()]))
    records = written(p.records.select("stream", "sid", "t", "v", "pos"))

    def count(scaled: DataFrame, variants: list[str] | None = None) -> dict[str, int]:
        made = segments.counts(records, scaled, variants=True)
        return {r["variant"]: r["n"] for r in made.groupBy(F.substring_index("sid", "|", 1).alias("variant")).agg(F.sum("count").alias("n")).collect()}

    target = {v.split("/")[0]: n for v, n in count(uniform).items()}
    goal = {f"{s}/{policy}:{float(skew)}": target[s] for s in names for policy in found for skew in skews}
    scales = budget.match_counts(count, budgets, list(goal), goal, TOLERANCE, rounds)
    factor = F.create_map(*[F.lit(y) for v in goal for y in (v, scales.get(v, 1.0))])[stream]
    scaled = budgets.withColumns({c: F.col(c) * factor for c in ("eps_v", "eps_t")})
    x = with_marked(p, written(scaled.unionByName(uniform)))
    # ids are unique over streams, skews and policies; a window has one ``base`` for all policies
    policies_of = ["uniform", *found]
    order = lambda values, c: F.create_map(*[F.lit(y) for i, z in enumerate(values) for y in (z, i)])[c]
    windows = test.withColumn("base", (F.col("qid") * len(names) + order(names, stream)) * len(skews) + order([float(z) for z in skews], F.col("skew")))
    asked = windows.withColumn("_p", F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(z).alias("policy")) for i, z in enumerate(policies_of)])))
    asked = asked.withColumns({"qid": F.col("base") * len(policies_of) + F.col("_p.i"), "policy": F.col("_p.policy"), "stream": stream})
    asked = asked.withColumn("variant", name(F.col("stream"), F.col("policy"), F.when(F.col("policy") == "uniform", "all").otherwise(F.col("skew").cast("string"))))
    asked = written(asked.withColumn("sid", F.concat_ws("|", "variant", "sid")).drop("_p", "lo", "hi"))
    keys = ["stream", "policy", "skew", "variant"]
    got = variant_intervals(p, x, asked).drop(*keys).join(asked.select("qid", *keys), "qid").groupBy(*keys).agg(F.avg(F.when(F.col("f") == "SUM", F.col("hi") - F.col("lo"))).alias("sum_width"), F.bool_and("inside").alias("inside"), F.count("*").alias("checks"))
    one = got.join(_counts(x), "variant").withColumn("target", F.create_map(*[F.lit(y) for z in target.items() for y in z])[F.col("stream")].cast("int"))
    matched = F.abs(F.col("s") - F.col("target")) <= TOLERANCE * F.col("target")
    return one.select("sum_width", "inside", "checks", "policy", "skew", F.col("s").cast("int").alias("s"), "target", matched.alias("matched"), "stream")


def budget_sweep(spark: SparkSession, d: str, name: str = "rate_block", fractions: tuple[float, ...] = (0.05, 0.1, 0.2, 0.4)) -> DataFrame:
    """Coarser bounds: fewer segments, wider intervals."""
    p = prepare(spark, d, name)
    q = queries_of(p, 10, only=[lengths(p.n)[1]])
    out = []
    for v in fractions:
        x = with_segments(p.records, p.nodes, p.stats, written(budget.defaults(p.stats, v_frac=v)))
        out.append(intervals(x, q).where("f = 'SUM'").agg(F.lit(v).alias("v_frac"), F.lit(x.segments.count()).alias("s"), F.avg(F.col("hi") - F.col("lo")).alias("sum_width"), F.bool_and("inside").alias("inside")))
    return _all(out)


def halve(spark: SparkSession, d: str, names: tuple[str, ...] = ("rate_block", "state_balance", "event_amt", "const_unit")) -> DataFrame:
    """SUM width after halving one budget and encoding again, relative to the default; share of the value term."""
    out = []
    for name in names:
        p = prepare(spark, d, name)
        q = queries_of(p, 20, only=[lengths(p.n)[-1]])
        x = with_variants(p, {"base": p.budgets, "half_v": budget.defaults(p.stats, 0.05, 0.5), "half_t": budget.defaults(p.stats, 0.10, 0.25)})
        got = variant_intervals(p, x, _asked(q, ["base", "half_v", "half_t"])).where("f = 'SUM'")
        width = lambda v: F.avg(F.when(F.col("variant") == v, F.col("hi") - F.col("lo")))
        of_base = lambda c: F.sum(F.when(F.col("variant") == "base", c))
        row = got.agg(width("base").alias("base"), width("half_v").alias("half_v"), width("half_t").alias("half_t"), F.try_divide(of_base(F.col("dv")), of_base(F.col("dv") + F.col("dt"))).alias("value_share"))
        out.append(row.select(F.lit(name).alias("stream"), F.try_divide("half_v", "base").alias("half_v"), F.try_divide("half_t", "base").alias("half_t"), "value_share"))
    return _all(out)


def value_blindness(spark: SparkSession, d: str, names: tuple[str, ...] = ("event_tail", "event_amt", "state_balance", "state_centred", "const_unit", "rate_block")) -> DataFrame:
    """Proof bytes of whole streams by window length: the exact path depends on records ``n``, not on values.  ``spread``
    is the largest mean over the smallest, less one, among streams of equal n."""
    out = []
    for name in names:
        p = prepare(spark, d, name)
        q = queries_of(p)
        size = costs.vo_bytes(exact.prove_aggregate(exact.locate(q, p.records, p.anchors), p.nodes, p.records)).join(q.select("qid", "k"), "qid")
        out.append(size.groupBy("k").agg(F.avg("bytes").alias("bytes")).withColumns({"stream": F.lit(name), "n": F.lit(p.n)}))
    rows = written(_all(out))
    return rows.join(costs.spread(rows, ["n", "k"], "bytes"), ["n", "k"])


def multi_source(spark: SparkSession, d: str, name: str = "by_user") -> DataFrame:
    """One proved window for every source, in one batch."""
    p = prepare(spark, d, name)
    q = written(workload.per_stream(p.records))
    return client.batch_verify(wire(p, q)).join(q.select("qid", "sid"), "qid").select("qid", "sid", "accepted", "reason", "s", "n", "mn", "mx")


def worked_example(spark: SparkSession, d: str) -> DataFrame:
    """The sum and mean of the first three records of every user, with proof."""
    r = written(streams.stream(spark, d, "by_user"))
    nodes = written(aggtree.build(aggtree.record_leaves(r)))
    anchors = written(aggtree.anchor(nodes))
    first = r.where("pos <= 2").groupBy("sid").agg(F.min("t").alias("t_s"), F.max("t").alias("t_e"))
    q = written(ordering.number(first.withColumn("_all", F.lit(0)), ["_all"], ["sid"], "qid").drop("_all"))
    v = client.batch_verify(exact.to_wire(exact.prove_aggregate(exact.locate(q, r, anchors), nodes, r), q, anchors))
    return v.join(q.select("qid", "sid"), "qid").select("sid", "accepted", F.col("s").alias("total"), F.col("n").alias("cnt"), F.round(F.col("s") / F.col("n"), 6).alias("mean"))
