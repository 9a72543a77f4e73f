"""The ways to answer without folding: scans, downloads, per-record proofs, leaf proofs, independent slides."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tsproof.functions import cover, encoding
from tsproof.operators import exact
from tsproof.sources import small


def scan(located: DataFrame, records: DataFrame, chunk: int = exact.FENCE) -> DataFrame:
    """Aggregates by reading every record of the window (client-side or chain-side: the plan is one, the bytes differ)."""
    spans = located.where("lo <= hi").withColumn("chunk", F.explode(F.sequence(F.expr(f"lo div {chunk}"), F.expr(f"hi div {chunk}")))).select("qid", "sid", "lo", "hi", "chunk")
    rows = records.select("sid", "pos", "v", F.expr(f"pos div {chunk}").alias("chunk")).join(spans, ["sid", "chunk"]).where("pos between lo and hi")
    got = rows.groupBy("qid").agg(F.sum("v").alias("s"), F.count("*").alias("n"), F.min("v").alias("mn"), F.max("v").alias("mx"))
    out = located.select("qid", "sid").join(got, "qid", "left")
    return out.select("qid", "sid", F.coalesce("s", F.lit(0)).alias("s"), F.coalesce("n", F.lit(0)).alias("n"), "mn", "mx")


def redownload(located: DataFrame, records: DataFrame) -> DataFrame:
    """Answers after shipping all records of the window: 16 bytes each."""
    return scan(located, records).withColumn("bytes", F.col("n") * 16)


def per_record_paths(located: DataFrame, fanout: int = 2, alpha: bool = False) -> DataFrame:
    """Hashes shipped if every record brings its own path: per query, records and path hashes (f - 1 siblings a level, less
    where the tree's right edge has fewer)."""
    rows = located.where("lo <= hi").withColumn("pos", F.explode(F.sequence("lo", "hi")))
    rows = rows.withColumn("lvl", F.explode(F.sequence(F.lit(0), cover.depth_column(F.col("n"), fanout))))
    w = F.pow(F.lit(fanout), F.col("lvl")).cast("long")
    width = F.ceil(F.col("n") / w)
    first = F.expr(f"(pos div cast(pow({fanout}, lvl + 1) as bigint)) * {fanout}")
    siblings = F.least(F.lit(fanout - 1), width - first - 1)
    got = rows.groupBy("qid").agg(F.count_if(F.col("lvl") == 0).alias("records"), F.sum(F.greatest(siblings, F.lit(0))).alias("path_nodes"))
    return got.withColumn("bytes", F.col("records") * 16 + F.col("path_nodes") * (64 if alpha else 32))


def prove_paths(located: DataFrame, nodes: DataFrame, records: DataFrame, fanout: int = 2) -> DataFrame:
    """What that baseline ships: per query the window's records and the two beside it, each with its own path (qid,
    entries)."""
    w = lambda lvl: F.pow(F.lit(fanout), lvl).cast("long")
    at = located.where("n > 0").select("qid", "sid", "n", F.explode(F.sequence(F.greatest(F.col("lo") - 1, F.lit(0)), F.least(F.col("hi") + 1, F.col("n") - 1))).alias("pos"))
    depth = cover.depth_column(F.col("n"), fanout)
    steps = at.where("n > 1").withColumn("lvl", F.explode(F.sequence(F.lit(0), depth - 1)))
    steps = steps.withColumn("_own", F.floor(F.col("pos") / w(F.col("lvl"))))
    steps = steps.withColumn("idx", F.explode(F.transform(F.sequence(F.lit(0), F.lit(fanout - 1)), lambda c: F.floor(F.col("_own") / fanout) * fanout + c)))
    steps = steps.where((F.col("idx") != F.col("_own")) & (F.col("idx") * w(F.col("lvl")) < F.col("n"))).select("qid", "sid", "pos", F.col("lvl").cast("int").alias("lvl"), F.col("idx").cast("long").alias("idx"))
    got = steps.join(nodes, ["sid", "lvl", "idx"]).groupBy("qid", "pos").agg(F.collect_list(F.struct("lvl", "idx", "eta", F.struct(*[F.col(c) for c in encoding.ALPHA]).alias("alpha"))).alias("path"))
    rows = at.join(records.select("sid", "pos", F.struct("t", "height", "i", "v", "tags").alias("rec")), ["sid", "pos"]).join(got, ["qid", "pos"], "left")
    return rows.groupBy("qid").agg(F.collect_list(F.struct("pos", "rec", "path")).alias("entries"))


def paths_wire(entries: DataFrame, queries: DataFrame, anchors: DataFrame) -> DataFrame:
    anchor = anchors.select("sid", F.struct(*[c for c in anchors.columns if c != "sid"], "sid").alias("anchor"))
    return queries.select("qid", "sid", "t_s", "t_e").join(entries, "qid", "left").join(small(anchor), "sid", "left")


def leaf_fold(located: DataFrame, nodes: DataFrame, records: DataFrame, fanout: int = 2) -> DataFrame:
    """Authenticated leaves: a range proof whose aggregate the client works out itself."""
    return exact.prove_range(located, nodes, records, fanout)


def block_scan(queries: DataFrame, records: DataFrame) -> DataFrame:
    """The status quo: walk the blocks of the window and filter their transactions.  Windows and blocks meet by equality on
    buckets of time, about one per 64 blocks."""
    r = records.select("sid", "height", "t", "v")
    blocks = r.groupBy("sid", "height").agg(F.min("t").alias("a"), F.max("t").alias("b"))
    width = blocks.groupBy("sid").agg(F.greatest(F.expr("(max(b) - min(a)) div greatest(count(*) div 64, 1) + 1"), F.max(F.col("b") - F.col("a")) + 1).alias("_w"))
    blocks = blocks.join(small(width), "sid").withColumn("_k", F.expr("floor(a / _w)"))
    # a block that reaches into the window starts at most one width before it
    spans = queries.select("qid", "sid", "t_s", "t_e").join(small(width), "sid").withColumn("_k", F.explode(F.expr("sequence(floor(t_s / _w) - 1, floor(t_e / _w))"))).drop("_w")
    near = spans.join(blocks.drop("_w"), ["sid", "_k"]).where("b >= t_s and a <= t_e").drop("_k")
    hit = near.join(r, ["sid", "height"])
    inside = F.col("t").between(F.col("t_s"), F.col("t_e"))
    return hit.groupBy("qid").agg(F.count_distinct("height").alias("blocks"), F.coalesce(F.sum(F.when(inside, F.col("v"))), F.lit(0)).alias("s"), F.count_if(inside).alias("n"))


def independent(vo: DataFrame) -> DataFrame:
    """Every slide with a whole proof: parts per window."""
    return vo.groupBy("qid").agg(F.count("*").alias("parts"))


