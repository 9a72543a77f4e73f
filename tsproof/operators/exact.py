"""Exact window queries over the tree: locating, folding, proofs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tsproof.functions import cover, encoding
from tsproof.plans import ordering

FENCE = 4096
#: Keys of this many rows at most are broadcast; more are shuffled.
BROADCAST_ROWS = 500_000


def _small(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def ranks(edges: DataFrame, ordered: DataFrame, t: str, pos: str, chunk: int = FENCE) -> DataFrame:
    """rank = rows of a stream with time below x, for edges (key, sid, x).

    A fence of one row per chunk of positions finds the chunk by an as-of merge; only that chunk's rows are then counted,
    through an equality join on (sid, chunk).  The merge orders the fence (a row per ``chunk`` records) and the edges.
    """
    rows = ordered.select("sid", F.col(t).alias("_t"), F.col(pos).alias("_p"), F.expr(f"{pos} div {chunk}").alias("chunk"))
    fence = rows.groupBy("sid", "chunk").agg(F.min("_t").alias("x"))
    merged = fence.select("sid", "x", "chunk", F.lit(None).cast("string").alias("key"), F.lit(1).alias("o")).unionByName(edges.select("sid", "x", F.lit(None).cast("long").alias("chunk"), "key", F.lit(0).alias("o")))
    w = Window.partitionBy("sid").orderBy("x", "o", "chunk").rowsBetween(Window.unboundedPreceding, 0)
    placed = merged.withColumn("chunk", F.last("chunk", ignorenulls=True).over(w)).where("o = 0").select("key", "sid", "x", "chunk")
    below = placed.where("chunk is not null").join(rows, ["sid", "chunk"]).groupBy("key").agg(F.sum((F.col("_t") < F.col("x")).cast("long")).alias("_c"))
    return placed.join(below, "key", "left").select("key", (F.coalesce(F.col("chunk") * chunk, F.lit(0)) + F.coalesce("_c", F.lit(0))).alias("rank"))


def bucket_ranks(edges: DataFrame, records: DataFrame, buckets: int = 4096) -> DataFrame:
    """The same ranks from equal buckets of time: rows of earlier buckets from a table of their counts, rows of the edge's
    own bucket through an equality join."""
    span = records.groupBy("sid").agg(F.min("t").alias("_a"), F.max("t").alias("_b")).select("sid", "_a", F.expr(f"(_b - _a) div {buckets} + 1").alias("_w"))
    at = lambda x: F.least(F.greatest(F.expr(f"floor(({x} - _a) / _w)"), F.lit(-1)), F.lit(buckets + 1)).cast("long")
    rows = records.select("sid", "t").join(span, "sid").select("sid", "t", at("t").alias("bucket"))
    counts = rows.groupBy("sid", "bucket").agg(F.count("*").alias("_c"))
    upto = Window.partitionBy("sid").orderBy("bucket", "o").rowsBetween(Window.unboundedPreceding, 0)
    marks = edges.join(span, "sid").select("key", "sid", "x", at("x").alias("bucket"))
    both = marks.select("sid", "bucket", F.lit(0).alias("o"), "key", F.lit(0).alias("_c")).unionByName(counts.select("sid", "bucket", F.lit(1).alias("o"), F.lit(None).cast("string").alias("key"), "_c"))
    earlier = both.withColumn("_before", F.sum("_c").over(upto)).where("o = 0").select("key", "_before")
    own = marks.join(rows, ["sid", "bucket"]).groupBy("key").agg(F.sum((F.col("t") < F.col("x")).cast("long")).alias("_own"))
    out = edges.select("key").join(earlier, "key", "left").join(own, "key", "left")
    return out.select("key", (F.coalesce("_before", F.lit(0)) + F.coalesce("_own", F.lit(0))).alias("rank"))


def locate(queries: DataFrame, records: DataFrame, anchors: DataFrame | None = None, how: str = "fence") -> DataFrame:
    """lo, hi (first and last position in the window; lo = hi + 1 if none) and n for queries (qid, sid, t_s, t_e): by a
    fence of chunks, a merge of all records (``asof``) or buckets of time (``range``)."""
    q = queries.select("qid", "sid", "t_s", "t_e")
    ends = q.select(F.concat_ws("|", "qid", F.lit("s")).alias("key"), "sid", F.col("t_s").alias("x")).unionByName(q.select(F.concat_ws("|", "qid", F.lit("e")).alias("key"), "sid", (F.col("t_e") + 1).alias("x")))
    r = {"fence": lambda: ranks(ends, records, "t", "pos"), "asof": lambda: ordering.ranks(ends, records, "t"), "range": lambda: bucket_ranks(ends, records)}[how]()
    side = r.groupBy(F.split("key", r"\|")[0].cast("long").alias("qid")).agg(F.max(F.when(F.col("key").endswith("s"), F.col("rank"))).alias("lo"), (F.max(F.when(F.col("key").endswith("e"), F.col("rank"))) - 1).alias("hi"))
    out = q.join(side, "qid")
    counts = anchors.select("sid", F.col("raw_n").alias("n")) if anchors is not None else records.groupBy("sid").agg(F.count("*").alias("n"))
    return out.join(counts, "sid", "left").withColumn("n", F.coalesce("n", F.lit(0))).select("qid", "sid", "t_s", "t_e", "lo", "hi", "n")


def aggregate(located: DataFrame, nodes: DataFrame, fanout: int = 2) -> DataFrame:
    """All five aggregates of each window, folded from its cover; empty windows: count 0, sum 0, others null."""
    keys = cover.with_cover(located.select("qid", "sid", "lo", "hi", "n"), F.col("lo"), F.col("hi"), F.col("n"), fanout).select("qid", "sid", "lvl", "idx")
    got = nodes.select("sid", "lvl", "idx", "s", F.col("n").alias("_n"), "mn", "mx").join(F.broadcast(keys) if _bounded(located) else keys, ["sid", "lvl", "idx"])
    folded = got.groupBy("qid").agg(F.sum("s").alias("s"), F.sum("_n").alias("cnt"), F.min("mn").alias("mn"), F.max("mx").alias("mx"), F.count("*").alias("touched"))
    out = located.select("qid", "sid").join(folded, "qid", "left")
    s, c = F.coalesce("s", F.lit(0)).cast("long"), F.coalesce("cnt", F.lit(0))
    return out.select("qid", "sid", s.alias("s"), c.alias("n"), "mn", "mx", F.round(F.try_divide(F.col("s").cast("double"), F.col("cnt").cast("double")), 6).alias("avg"), F.coalesce("touched", F.lit(0)).alias("touched"))


def _bounded(located: DataFrame) -> bool:
    """A window has about 2 (f - 1) log n keys; beyond the bound keys are shuffled instead of broadcast."""
    return located.limit(BROADCAST_ROWS // 40 + 1).count() <= BROADCAST_ROWS // 40


def _alpha(prefix: str = "") -> Column:
    return F.struct(*[F.col(prefix + c).alias(c) for c in encoding.ALPHA])


NO_REC = "struct<t:bigint,height:bigint,i:int,v:bigint,tags:map<string,string>>"


def prove_aggregate(located: DataFrame, nodes: DataFrame, records: DataFrame, fanout: int = 2) -> DataFrame:
    """Proof rows (qid, sid, role, lvl, idx, eta, alpha, rec): cover, siblings, and the records beside the window."""
    keys = cover.proof_keys(located, fanout)
    keys = F.broadcast(keys) if _bounded(located) else keys
    inner = nodes.join(keys.where("role != 'edge'"), ["sid", "lvl", "idx"]).select("qid", "sid", "role", "lvl", "idx", "eta", _alpha().alias("alpha"), F.lit(None).cast(NO_REC).alias("rec"))
    edge = records.join(keys.where("role = 'edge'").withColumnRenamed("idx", "pos"), ["sid", "pos"])
    edge = edge.select("qid", "sid", "role", "lvl", F.col("pos").alias("idx"), F.lit(None).cast("string").alias("eta"), F.lit(None).cast(inner.schema["alpha"].dataType).alias("alpha"), F.struct("t", "height", "i", "v", "tags").cast(NO_REC).alias("rec"))
    return inner.unionByName(edge)


def prove_range(located: DataFrame, nodes: DataFrame, records: DataFrame, fanout: int = 2, chunk: int = FENCE) -> DataFrame:
    """As above with the cover opened to all records of the window."""
    vo = prove_aggregate(located, nodes, records, fanout).where("role != 'cover'")
    spans = located.where("lo <= hi").withColumn("chunk", F.explode(F.sequence(F.expr(f"lo div {chunk}"), F.expr(f"hi div {chunk}")))).select("qid", "sid", "lo", "hi", "chunk")
    rows = records.withColumn("chunk", F.expr(f"pos div {chunk}")).join(spans, ["sid", "chunk"]).where("pos between lo and hi")
    inside = rows.select("qid", "sid", F.lit("record").alias("role"), F.lit(0).alias("lvl"), F.col("pos").alias("idx"), F.lit(None).cast("string").alias("eta"), F.lit(None).cast(vo.schema["alpha"].dataType).alias("alpha"), F.struct("t", "height", "i", "v", "tags").cast(NO_REC).alias("rec"))
    return vo.unionByName(inside)


def to_wire(vo: DataFrame, queries: DataFrame, anchors: DataFrame, extra: list[str] | None = None) -> DataFrame:
    """One row per query: the query, its proof as an array, and the anchor the client trusts."""
    parts = [c for c in ("role", "lvl", "idx", "eta", "alpha", "rec", "seg") if c in vo.columns]
    proof = vo.groupBy("qid").agg(F.collect_list(F.struct(*parts)).alias("proof"))
    anchor = F.struct(*[c for c in anchors.columns if c != "sid"], "sid").alias("anchor")
    return queries.select("qid", "sid", "t_s", "t_e", *(extra or [])).join(proof, "qid", "left").join(F.broadcast(anchors.select("sid", anchor)) if _bounded(anchors) else anchors.select("sid", anchor), "sid", "left")
