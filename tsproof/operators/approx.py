"""Approximate queries over segments: proofs for the client, reconstruction, edge sets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tsproof.functions import cover, encoding
from tsproof.functions.lines import T
from tsproof.operators import exact
from tsproof.plans import ordering
from tsproof.sources import small

SEG = "struct<tau_lo:bigint,tau_hi:bigint,a:bigint,b:bigint,mu:bigint,beta:bigint,eps_v:bigint,eps_t:bigint,c:bigint>"


def locate(queries: DataFrame, segments: DataFrame) -> DataFrame:
    """lo..hi: segments wholly inside the window by their certified extents; the leaves beside them straddle an edge."""
    q = queries.select("qid", "sid", "t_s", "t_e")
    starts = q.select(F.concat_ws("|", "qid", F.lit("s")).alias("key"), "sid", F.col("t_s").alias("x"))
    ends = q.select(F.concat_ws("|", "qid", F.lit("e")).alias("key"), "sid", (F.col("t_e") + 2).alias("x"))
    lo = exact.ranks(starts, segments, "tau_lo", "j").select(F.split("key", r"\|")[0].cast("long").alias("qid"), F.col("rank").alias("lo"))
    hi = exact.ranks(ends, segments, "tau_hi", "j").select(F.split("key", r"\|")[0].cast("long").alias("qid"), (F.col("rank") - 1).alias("hi"))
    n = segments.groupBy("sid").agg(F.count("*").alias("n"))
    return q.join(lo, "qid").join(hi, "qid").join(n, "sid", "left").withColumn("n", F.coalesce("n", F.lit(0)))


def prove_aggregate(located: DataFrame, seg_nodes: DataFrame, segments: DataFrame, fanout: int = 2) -> DataFrame:
    """Cover of whole segments, siblings, and the opened segments at the edges."""
    keys = cover.proof_keys(located, fanout)
    inner = seg_nodes.join(keys.where("role != 'edge'"), ["sid", "lvl", "idx"]).select("qid", "sid", "role", "lvl", "idx", "eta", F.struct(*encoding.ALPHA).alias("alpha"), F.lit(None).cast(SEG).alias("seg"))
    edge = segments.join(keys.where("role = 'edge'").withColumnRenamed("idx", "j"), ["sid", "j"])
    return inner.unionByName(_opened(edge, inner))


def _opened(rows: DataFrame, like: DataFrame) -> DataFrame:
    return rows.select("qid", "sid", "role", F.lit(0).alias("lvl"), F.col("j").alias("idx"), F.lit(None).cast("string").alias("eta"), F.lit(None).cast(like.schema["alpha"].dataType).alias("alpha"), F.struct(*encoding.SEGMENT).cast(SEG).alias("seg"))


def prove_range(located: DataFrame, seg_nodes: DataFrame, segments: DataFrame, fanout: int = 2, chunk: int = 1024) -> DataFrame:
    """All covering segments opened: the client reconstructs every position."""
    vo = prove_aggregate(located, seg_nodes, segments, fanout).where("role != 'cover'")
    spans = located.where("lo <= hi").withColumn("chunk", F.explode(F.sequence(F.expr(f"lo div {chunk}"), F.expr(f"hi div {chunk}")))).select("qid", "sid", "lo", "hi", "chunk")
    rows = segments.withColumn("chunk", F.expr(f"j div {chunk}")).join(spans, ["sid", "chunk"]).where("j between lo and hi").withColumn("role", F.lit("record"))
    return vo.unionByName(_opened(rows, vo))


def reconstruct(segments: DataFrame) -> DataFrame:
    """Per position the intervals of its value and time, in scaled integers."""
    rows = segments.withColumn("p", F.explode(F.sequence(F.lit(0).cast("long"), F.col("c") - 1)))
    v = F.col("a").cast("decimal(19,0)") * F.col("p").cast("decimal(18,0)") + F.col("b")
    t = F.col("tau_lo").cast("decimal(19,0)") * T + F.col("mu").cast("decimal(19,0)") * F.col("p").cast("decimal(18,0)") + F.col("beta")
    return rows.select("sid", (F.col("pos_lo") + F.col("p")).alias("pos"), (v - F.col("eps_v")).alias("v_lo"), (v + F.col("eps_v")).alias("v_hi"), (t - F.col("eps_t")).alias("t_lo"), (t + F.col("eps_t")).alias("t_hi"))


def edge_set(segments: DataFrame, queries: DataFrame, rule: str = "padded") -> DataFrame:
    """Segments per window that aren't certified to lie inside it: by extents widened by the arrival bound (``padded``) or
    by the extents themselves (``tau``).

    Segments and window edges meet by equality on buckets of time as wide as a stream's longest padded segment, so that
    only those around an edge are compared; whole segments inside are counted by position.
    """
    pad = F.ceil(F.col("eps_t") / T) if rule == "padded" else F.lit(0)
    s = segments.select("sid", "j", (F.col("tau_lo") - pad).alias("p_lo"), (F.col("tau_hi") + pad).alias("p_hi"))
    width = s.groupBy("sid").agg((F.max(F.col("p_hi") - F.col("p_lo")) + 1).alias("_w"))
    s = s.join(small(width), "sid").withColumn("_b", F.expr("floor(p_lo / _w)"))
    q = queries.select("qid", "sid", "t_s", "t_e").join(small(width), "sid")
    # a segment that an edge cuts starts at most one width before the edge
    cuts = q.withColumn("_x", F.explode(F.array("t_s", F.col("t_e") + 1))).withColumn("_b", F.explode(F.array(F.expr("floor(_x / _w)"), F.expr("floor(_x / _w) - 1")))).drop("_w")
    hit = cuts.join(s.drop("_w"), ["sid", "_b"]).where("p_lo <= t_e and p_hi > t_s and (p_lo < t_s or p_hi > t_e + 1)").select("qid", "j").distinct()
    edges = hit.groupBy("qid").agg(F.count("*").alias("edge"))
    # overlapping: those that start at or before the window's end, less those that end at or before its start
    ends = q.select(F.col("qid").cast("string").alias("key"), "sid", (F.col("t_e") + 1).alias("x"))
    starts = q.select(F.col("qid").cast("string").alias("key"), "sid", (F.col("t_s") + 1).alias("x"))
    begun, over = ordering.ranks(ends, s, "p_lo").withColumnRenamed("rank", "_begun"), ordering.ranks(starts, s, "p_hi").withColumnRenamed("rank", "_over")
    both = begun.join(over, "key").select(F.col("key").cast("long").alias("qid"), (F.col("_begun") - F.col("_over")).alias("segments"))
    out = both.where("segments > 0").join(edges, "qid", "left")
    return out.select("qid", F.coalesce("edge", F.lit(0)).alias("edge"), "segments")
