"""Cost and accuracy measures over proofs and intervals."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Bytes of the printed model: hash, one aggregate part, record, segment fields (fixed values).
HASH, PART, RECORD, SEGMENT = 32, 8, 16, 48


def vo_bytes(vo: DataFrame, model: str = "printed") -> DataFrame:
    """parts and bytes per query.  printed: node = hash + 4 parts, record 16, segment 48; full: node with time extent, record
    with position and tags, segment with extent and count."""
    opened = SEGMENT if "seg" in vo.columns else RECORD
    full = (72 if "seg" in vo.columns else 40) if model == "full" else opened
    node = HASH + PART * (4 if model == "printed" else 6)
    size = F.when(F.col("eta").isNull(), full).otherwise(node)
    return vo.groupBy("qid").agg(F.count("*").alias("parts"), F.sum(size).cast("long").alias("bytes"))


def touched(vo: DataFrame) -> DataFrame:
    """Objects that answer the window: cover nodes or records."""
    return vo.groupBy("qid").agg(F.count_if(F.col("role").isin("cover", "record")).alias("touched"), F.count("*").alias("shipped"))


def transfer(scanned: DataFrame) -> DataFrame:
    """Bytes that cross to the client if it scans itself, or if the chain scans."""
    return scanned.select("qid", (F.col("n") * RECORD).alias("client_side"), F.lit(PART).cast("long").alias("chain_side"))


def delta_ratio(delta: DataFrame) -> DataFrame:
    """Per sequence: bytes of independent proofs over bytes of delta proofs."""
    size = F.when(F.col("eta").isNull(), RECORD).otherwise(HASH + 4 * PART)
    out = delta.groupBy("seq_id").agg(F.sum(size).cast("long").alias("independent"), F.sum(F.when(F.col("fresh"), size).otherwise(0)).cast("long").alias("delta"))
    return out.withColumn("ratio", F.col("independent") / F.col("delta"))


def value_share(intervals: DataFrame) -> DataFrame:
    """Share of the value term in the width of SUM intervals."""
    return intervals.where("f = 'SUM'").groupBy("stream").agg(F.try_divide(F.sum("dv"), F.sum(F.col("dv") + F.col("dt"))).alias("value_share"))


def width_units(intervals: DataFrame, budgets: DataFrame) -> DataFrame:
    """Interval widths in value budgets (COUNT in records)."""
    b = budgets.groupBy("sid").agg(F.max("eps_v").alias("_b"))
    w = F.col("hi") - F.col("lo")
    return intervals.join(b, "sid").withColumn("width", F.when(F.col("f") == "COUNT", w).otherwise(F.try_divide(w, F.col("_b")))).drop("_b")


def spread(rows: DataFrame, keys: list[str], c: str) -> DataFrame:
    """Largest over smallest of a measure within each key, less one."""
    return rows.groupBy(*keys).agg((F.max(c) / F.min(c) - 1).alias("spread"))


def containment(intervals: DataFrame, exact: DataFrame) -> DataFrame:
    """Each interval beside the exact answer: inside is the soundness claim (null answers of empty windows count)."""
    e = exact.select("qid", F.expr("stack(5, 'SUM', cast(s as double), 'COUNT', cast(n as double), 'MIN', cast(mn as double), 'MAX', cast(mx as double), 'AVG', cast(s as double) / nullif(n, 0)) as (f, exact)"))
    inside = F.col("exact").isNull() | (F.col("exact").between(F.col("lo") - F.abs("lo") * 1e-12, F.col("hi") + F.abs("hi") * 1e-12))
    return intervals.join(e, ["qid", "f"]).withColumn("inside", F.coalesce(inside, F.lit(False)))


def timer(make: Callable[[], DataFrame]) -> float:
    """Seconds to run a plan without keeping its rows."""
    start = time.perf_counter()
    make().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start
