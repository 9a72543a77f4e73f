"""Connected components of a link table by alternating star contraction, on DataFrames only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tsproof.llm import shared


def _mark(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v")), F.bit_xor(F.xxhash64("v", F.lit(1), "u"))).first())


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """doc_id, component_id for every id that has a link; component_id is the smallest id reachable.

    Each round hangs neighbours under the smallest id around them, first among larger neighbours, then among smaller
    ones; O(log^2 n) rounds, one for stars.  Only a count and checksums return to the driver.  Minima combine before the
    shuffle, so hubs of any degree are safe.  Self links and nulls are ignored; no links give no rows.
    """
    u, v = F.greatest(a, b), F.least(a, b)
    edges = shared.written(links.where(F.col(a).isNotNull() & F.col(b).isNotNull()).select(u.alias("u"), v.alias("v")).where("u != v").distinct())
    before = None
    while (now := _mark(edges)) != before and now[0]:
        before = now
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min(F.least("u", "v")).alias("m"))
        wide = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        wide = shared.written(wide)
        least = wide.groupBy("u").agg(F.min("v").alias("m"))
        near = wide.join(least, "u").where("v != m").select(F.col("v").alias("x"), F.col("m").alias("y"))
        near = near.select(F.greatest("x", "y").alias("u"), F.least("x", "y").alias("v"))
        edges = shared.written(near.union(least.select("u", F.col("m").alias("v"))).distinct())
    roots = edges.select(F.col("v").alias("doc_id"), F.col("v").alias("component_id")).distinct()
    return edges.select(F.col("u").alias("doc_id"), F.col("v").alias("component_id")).union(roots)
