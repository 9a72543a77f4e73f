"""The choice between the exact and the approximate path, computed before anything runs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tsproof.sources import small

RECORD_BYTES, SEGMENT_BYTES = 16, 48


def break_even(stats: DataFrame, b_g: int = SEGMENT_BYTES, b_r: int = RECORD_BYTES) -> DataFrame:
    """Predicted saving of approximate retrieval, (n/s) / (b_g/b_r), and the levels an aggregation proof loses."""
    ratio = F.col("n") / F.col("s")
    return stats.select("stream", "sid", "n", "s", ratio.alias("per_segment"), (ratio * b_r / b_g).alias("predicted"), F.log2(ratio).alias("levels_saved"), (ratio > b_g / b_r).alias("pays"))


def choose(queries: DataFrame, stats: DataFrame, b_g: int = SEGMENT_BYTES, b_r: int = RECORD_BYTES) -> DataFrame:
    """path per query: exact if asked for, else approximate where it pays (retrieval) and the expected width fits."""
    s = stats.select("sid", "n", "s", "eps_v")
    width = F.when(F.col("f") == "AVG", 2 * F.col("eps_v")).when(F.col("f") == "SUM", 2 * F.col("eps_v") * F.col("k")).otherwise(2 * F.col("eps_v"))
    pays = (F.col("f") != "RANGE") | (F.col("n") * b_r > F.col("s") * b_g)
    path = F.when(F.col("exact") | ~pays | (width > F.col("max_width")), "exact").otherwise("approximate")
    return queries.join(small(s), "sid", "left").select("qid", "sid", "f", F.coalesce(path, F.lit("exact")).alias("path"))
