"""Relational operators around the proofs, each a thin name over one Spark plan."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Rows up to which a side is broadcast; larger sides are shuffled.
BROADCAST_ROWS = 1_000_000


def join_broadcast(big: DataFrame, small: DataFrame, keys: list[str], how: str = "inner") -> DataFrame:
    """Broadcast hash join behind a bounded count of the small side."""
    fits = small.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS
    return big.join(F.broadcast(small) if fits else small, keys, how)


def join_merge(a: DataFrame, b: DataFrame, keys: list[str], how: str = "inner") -> DataFrame:
    return a.join(b.hint("merge"), keys, how)


def join_hash(a: DataFrame, b: DataFrame, keys: list[str], how: str = "inner") -> DataFrame:
    return a.join(b.hint("shuffle_hash"), keys, how)


def grid(a: DataFrame, b: DataFrame, most: int = 10_000) -> DataFrame:
    """Cross product of two small tables; refuses larger ones."""
    if b.limit(most + 1).count() > most:
        raise ValueError("grid is for small tables")
    return a.crossJoin(F.broadcast(b))


def join_range(points: DataFrame, spans: DataFrame, keys: list[str], at: str, lo: str, hi: str, chunk: int) -> DataFrame:
    """Points inside spans: spans are split by chunks of the axis, equal chunks join, the bounds filter."""
    p = points.withColumn("_chunk", F.floor(F.col(at) / chunk))
    s = spans.withColumn("_chunk", F.explode(F.sequence(F.floor(F.col(lo) / chunk), F.floor(F.col(hi) / chunk))))
    return p.join(s, [*keys, "_chunk"]).where(F.col(at).between(F.col(lo), F.col(hi))).drop("_chunk")


def join_asof(left: DataFrame, right: DataFrame, key: str, at: str, value: str, direction: str = "backward") -> DataFrame:
    """Last (or next) value of the right side at or before (after) each left row: a merge and one window, no range join."""
    a = left.withColumns({"_side": F.lit(1 if direction == "backward" else 0), "_v": F.lit(None).cast(right.schema[value].dataType)})
    b = right.select(key, at, F.col(value).alias("_v")).withColumn("_side", F.lit(0 if direction == "backward" else 1))
    w = Window.partitionBy(key).orderBy(at, "_side")
    frame = w.rowsBetween(Window.unboundedPreceding, 0) if direction == "backward" else w.rowsBetween(0, Window.unboundedFollowing)
    pick = F.last if direction == "backward" else F.first
    mine = 1 if direction == "backward" else 0
    both = a.unionByName(b, allowMissingColumns=True).withColumn(value, pick("_v", ignorenulls=True).over(frame))
    return both.where(F.col("_side") == mine).drop("_side", "_v")


def agg5(df: DataFrame, keys: list[str], v: str) -> DataFrame:
    return df.groupBy(*keys).agg(F.sum(v).alias("s"), F.count(v).alias("n"), F.min(v).alias("mn"), F.max(v).alias("mx"), F.round(F.avg(v), 6).alias("avg"))


def agg_ordered(df: DataFrame, keys: list[str], order: str, v: str) -> DataFrame:
    """Values in order, and the values at the extremes of the order.  For bounded groups."""
    pairs = F.array_sort(F.collect_list(F.struct(order, v)))
    return df.groupBy(*keys).agg(F.array_join(F.transform(pairs, lambda x: x[v].cast("string")), ",").alias("in_order"), F.max_by(v, order).alias("last"), F.min_by(v, order).alias("first"))


def rankings(df: DataFrame, key: str, *order: Column) -> DataFrame:
    w = Window.partitionBy(key).orderBy(*order)
    return df.withColumns({"rn": F.row_number().over(w), "rk": F.rank().over(w), "dr": F.dense_rank().over(w), "nt": F.ntile(4).over(w)})


def neighbours(df: DataFrame, key: str, order: str, v: str) -> DataFrame:
    w = Window.partitionBy(key).orderBy(order)
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return df.withColumns({"before": F.lag(v).over(w), "after": F.lead(v).over(w), "first": F.first(v).over(whole), "last": F.last(v).over(whole)})


def frames(df: DataFrame, key: str, at: str, v: str, rows: int, span: int) -> DataFrame:
    """Moving sums over the last ``rows`` rows and over the last ``span`` units of the axis."""
    w = Window.partitionBy(key).orderBy(at)
    return df.withColumns({"by_rows": F.sum(v).over(w.rowsBetween(-rows, 0)), "by_span": F.sum(v).over(w.rangeBetween(-span, 0))})


def quantiles(df: DataFrame, keys: list[str], v: str) -> DataFrame:
    return df.groupBy(*keys).agg(F.percentile(v, 0.5).alias("median"), F.percentile(v, 0.9).alias("p90"), F.round(F.stddev_pop(v), 4).alias("spread"))


def distinct_counts(df: DataFrame, keys: list[str], v: str, approximate: bool = False) -> DataFrame:
    return df.groupBy(*keys).agg((F.approx_count_distinct(v) if approximate else F.count_distinct(v)).alias("kinds"))


def checks(df: DataFrame, keys: list[str], condition: Column) -> DataFrame:
    return df.groupBy(*keys).agg(F.count_if(condition).alias("hits"), F.bool_and(condition).alias("all_of"), F.bool_or(condition).alias("any_of"))


def topk(df: DataFrame, k: int, *order: Column | str, offset: int = 0) -> DataFrame:
    return df.orderBy(*order).offset(offset).limit(k) if offset else df.orderBy(*order).limit(k)
