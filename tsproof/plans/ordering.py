"""Dense positions in the strict order (t, height, i) of each stream, and what follows from order without sorting a
stream in one task: running totals, neighbours, exact quantiles, as-of ranks."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tsproof.sources import written

ORDER = ("t", "height", "i")
#: Records of a stream that one task orders or folds at a time.
CHUNK = 65_536


def number(rows: DataFrame, keys: list[str], order: list[str], out: str = "pos", partitions: int | None = None) -> DataFrame:
    """Adds ``out``: 0, 1, 2 ... within each key by the given order.

    All rows are sorted over range partitions of (keys, order) and written once (so that sampled borders can't move); local
    numbers get the rows of the key in earlier partitions added, from a table of one row per (partition, key).
    """
    n = partitions or int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = rows.repartitionByRange(n, *keys, *order).sortWithinPartitions(*keys, *order)
    ranged = written(ranged.withColumn("_m", F.monotonically_increasing_id()))
    ranged = ranged.withColumn("_part", F.shiftright("_m", 33))
    counts = ranged.groupBy(*keys, "_part").agg(F.count("*").alias("_rows"), F.min("_m").alias("_first"))
    before = Window.partitionBy(*keys).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    names = [f"_key{i}" for i in range(len(keys))]
    offsets = counts.select(*[F.col(k).alias(x) for k, x in zip(keys, names)], F.col("_part").alias("_of"), (F.coalesce(F.sum("_rows").over(before), F.lit(0)) - F.col("_first")).alias("_shift"))
    same = F.col("_part") == F.col("_of")
    for k, x in zip(keys, names):  # null keys are a group of their own
        same &= F.col(k).eqNullSafe(F.col(x))
    return ranged.join(offsets, same).select(*rows.columns, (F.col("_m") + F.col("_shift")).alias(out))


def assign_positions(records: DataFrame, mode: str = "range", partitions: int | None = None) -> DataFrame:
    """Adds pos.  ``range`` numbers all streams over range partitions; ``window`` sorts each stream in one task and is for
    small streams and comparison only."""
    if mode == "window":
        return records.withColumn("pos", F.row_number().over(Window.partitionBy("sid").orderBy(*ORDER)).cast("long") - 1)
    return number(records, ["sid"], list(ORDER), "pos", partitions)


def running_total(records: DataFrame, mode: str = "chunk", chunk: int = CHUNK, keys: tuple[str, ...] = ("sid",), pos: str = "pos", v: str = "v") -> DataFrame:
    """v becomes the running sum by position.  ``chunk`` sums within chunks of positions and adds the totals of earlier
    chunks, so a giant stream is never one task's work."""
    if mode == "window":
        upto = Window.partitionBy(*keys).orderBy(pos).rowsBetween(Window.unboundedPreceding, 0)
        return records.withColumn(v, F.sum(v).over(upto))
    df = records.withColumn("_k", F.expr(f"{pos} div {chunk}"))
    totals = df.groupBy(*keys, "_k").agg(F.sum(v).alias("_t"))
    before = Window.partitionBy(*keys).orderBy("_k").rowsBetween(Window.unboundedPreceding, -1)
    totals = totals.select(*keys, "_k", F.coalesce(F.sum("_t").over(before), F.lit(0)).alias("_b"))
    upto = Window.partitionBy(*keys, "_k").orderBy(pos).rowsBetween(Window.unboundedPreceding, 0)
    return df.join(totals, [*keys, "_k"]).withColumn(v, F.sum(v).over(upto) + F.col("_b")).drop("_k", "_b")


def before(records: DataFrame, value: str, out: str, keys: tuple[str, ...] = ("sid",), chunk: int = CHUNK) -> DataFrame:
    """Adds the value at the previous position: by a window within chunks, and across their borders from a table of each
    chunk's last value."""
    df = records.withColumn("_k", F.expr(f"pos div {chunk}"))
    lasts = df.groupBy(*keys, "_k").agg(F.max_by(value, "pos").alias("_last")).withColumn("_k", F.col("_k") + 1)
    w = Window.partitionBy(*keys, "_k").orderBy("pos")
    return df.join(lasts, [*keys, "_k"], "left").withColumn(out, F.coalesce(F.lag(value).over(w), F.col("_last"))).drop("_k", "_last")


def quantiles(rows: DataFrame, keys: list[str], shares: dict[str, tuple[str, float]]) -> DataFrame:
    """Exact quantiles (linear between neighbours) per key, name -> (column, share), by picking positions of the sorted
    values of all columns at once: no task holds a group's values.  Nulls are left out; null where a key has no value."""
    columns = sorted({c for c, _ in shares.values()})
    values = F.array(*[F.struct(F.lit(i).alias("c"), F.col(c).cast("double").alias("x")) for i, c in enumerate(columns)])
    rows = rows.select(*keys, F.explode(values).alias("_s")).select(*keys, F.col("_s.c").alias("_c"), F.col("_s.x").alias("_x")).where("_x is not null")
    placed = number(rows, [*keys, "_c"], ["_x"], "_p")
    counts = placed.groupBy(*keys, "_c").agg(F.count("*").alias("_n"))
    asked = F.array(*[F.struct(F.lit(k).alias("q"), F.lit(columns.index(c)).alias("c"), F.lit(float(f)).alias("f")) for k, (c, f) in enumerate(shares.values())])
    wanted = counts.withColumn("_w", F.explode(asked)).where("_c = _w.c").select(*keys, "_c", F.col("_w.q").alias("_q"), (F.col("_w.f") * (F.col("_n") - 1)).alias("_at"))
    wanted = wanted.withColumn("_p", F.explode(F.array_distinct(F.array(F.floor("_at"), F.ceil("_at")))))
    hit = placed.join(wanted, [*keys, "_c", "_p"]).withColumn("_w", F.when(F.floor("_at") == F.ceil("_at"), 1.0).otherwise(1 - F.abs(F.col("_at") - F.col("_p"))))
    part = F.col("_x") * F.col("_w")
    return hit.groupBy(*keys).agg(*[F.sum(F.when(F.col("_q") == i, part)).alias(name) for i, name in enumerate(shares)])


def ranks(edges: DataFrame, ordered: DataFrame, t: str) -> DataFrame:
    """rank = rows of a stream with time below x, for edges (key, sid, x): one merge of both sides, numbered twice, once
    with the rows and once without; no task sorts a stream."""
    marks = edges.select("sid", "x", F.lit(0).alias("o"), F.col("key"))
    both = marks.unionByName(ordered.select("sid", F.col(t).alias("x"), F.lit(1).alias("o"), F.lit(None).cast("string").alias("key")))
    among = number(both, ["sid"], ["x", "o", "key"], "_all").where("o = 0").select("key", "_all")
    alone = number(marks, ["sid"], ["x", "o", "key"], "_own").select("key", "_own")
    return among.join(alone, "key").select("key", (F.col("_all") - F.col("_own")).alias("rank"))
