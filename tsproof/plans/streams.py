"""Streams of records over the given tables (values are fixed-point integers) and what they are made from."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tsproof.plans import ordering
from tsproof.sources import read_table, written


def micros(ts: str) -> Column:
    return F.unix_micros(F.col(ts).cast("timestamp"))


def cents(c: str) -> Column:
    return F.round(F.col(c) * 100).cast("long")


def from_transactions(df: DataFrame, sid: Column, t: Column, v: Column, height: Column, i: Column, tags: Column | None = None) -> DataFrame:
    """Each transaction is a record at (height, i)."""
    tags = F.create_map().cast("map<string,string>") if tags is None else tags
    return df.select(sid.cast("string").alias("sid"), t.alias("t"), height.cast("long").alias("height"), i.cast("int").alias("i"), v.cast("long").alias("v"), tags.alias("tags"))


METRICS = {"mean": lambda: F.expr("sum(v) * 100 div count(v)"), "sum": lambda: F.sum("v"), "min": lambda: F.min("v"), "max": lambda: F.max("v"), "count": lambda: F.count("v")}


def block_metric(records: DataFrame, metric: str = "mean", sid: str = "blockmean") -> DataFrame:
    """One record per block at (height, 0), timed by its last transaction; the mean has four decimals."""
    out = records.groupBy("height").agg(F.max("t").alias("t"), METRICS[metric]().cast("long").alias("v"))
    return from_transactions(out, F.lit(sid), F.col("t"), F.col("v"), F.col("height"), F.lit(0))


def constant(records: DataFrame, c: int = 1) -> DataFrame:
    return records.withColumn("v", F.lit(c).cast("long"))


def top_source(records: DataFrame, by: str = "value", k: int = 1) -> DataFrame:
    """The sources that move most value (or, as a contrast, have most records); ties to the smaller sid."""
    out = records.groupBy("sid").agg(F.sum("v").alias("value"), F.count("*").alias("count"))
    return out.orderBy(F.desc(by), "sid").limit(k)


def prefix(records: DataFrame, n: int) -> DataFrame:
    return records.where(F.col("pos") < n)


def from_sequence(df: DataFrame, sid: Column, order: Column, v: Column) -> DataFrame:
    """Any ordered table as a stream: time is the order column."""
    return from_transactions(df, sid, order.cast("long"), v, order, F.lit(0))


def _events(spark: SparkSession, d: str, sid: Column | None = None) -> DataFrame:
    e = read_table(spark, d, "events", ["event_id", "ts", "user_id", "event_type", "value", "props"])
    tags = F.create_map(F.lit("event_type"), F.col("event_type"), F.lit("k"), F.get_json_object("props", "$.k"), F.lit("user_id"), F.col("user_id").cast("string"))
    return from_transactions(e, F.lit("all") if sid is None else sid, micros("ts"), cents("value"), F.expr("event_id div 10"), F.col("event_id") % 10, tags)


def _orders(spark: SparkSession, d: str, sid: Column) -> DataFrame:
    o = read_table(spark, d, "orders")
    day = F.expr("unix_micros(cast(o_orderdate as timestamp)) div 86400000000")
    return from_transactions(ordering.number(o, ["o_orderdate"], ["o_orderkey"], "_r"), sid, micros("o_orderdate"), cents("o_totalprice"), day, F.col("_r"), F.create_map(F.lit("status"), F.col("o_orderstatus")))


def _lines(spark: SparkSession, d: str, sid: Column) -> DataFrame:
    x = read_table(spark, d, "lineitem")
    day = F.expr("unix_micros(cast(l_shipdate as timestamp)) div 86400000000")
    return from_transactions(ordering.number(x, ["l_shipdate"], sorted(x.columns), "_r"), sid, micros("l_shipdate"), cents("l_extendedprice"), day, F.col("_r"), F.create_map(F.lit("returnflag"), F.col("l_returnflag")))


def _mean_of(spark: SparkSession, d: str, which: str) -> DataFrame:
    if which == "day":
        rows = _orders(spark, d, F.lit("x")).withColumn("g", F.col("t"))
    else:
        rows = _events(spark, d).withColumn("g", F.expr("t - pmod(t, 3600000000)"))
    out = rows.groupBy("g").agg(F.expr("sum(v) * 100 div count(v)").alias("v"))
    unit = 86_400_000_000 if which == "day" else 3_600_000_000
    return from_transactions(out, F.lit(f"{which}mean"), F.col("g"), F.col("v"), F.expr(f"g div {unit}"), F.lit(0))


def _cubed(records: DataFrame) -> DataFrame:
    return records.withColumn("v", F.expr("cast(cast(v as decimal(38,0)) * v * v div 10000 as bigint)"))


def _tail(spark: SparkSession, d: str) -> DataFrame:
    return _cubed(_events(spark, d))


def _state(spark: SparkSession, d: str, centred: bool) -> DataFrame:
    rows = ordering.assign_positions(_events(spark, d))
    if centred:
        mean = rows.groupBy("sid").agg(F.expr("sum(v) div count(v)").alias("_mean"))
        rows = rows.join(F.broadcast(mean), "sid").withColumn("v", F.col("v") - F.col("_mean")).drop("_mean")
    return ordering.running_total(rows).drop("pos")


STREAMS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "event_amt": lambda s, d: _events(s, d),
    "event_tail": _tail,
    "rate_block": lambda s, d: block_metric(_events(s, d)),
    "rate_hour": lambda s, d: _mean_of(s, d, "hour"),
    "rate_day": lambda s, d: _mean_of(s, d, "day"),
    "state_balance": lambda s, d: _state(s, d, False),
    "state_centred": lambda s, d: _state(s, d, True),
    "const_unit": lambda s, d: constant(_events(s, d)),
    "by_user": lambda s, d: _events(s, d, F.col("user_id")),
    "by_type": lambda s, d: _events(s, d, F.col("event_type")),
    "order_price": lambda s, d: _orders(s, d, F.lit("orders")),
    "by_customer": lambda s, d: _orders(s, d, F.col("o_custkey")),
    "line_price": lambda s, d: _lines(s, d, F.lit("lines")),
    "by_supplier": lambda s, d: _lines(s, d, F.col("l_suppkey")),
    "doc_chars": lambda s, d: from_sequence(read_table(s, d, "documents", ["doc_id", "lang", "n_chars"]), F.col("lang"), F.col("doc_id"), F.col("n_chars")),
    "page_chars": lambda s, d: from_sequence(read_table(s, d, "pages", ["page_id", "html"]), F.lit("pages"), F.col("page_id"), F.length("html")),
    "turn_chars": lambda s, d: from_sequence(read_table(s, d, "conversations", ["conv_id", "turn", "text"]), F.col("conv_id"), F.col("turn"), F.length("text")),
    "label_flags": lambda s, d: from_sequence(read_table(s, d, "labels", ["doc_id", "quality", "toxic"]), F.lit("labels"), F.col("doc_id"), F.col("quality") * 2 + F.col("toxic")),
    "item_chars": lambda s, d: from_sequence(read_table(s, d, "benchmark", ["item_id", "text"]), F.lit("items"), F.col("item_id"), F.length("text")),
    "first_component": lambda s, d: from_sequence(read_table(s, d, "embeddings", ["vec_id", "embedding"]), F.lit("emb"), F.col("vec_id"), F.floor(F.element_at("embedding", 1).cast("double") * 1000)),
}
#: The five kinds that the experiments compare.
MAIN = ("rate_block", "event_tail", "event_amt", "state_balance", "const_unit")


def stream(spark: SparkSession, directory: str, name: str, mode: str = "range") -> DataFrame:
    """Records of a named stream with positions, the stream's name in ``stream``."""
    return ordering.assign_positions(STREAMS[name](spark, directory), mode).withColumn("stream", F.lit(name))


#: Streams that hold the events in their order, with other values.
FROM_EVENTS: dict[str, Callable[[DataFrame], DataFrame]] = {"event_amt": lambda r: r, "event_tail": _cubed, "state_balance": ordering.running_total, "const_unit": constant}


def several(spark: SparkSession, directory: str, names: tuple[str, ...]) -> DataFrame:
    """Records of several streams with positions, of the sids ``stream|sid``; those of the same events are ordered once."""
    events = written(ordering.assign_positions(_events(spark, directory))) if any(x in FROM_EVENTS for x in names) else None
    parts = [(x, FROM_EVENTS[x](events) if x in FROM_EVENTS else ordering.assign_positions(STREAMS[x](spark, directory))) for x in names]
    columns = ["stream", "sid", "t", "height", "i", "v", "tags", "pos"]
    rows = [r.withColumns({"stream": F.lit(x), "sid": F.concat_ws("|", F.lit(x), "sid")}).select(*columns) for x, r in parts]
    return reduce(DataFrame.unionByName, rows)


def statistics(records: DataFrame, segments: DataFrame | None = None) -> DataFrame:
    """Per stream and sid: records, mean and median gap, value variation, median absolute value, records per segment."""
    keys = ["stream", "sid"]
    gaps = written(ordering.before(records, "t", "_t", ("stream", "sid")).select(*keys, "v", (F.col("t") - F.col("_t")).alias("gap"), F.abs("v").alias("size")))
    out = gaps.groupBy(*keys).agg(F.count("*").alias("n"), F.avg("gap").alias("mean_gap"), F.max("gap").alias("max_gap"), (F.stddev_pop("v") / F.abs(F.avg("v"))).alias("cv"), F.min("v").alias("min_v"))
    out = out.join(ordering.quantiles(gaps, keys, {"median_abs": ("size", 0.5), "p99_abs": ("size", 0.99), "median_gap": ("gap", 0.5)}), keys, "left")
    out = out.select(*keys, "n", "mean_gap", "median_gap", "max_gap", "cv", "median_abs", "p99_abs", "min_v")
    if segments is None:
        return out
    s = segments.groupBy("stream", "sid").agg(F.count("*").alias("s"))
    return out.join(s, ["stream", "sid"]).withColumn("per_segment", F.col("n") / F.col("s"))


def blocks(records: DataFrame) -> DataFrame:
    """Block headers: height, t, n_tx, root of the block's records and the previous header's hash, chained in order."""
    from tsproof.functions import encoding

    body = records.withColumn("leaf", encoding.record_hash()).groupBy("height").agg(F.max("t").alias("t"), F.count("*").alias("n_tx"), F.sha2(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("i", "leaf"))), lambda x: x["leaf"]), "|"), 256).alias("root"))

    def chain(batches):
        import pyarrow as pa

        before = "0" * 64
        for b in batches:
            rows = b.to_pylist()
            for r in rows:
                r["prev_hash"] = before
                before = r["hash"] = encoding.sha(f"H|{r['height']}|{r['t']}|{r['root']}|{before}")
            yield pa.RecordBatch.from_pylist(rows, schema=pa.schema([("height", pa.int64()), ("t", pa.int64()), ("n_tx", pa.int64()), ("root", pa.string()), ("prev_hash", pa.string()), ("hash", pa.string())]))

    # the chain is sequential by definition; it runs over headers only
    return body.orderBy("height").coalesce(1).mapInArrow(chain, "height long, t long, n_tx long, root string, prev_hash string, hash string")
