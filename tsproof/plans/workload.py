"""Query workloads from a portable integer generator, so that any engine draws the same windows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tsproof.plans import ordering

MODULUS = 2_147_483_647  # prime; state * 48271 stays below 2^63


def draw(key: Column, seed: int) -> Column:
    """0..MODULUS-1 for an integer key (three multiplicative steps; same in SQL with bigint arithmetic)."""
    x = (key * 48_271 + F.lit(seed * 7_919 + 12_345)) % MODULUS
    for _ in range(2):
        x = (x * 48_271 + 11) % MODULUS
    return x


def draw_sql(key: str, seed: int) -> str:
    x = f"((({key})::bigint * 48271 + {seed * 7919 + 12345}) % {MODULUS})"
    for _ in range(2):
        x = f"(({x} * 48271 + 11) % {MODULUS})"
    return x


def windows(records: DataFrame, lengths: list[int], count: int, seed: int = 1) -> DataFrame:
    """(qid, sid, t_s, t_e, k): ``count`` random windows of each length in records for every stream long enough."""
    spark = records.sparkSession
    n = records.groupBy("sid").agg(F.count("*").alias("_n"))
    grid = spark.range(len(lengths) * count).select(F.col("id").alias("_q"), F.element_at(F.array(*[F.lit(x) for x in lengths]), (F.expr(f"id div {count}") + 1).cast("int")).cast("long").alias("k"))
    starts = n.join(F.broadcast(grid)).where("k < _n").withColumn("_lo", draw(F.col("_q"), seed) % (F.col("_n") - F.col("k")))
    starts = starts.withColumns({"_hi": F.col("_lo") + F.col("k") - 1})
    ends = starts.select("sid", "_q", "k", F.explode(F.array(F.struct(F.col("_lo").alias("p"), F.lit(0).alias("e")), F.struct(F.col("_hi").alias("p"), F.lit(1).alias("e")))).alias("x"))
    at = ends.select("sid", "_q", "k", F.col("x.p").alias("pos"), F.col("x.e").alias("e")).join(records.select("sid", "pos", "t"), ["sid", "pos"])
    out = at.groupBy("sid", "_q", "k").agg(F.max(F.when(F.col("e") == 0, F.col("t"))).alias("t_s"), F.max(F.when(F.col("e") == 1, F.col("t"))).alias("t_e"))
    return out.select((F.col("_q") + F.lit(seed * 1_000_000)).alias("qid"), "sid", "t_s", "t_e", "k")


def per_stream(records: DataFrame, each: int = 1) -> DataFrame:
    """``each`` windows for every sid: the middle part of its time extent, cut in equal spans; qid = rank * each + i."""
    span = records.groupBy("sid").agg(F.min("t").alias("a"), F.max("t").alias("b"))
    ranked = ordering.number(span.withColumn("_all", F.lit(0)), ["_all"], ["sid"], "_r").drop("_all")
    grid = ranked.withColumn("_i", F.explode(F.sequence(F.lit(0), F.lit(each - 1))))
    step = (F.expr("(b - a) div 4") / each).cast("long")
    lo = F.col("a") + F.expr("(b - a) div 4") + F.col("_i") * step
    return grid.select((F.col("_r") * each + F.col("_i")).alias("qid"), "sid", lo.alias("t_s"), (F.col("b") - F.expr("(b - a) div 4")).alias("t_e"))


def by_time(records: DataFrame, spans: list[int], count: int, seed: int = 1) -> DataFrame:
    """Windows of given lengths in microseconds."""
    ext = records.groupBy("sid").agg(F.min("t").alias("a"), F.max("t").alias("b"))
    grid = records.sparkSession.range(len(spans) * count).select(F.col("id").alias("_q"), F.element_at(F.array(*[F.lit(x) for x in spans]), (F.expr(f"id div {count}") + 1).cast("int")).cast("long").alias("k"))
    lo = F.col("a") + draw(F.col("_q"), seed) * F.expr("(b - a) div 2147483647 + 1") % F.greatest(F.col("b") - F.col("a"), F.lit(1))
    return ext.join(F.broadcast(grid)).select((F.col("_q") + seed * 1_000_000).alias("qid"), "sid", lo.alias("t_s"), (lo + F.col("k") - 1).alias("t_e"), "k")


def sliding(spark: SparkSession, seq: DataFrame) -> DataFrame:
    """Windows of sequences (seq_id, sid, t_s, t_e, delta, count): one row per slide i; qid = seq_id * 1000 + i."""
    out = seq.withColumn("i", F.explode(F.sequence(F.lit(0).cast("long"), F.col("count") - 1)))
    return out.select((F.col("seq_id") * 1000 + F.col("i")).alias("qid"), "seq_id", "i", "sid", (F.col("t_s") + F.col("i") * F.col("delta")).alias("t_s"), (F.col("t_e") + F.col("i") * F.col("delta")).alias("t_e"))


def edge_cases(records: DataFrame) -> DataFrame:
    """Before the stream, after it, the whole, one instant, an empty gap (between the two first distinct times), head, tail."""
    x = records.groupBy("sid").agg(F.min("t").alias("a"), F.max("t").alias("b"))
    second = records.join(x, "sid").where("t > a").groupBy("sid").agg(F.min("t").alias("a2"))
    x = x.join(second, "sid")
    cases = F.array(
        F.struct(F.lit(0).alias("k"), (F.col("a") - 100).alias("t_s"), (F.col("a") - 1).alias("t_e")),
        F.struct(F.lit(1).alias("k"), (F.col("b") + 1).alias("t_s"), (F.col("b") + 100).alias("t_e")),
        F.struct(F.lit(2).alias("k"), F.col("a").alias("t_s"), F.col("b").alias("t_e")),
        F.struct(F.lit(3).alias("k"), F.col("a2").alias("t_s"), F.col("a2").alias("t_e")),
        F.struct(F.lit(4).alias("k"), (F.col("a") + 1).alias("t_s"), (F.col("a2") - 1).alias("t_e")),
        F.struct(F.lit(5).alias("k"), (F.col("a") - 5).alias("t_s"), F.col("a2").alias("t_e")),
        F.struct(F.lit(6).alias("k"), F.col("a2").alias("t_s"), (F.col("b") + 5).alias("t_e")),
    )
    return x.select("sid", F.explode(cases).alias("c")).select(F.col("c.k").cast("long").alias("qid"), "sid", F.col("c.t_s").alias("t_s"), F.col("c.t_e").alias("t_e"))


def skewed(records: DataFrame, skew: float, count: int, k: int, regions: int = 16, hot: int = 5, seed: int = 1) -> DataFrame:
    """Windows of k records that start in the hot region with probability ``skew``, else anywhere."""
    return skewed_each(records, (skew,), count, F.lit(k), regions, hot, seed).drop("skew", "k")


def skewed_each(records: DataFrame, skews: tuple[float, ...], count: int, k: Column, regions: int = 16, hot: int = 5, seed: int = 1) -> DataFrame:
    """The same for several skews at once, k an expression of sid and the stream's size ``_n``."""
    n = records.groupBy("sid").agg(F.count("*").alias("_n")).withColumn("k", k.cast("long"))
    q = records.sparkSession.range(count).select(F.col("id").alias("_q"), F.explode(F.array(*[F.lit(float(x)) for x in skews])).alias("skew"))
    u, at = draw(F.col("_q"), seed) % 1000, draw(F.col("_q"), seed + 1)
    room = F.col("_n") - F.col("k")
    width = F.greatest(F.expr(f"_n div {regions}"), F.lit(1))
    often = F.element_at(F.create_map(*[F.lit(y) for x in dict.fromkeys(skews) for y in (float(x), int(x * 1000))]), F.col("skew"))
    lo = F.when(u < often, F.least(F.lit(hot) * width + at % width, room - 1)).otherwise(at % room)
    s = n.where(F.col("_n") > F.col("k")).join(F.broadcast(q)).select("sid", "_q", "skew", "k", lo.alias("_lo"))
    r = records.select("sid", F.col("pos"), "t")
    s = s.join(r.select("sid", F.col("pos").alias("_lo"), F.col("t").alias("t_s")), ["sid", "_lo"])
    s = s.withColumn("_hi", F.col("_lo") + F.col("k") - 1).join(r.select("sid", F.col("pos").alias("_hi"), F.col("t").alias("t_e")), ["sid", "_hi"])
    return s.select(F.col("_q").alias("qid"), "sid", "t_s", "t_e", F.col("_lo").alias("lo"), F.col("_hi").alias("hi"), "skew", "k")


def touch_counts(located: DataFrame, n: int | str, regions: int = 16) -> DataFrame:
    """(sid, region, f_touch, f_edge): windows that overlap a region, and window ends that fall into it; ``n`` is the stream's
    size or the column that holds it."""
    size = f"greatest({n} div {regions}, 1)"
    last = regions - 1
    r = located.where("lo <= hi").select("sid", F.least(F.expr(f"lo div {size}"), F.lit(last)).alias("a"), F.least(F.expr(f"hi div {size}"), F.lit(last)).alias("b"))
    x = r.select("sid", F.explode(F.transform(F.sequence("a", "b"), lambda g: F.struct(g.alias("region"), ((g == F.col("a")).cast("int") + (g == F.col("b")).cast("int")).alias("e")))).alias("x"))
    return x.groupBy("sid", F.col("x.region").alias("region")).agg(F.count("*").alias("f_touch"), F.sum("x.e").alias("f_edge"))


def split(queries: DataFrame, seed: int = 3) -> tuple[DataFrame, DataFrame]:
    """Repeatable halves: one to fit a policy on, one to measure it."""
    side = draw(F.col("qid"), seed) % 2
    return queries.where(side == 0), queries.where(side == 1)
