"""Structured Streaming: ingest of blocks into trees, late rows, windows, stateful frontier."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tsproof.functions import encoding
from tsproof.operators import aggtree
from tsproof.sources import RECORD


def read_blocks(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """Records as they arrive: one file is one or more blocks."""
    return spark.readStream.schema(RECORD).option("maxFilesPerTrigger", files_per_batch).parquet(path)


FRONT = "sid string, n long, t long, height long, i int"
NODES = "sid string, lvl int, idx long, s decimal(38,0), n long, mn long, mx long, t_lo long, t_hi long, w decimal(38,0), eta string"


class TreeSink:
    """``foreachBatch`` target: orders a batch behind what is stored, sends late rows to quarantine, appends to the tree.

    Every batch writes partitions named by its id, so a batch that runs again overwrites its own output only.  A batch reads
    the frontier (last position of each stream) and the spine (full blocks on the right edge), not the stored tree.
    """

    def __init__(self, path: str, fanout: int = 2):
        self.path, self.fanout = path, fanout

    def _before(self, spark: SparkSession, table: str, batch: int, schema: str) -> DataFrame:
        """Rows of earlier batches with their batch_id: one scan, pruned by partition."""
        schema += ", batch_id long"
        if batch == 0:
            return spark.createDataFrame([], schema)
        return spark.read.schema(schema).parquet(f"{self.path}/{table}").where(F.col("batch_id") < batch)

    def __call__(self, df: DataFrame, batch: int) -> None:
        spark = df.sparkSession
        seen = self._before(spark, "frontier", batch, FRONT).groupBy("sid").agg(F.max(F.struct("n", "t", "height", "i", "batch_id")).alias("f")).select("sid", "f.*")
        joined = df.select("sid", "t", "height", "i", "v", "tags").join(seen.select("sid", "n", F.struct("t", "height", "i").alias("f")), "sid", "left")
        fresh = F.col("f").isNull() | (F.struct("t", "height", "i") > F.col("f"))
        write = lambda out, table: out.write.mode("overwrite").parquet(f"{self.path}/{table}/batch_id={batch}")
        stored = lambda table: spark.read.parquet(f"{self.path}/{table}/batch_id={batch}")
        write(joined.where(~fresh).drop("f", "n"), "quarantine")
        order = Window.partitionBy("sid").orderBy("t", "height", "i")
        rows = joined.where(fresh).withColumn("pos", F.row_number().over(order) - 1 + F.coalesce("n", F.lit(0))).drop("f", "n")
        write(rows.select("sid", "t", "height", "i", "v", "tags", F.col("pos").cast("long").alias("pos")), "records")
        rows = stored("records")
        last = rows.groupBy("sid").agg(F.max(F.struct((F.col("pos") + 1).alias("n"), "t", "height", "i")).alias("f")).select("sid", "f.*")
        write(last, "frontier")
        last = stored("frontier")
        # a stream's spine is the one written by the last batch that held rows of it
        spine = self._before(spark, "spine", batch, NODES).join(seen.select("sid", "batch_id"), ["sid", "batch_id"], "left_semi").drop("batch_id")
        write(aggtree.grow(spine, aggtree.record_leaves(rows), self.fanout), "nodes")
        write(aggtree.spine(spine.unionByName(stored("nodes")), last, self.fanout), "spine")

    def nodes(self, spark: SparkSession, batch: int) -> DataFrame:
        """Current nodes after the batches below ``batch``: the latest version of each."""
        rows = self._before(spark, "nodes", batch, NODES)
        latest = rows.groupBy("sid", "lvl", "idx").agg(F.max_by(F.struct(*encoding.ALPHA, "eta"), "batch_id").alias("x"))
        return latest.select("sid", "lvl", "idx", "x.*")


def ingest(spark: SparkSession, source: str, target: str, fanout: int = 2) -> int:
    """Runs all files of ``source`` through the sink with a checkpoint; returns the number of batches so far."""
    sink = TreeSink(target, fanout)
    q = read_blocks(spark, source).writeStream.foreachBatch(sink).option("checkpointLocation", f"{target}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    last = q.lastProgress
    return (last["batchId"] + 1) if last else 0


def with_late_policy(df: DataFrame, ts: str, delay: str) -> DataFrame:
    return df.withWatermark(ts, delay)


def window_agg(df: DataFrame, ts: str, v: str, kind: str = "tumbling", size: str = "1 day", slide: str = "12 hours") -> DataFrame:
    """Tumbling, sliding or session windows; the same plan runs on batches and streams."""
    w: Column = {"tumbling": lambda: F.window(ts, size), "sliding": lambda: F.window(ts, size, slide), "session": lambda: F.session_window(ts, size)}[kind]()
    out = df.groupBy(w.alias("w")).agg(F.sum(v).alias("s"), F.count("*").alias("n"))
    return out.select(F.unix_micros("w.start").alias("t_lo"), F.unix_micros("w.end").alias("t_hi"), "s", "n")


def dedup(df: DataFrame, key: str) -> DataFrame:
    return df.dropDuplicatesWithinWatermark([key])


def enrich(stream: DataFrame, static: DataFrame, key: str) -> DataFrame:
    return stream.join(static, key, "left")


FRONTIER = "sid string, n long, s long, mn long, mx long, root string"


def append_frontier(records: DataFrame, fanout: int = 2) -> DataFrame:
    """Root of each stream after each batch, with only the frontier (at most f - 1 nodes a level) as state."""
    state = "n long, nodes string"

    def leaf(sid: str, pos: int, r) -> tuple[str, dict]:
        rec = {"t": int(r.t), "height": int(r.height), "i": int(r.i), "v": int(r.v), "tags": dict(r.tags or {})}
        return encoding.py_record_hash(sid, pos, rec), {"s": rec["v"], "n": 1, "mn": rec["v"], "mx": rec["v"], "t_lo": rec["t"], "t_hi": rec["t"], "w": 0}

    def fold(kids: list) -> list:
        a = [k[1] for k in kids]
        return [encoding.py_node_hash(kids), {"s": sum(x["s"] for x in a), "n": sum(x["n"] for x in a), "mn": min(x["mn"] for x in a), "mx": max(x["mx"] for x in a), "t_lo": a[0]["t_lo"], "t_hi": max(x["t_hi"] for x in a), "w": 0}]

    def step(key: tuple, frames: Iterator[pd.DataFrame], held) -> Iterator[pd.DataFrame]:
        import json

        n, levels = held.get if held.exists else (0, "[]")
        levels = json.loads(levels)
        rows = pd.concat(list(frames)).sort_values(["t", "height", "i"])
        for r in rows.itertuples(index=False):
            carry, lvl = list(leaf(key[0], n, r)), 0
            n += 1
            while True:
                if lvl == len(levels):
                    levels.append([])
                levels[lvl].append(carry)
                if len(levels[lvl]) < fanout:
                    break
                carry, levels[lvl], lvl = fold(levels[lvl]), [], lvl + 1
        held.update((n, json.dumps(levels)))
        carry, depth = None, 0
        while fanout**depth < n:
            depth += 1
        for lvl in range(depth):
            kids = (levels[lvl] if lvl < len(levels) else []) + ([carry] if carry else [])
            carry = fold(kids) if kids else None
        top = carry or levels[depth][0]
        if carry is None or (depth < len(levels) and levels[depth]):
            top = levels[depth][0]
        yield pd.DataFrame([{"sid": key[0], "n": n, "s": top[1]["s"], "mn": top[1]["mn"], "mx": top[1]["mx"], "root": top[0]}])

    return records.groupBy("sid").applyInPandasWithState(step, FRONTIER, state, "update", "NoTimeout")
