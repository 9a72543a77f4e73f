"""Readers, writers and shared scratch space."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Schema of canonical records: one row per stream position.
RECORD = "sid string, t long, height long, i int, v long, tags map<string,string>"


def read_table(spark: SparkSession, directory: str, name: str, columns: list[str] | None = None) -> DataFrame:
    """A Parquet table; only ``columns`` are scanned."""
    df = spark.read.parquet(f"{directory}/{name}.parquet")
    return df.select(*columns) if columns else df


def scratch(spark: SparkSession) -> str:
    """A fresh path in the folder that driver and executors share (``spark.checkpoint.dir``); a local one on a local
    master only, as executors of a cluster couldn't see it."""
    base = spark.conf.get("spark.checkpoint.dir", None) or getattr(spark, "_proof_scratch", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = spark._proof_scratch = tempfile.mkdtemp(prefix="tsproof-")
    path = f"{base.rstrip('/')}/t-{uuid.uuid4().hex}"
    _made.setdefault(id(spark), []).append(path)
    return path


_made: dict[int, list[str]] = {}


def release(spark: SparkSession) -> int:
    """Deletes every scratch path of the session; frames that read one can't be used any more.  Returns their number."""
    paths = _made.pop(id(spark), [])
    for p in paths:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(p)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
    return len(paths)


def fingerprint(spark: SparkSession, directory: str) -> str:
    """Names, lengths and times of a folder's files: changes with the input."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(directory)
    system = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    return "|".join(sorted(f"{x.getPath().getName()}:{x.getLen()}:{x.getModificationTime()}" for x in system.listStatus(path)))


#: Rows up to which a side is broadcast; larger sides are shuffled.
BROADCAST_ROWS = 500_000


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """The frame with a broadcast hint if a bounded count finds it small enough, else as it is."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def written(df: DataFrame) -> DataFrame:
    """The frame written once and read back, which cuts its lineage."""
    path = scratch(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def round_trip(df: DataFrame, form: str) -> DataFrame:
    """Flat columns through a file format and back."""
    path = scratch(df.sparkSession)
    options = {"header": "true"} if form == "csv" else {}
    if form == "text":  # one column of JSON lines, which keeps nulls and types
        df.select(F.to_json(F.struct(*df.columns)).alias("value")).write.text(path)
        parsed = df.sparkSession.read.text(path).select(F.from_json("value", df.schema).alias("x"))
        return parsed.select("x.*")
    df.write.format(form).options(**options).save(path)
    return df.sparkSession.read.format(form).options(**options).schema(df.schema).load(path)


def write_nodes(nodes: DataFrame, path: str, buckets: int = 16) -> None:
    """Node tables on disk: one folder per band of levels, sorted so that row groups skip by stream and index."""
    banded = nodes.withColumns({"sid_bucket": F.pmod(F.xxhash64("sid"), F.lit(buckets)), "lvl_band": F.expr("lvl div 8")})
    ordered = banded.repartition("sid_bucket", "lvl_band").sortWithinPartitions("sid", "lvl", "idx")
    ordered.write.partitionBy("lvl_band", "sid_bucket").parquet(path)


def connector_options(kind: str, **given: str) -> dict[str, str]:
    """Options for sources that need a network; pass them to ``spark.read.format(kind)``."""
    base = {
        "jdbc": {"fetchsize": "10000", "partitionColumn": "height", "numPartitions": "64"},
        "kafka": {"startingOffsets": "earliest", "failOnDataLoss": "true", "maxOffsetsPerTrigger": "1000000"},
        "rate": {"rowsPerSecond": "1000"},
    }
    if kind not in base:
        raise ValueError(f"unknown connector {kind!r}")
    return base[kind] | given
