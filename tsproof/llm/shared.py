"""Session helpers: shared scratch space, table reading, partition counts and defined results for odd inputs."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

WORD = r"[^\x20\x09-\x0D]+"


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def scratch(spark: SparkSession) -> str:
    """A fresh path in the folder that driver and executors share (``spark.checkpoint.dir``).

    Where the setting is absent a local folder is used, on a local master only: executors of a cluster couldn't see it.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or getattr(spark, "_llm_scratch", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = spark._llm_scratch = tempfile.mkdtemp(prefix="llm-")
    path = f"{base.rstrip('/')}/llm-{uuid.uuid4().hex}"
    _made.setdefault(id(spark), []).append(path)
    return path


_made: dict[int, list[str]] = {}


def mark(spark: SparkSession) -> int:
    """A point in the list of scratch paths, for ``release``."""
    return len(_made.get(id(spark), []))


def release(spark: SparkSession, since: int = 0, keep: tuple[DataFrame, ...] = ()) -> int:
    """Deletes the scratch paths made after ``since``, but for those that the frames of ``keep`` read; returns their
    number.  Frames that read a deleted path can't be used any more, so call it once their results are written."""
    made = _made.get(id(spark), [])
    used = {f.split("/llm-")[-1].split("/")[0] for df in keep for f in df.inputFiles()}
    gone = [p for p in made[since:] if p.rsplit("/llm-", 1)[-1] not in used]
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    for p in gone:
        path = jvm.org.apache.hadoop.fs.Path(p)
        path.getFileSystem(conf).delete(path, True)
    _made[id(spark)] = made[:since] + [p for p in made[since:] if p not in set(gone)]
    return len(gone)


def written(df: DataFrame) -> DataFrame:
    """The frame written once to the shared folder and read back: later uses neither recompute it nor need its
    shuffle files, so a lost executor costs a read, not a rerun."""
    path = scratch(df.sparkSession)
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def give_back() -> None:
    """Returns memory that the driver's Python has freed to the system; allocators keep it otherwise, for the whole session."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc only
    if trim:
        trim(0)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def one_row_per_id(df: DataFrame, key: str, *others: str) -> DataFrame:
    """Columns (key, others) with one row per non-null key.

    Of rows that share a key, the one with the smallest values of ``others`` stays.  The extra shuffle is only
    planned if a count over the keys alone finds a repeated one.
    """
    df = df.select(key, *others).where(F.col(key).isNotNull())
    twice = df.groupBy(key).count().where("count > 1").limit(1)
    if twice.isEmpty():
        return df
    smallest = F.min(F.struct(*[F.col(c).alias(f"_{i}") for i, c in enumerate(others)])).alias("_least")
    picked = df.groupBy(key).agg(smallest)
    return picked.select(key, *[F.col(f"_least._{i}").alias(c) for i, c in enumerate(others)])


def crc_bucket(key: str | Column, modulus: int) -> Column:
    """crc32 of the id written as text, modulo ``modulus``."""
    key = F.col(key) if isinstance(key, str) else key
    return F.crc32(key.cast("string").cast("binary")) % modulus
