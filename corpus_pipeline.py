"""A corpus pipeline: toxicity, line dedup, near dedup, benchmark decontamination, packing.

Each stage takes (spark, docs, sf_dir), works on all rows its predecessor kept, and is written as Parquet before the next
one reads it.  All but the last return the columns of ``documents``.

Defined cases of all stages: an empty table gives no rows; rows with a null doc_id are scored, tiled and packed like
others, but have no lines removed and are no one's copy; of rows that share a doc_id the operators judge the smallest
text, and none of them is dropped for another; null and empty texts pass every filter and are packed with 0 tokens.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tsproof.llm import decontamination, line_dedup, near_dedup, packing, shared, toxicity


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose score stays below the threshold; the model never learns from the held-out quarter."""
    held_out = F.coalesce(shared.crc_bucket("doc_id", 4) == 2, F.lit(False))
    model = toxicity.train(docs, shared.table(spark, sf_dir, "labels"), held_out)
    return toxicity.score(docs, model).where(F.col("_score") < toxicity.THRESHOLD).select(*docs.columns)


def drop_common_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the line blocks that an earlier document has; n_chars follows the text."""
    out = line_dedup.line_dedup(docs)
    n = F.when(F.col("_lines_removed") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))
    return out.withColumn("n_chars", n).select(*docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group; rows without an id stay."""
    gone = near_dedup.near_duplicates(docs, shingle=5, per_cent=80).where("not kept").select(F.col("doc_id").alias("_id"))
    return docs.join(gone, docs["doc_id"].cast("long") == gone["_id"], "left_anti").select(*docs.columns)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows none of whose benchmark items is covered by half or more; null and empty texts cover nothing and stay."""
    return decontamination.decontaminate(docs, shared.table(spark, sf_dir, "benchmark"), threshold=0.5)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row per piece of a document: bin, capacity and offset; texts without words have one row and no bin."""
    return packing.best_fit(packing.word_lengths(docs))


STAGES = [("toxicity", drop_toxic), ("line_dedup", drop_common_lines), ("minhash_near_dedup", drop_near_copies), ("benchmark_decontamination", drop_leaks), ("best_fit_packing", pack)]

#: Learned scores and alignment have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, start = shared.table(spark, sf_dir, "documents"), shared.mark(spark)
    for _, stage in STAGES[:-1]:
        docs = shared.written(stage(spark, docs, sf_dir))
        shared.release(spark, start, keep=(docs,))  # what the stage wrote on its way, and its input
    return STAGES[-1][1](spark, docs, sf_dir)
