"""SQL surface: cover nodes as a table function, proof checks and folds as functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tsproof.functions import cover
from tsproof.operators import client


@F.udtf(returnType=T.StructType([T.StructField("lvl", T.IntegerType()), T.StructField("idx", T.LongType())]))
class CoverNodes:
    """cover_nodes(lo, hi, n, f) in a LATERAL join."""

    def eval(self, lo: int, hi: int, n: int, f: int):
        yield from cover.cover(lo, hi, n, f)


VERDICT = T.StructType([T.StructField("accepted", T.BooleanType()), T.StructField("reason", T.StringType()), *[T.StructField(c, T.LongType()) for c in ("s", "n", "mn", "mx")]])


@F.udf(returnType=VERDICT)
def verify_window(sid: str, t_s: int, t_e: int, proof: list, anchor) -> tuple:
    """The client's check of one window: only the query, its proof and the anchor."""
    rows = [x.asDict(recursive=True) for x in proof or []]
    v = client.verify({"sid": sid, "t_s": t_s, "t_e": t_e}, rows, anchor.asDict(recursive=True) if anchor else None)
    return v.accepted, v.reason, v.s, v.n, v.mn, v.mx


@F.pandas_udf(T.LongType())
def fold_sum(v: pd.Series) -> int:
    """Grouped fold of partial sums: a user-defined aggregate."""
    return int(v.sum())


def register(spark: SparkSession, sf_dir: str | None = None) -> None:
    """Functions, and a view per table of a folder if one is given."""
    spark.udtf.register("cover_nodes", CoverNodes)
    spark.udf.register("fold_sum", fold_sum)
    spark.udf.register("verify_window", verify_window)
    if sf_dir:
        for name in ("events", "orders", "lineitem", "customer", "nation", "region", "part", "supplier"):
            spark.read.parquet(f"{sf_dir}/{name}.parquet").createOrReplaceTempView(name)
