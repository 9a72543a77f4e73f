"""Closed-form covers of a position range in a right-ragged tree of fanout f over n leaves.

At level l the blocks that lie inside [lo, hi] are L..R with L = ceil(lo / f^l) and R = (hi + 1) div f^l - 1, or the last
block if hi is the last leaf.  A block belongs to the minimal cover if its parent isn't inside.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def depth_of(n: int, f: int) -> int:
    d = 0
    while f**d < n:
        d += 1
    return d


def depth_column(n: Column, f: int) -> Column:
    """Levels above the leaves: powers of f below n."""
    powers = [f**k for k in range(63) if f**k < 2**62]
    return F.size(F.filter(F.array(*[F.lit(p) for p in powers]), lambda p: p < n))


def cover(lo: int, hi: int, n: int, f: int = 2) -> list[tuple[int, int]]:
    """(lvl, idx) of the minimal cover, by level; empty if lo > hi."""
    out: list[tuple[int, int]] = []
    if lo > hi or n <= 0:
        return out

    def inside(lvl: int) -> tuple[int, int]:
        w = f**lvl
        return -(-lo // w), (n - 1) // w if hi == n - 1 else (hi + 1) // w - 1

    top = depth_of(n, f)
    for lvl in range(top + 1):
        left, right = inside(lvl)
        if left > right:
            break
        up = inside(lvl + 1) if lvl < top else (1, 0)
        if up[0] > up[1]:
            out += [(lvl, k) for k in range(left, right + 1)]
        else:
            out += [(lvl, k) for k in range(left, min(right, up[0] * f - 1) + 1)]
            out += [(lvl, k) for k in range(max(left, (up[1] + 1) * f), right + 1)]
    return out


def proof_parts(lo: int, hi: int, n: int, f: int = 2) -> dict[str, list[tuple[int, int]]]:
    """Cover of the window, leaves opened beside it, and siblings: together they tile 0..n-1."""
    a, b = min(lo - 1, hi + 1), max(lo - 1, hi + 1)
    opened = sorted({x for x in (a, b) if 0 <= x < n})
    return {"cover": cover(lo, hi, n, f), "edge": [(0, x) for x in opened], "sibling": cover(0, min(a, n) - 1, n, f) + cover(max(b + 1, 0), n - 1, n, f)}


def _steps(a: Column, b: Column) -> Column:
    """a..b, empty if a > b."""
    return F.when(a <= b, F.sequence(a, F.greatest(a, b))).otherwise(F.array().cast("array<bigint>"))


def with_cover(df: DataFrame, lo: Column, hi: Column, n: Column, f: int = 2, most_levels: int = 48) -> DataFrame:
    """One row per cover node of each row: adds lvl and idx.  Only arithmetic and generators: no join."""
    df = df.withColumns({"_lo": lo.cast("long"), "_hi": hi.cast("long"), "_n": n.cast("long")}).where("_lo <= _hi and _n > 0")
    df = df.withColumn("_top", F.least(depth_column(F.col("_n"), f), F.lit(most_levels)))
    df = df.withColumn("lvl", F.explode(F.sequence(F.lit(0), F.col("_top"))))

    def side(level: Column) -> tuple[Column, Column]:
        w = F.pow(F.lit(f), level).cast("long")
        return F.ceil(F.col("_lo") / w).cast("long"), F.when(F.col("_hi") == F.col("_n") - 1, F.floor((F.col("_n") - 1) / w)).otherwise(F.floor((F.col("_hi") + 1) / w) - 1).cast("long")

    left, right = side(F.col("lvl"))
    up_left, up_right = side(F.col("lvl") + 1)
    df = df.withColumns({"_l": left, "_r": right, "_ul": up_left, "_ur": up_right})
    no_parent = (F.col("lvl") == F.col("_top")) | (F.col("_ul") > F.col("_ur"))
    parts = F.concat(_steps(F.col("_l"), F.least(F.col("_r"), F.col("_ul") * f - 1)), _steps(F.greatest(F.col("_l"), (F.col("_ur") + 1) * f), F.col("_r")))
    ids = F.when(no_parent, _steps(F.col("_l"), F.col("_r"))).otherwise(parts)
    return df.withColumn("idx", F.explode(ids)).drop("_lo", "_hi", "_n", "_top", "_l", "_r", "_ul", "_ur")


def proof_keys(located: DataFrame, f: int = 2) -> DataFrame:
    """role, lvl, idx for rows (qid, sid, lo, hi, n)."""
    base = located.select("qid", "sid", "lo", "hi", "n")
    a, b = F.least(F.col("lo") - 1, F.col("hi") + 1), F.greatest(F.col("lo") - 1, F.col("hi") + 1)
    n = F.col("n")
    keep = ["qid", "sid", "role", "lvl", "idx"]
    inner = with_cover(base, F.col("lo"), F.col("hi"), n, f).withColumn("role", F.lit("cover"))
    left = with_cover(base, F.lit(0), F.least(a, n) - 1, n, f).withColumn("role", F.lit("sibling"))
    right = with_cover(base, F.greatest(b + 1, F.lit(0)), n - 1, n, f).withColumn("role", F.lit("sibling"))
    edges = base.withColumn("idx", F.explode(F.array_distinct(F.array(a, b)))).where("idx >= 0 and idx < n").withColumns({"role": F.lit("edge"), "lvl": F.lit(0)})
    return inner.select(*keep).unionByName(left.select(*keep)).unionByName(right.select(*keep)).unionByName(edges.select(*keep))
