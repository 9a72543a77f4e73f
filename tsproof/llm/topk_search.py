"""Exact top-k inner products by multi-resolution segment statistics.

Vectors become integers, floor(256 x).  Cutting both vectors into equal segments of width w, with segment means m and
deviations s, the inner product over a segment is at most ``w (m_x m_q + s_x s_q)``, and |x - q|^2 is correspondingly at
least ``sum w ((m_x - m_q)^2 + (s_x - s_q)^2)``.  The bound is computed for few segments first, then for more, down to
segments of two components; a pair whose bound lies below the query's k-th best score so far is dropped at that level,
and only survivors get exact scores.  A level is evaluated for the rows and queries that still have a pair.

The work is a grid: rows are dealt into groups of about ``row_bytes`` and queries into groups of about ``query_bytes`` by
a hash of the id, and each cell (row group, query group) is one group of a co-grouped map, so memory is bounded by the two
sizes, nothing passes through the driver, and a lost executor costs its cells only.  Statistics are made once per vector
and stored beside it in single precision; the slack of the bounds covers their rounding.  A cell sends k rows a query; the
final ranking combines those before its shuffle.

Defined cases: null vectors, vectors with null, NaN or infinite components and rows with a null id take no part; equal
scores go to the smaller id; of rows that share an id the smallest vector counts; vectors of other lengths than the
query's aren't its candidates; empty vectors score 0.  Components of any finite size are exact (whole numbers beyond
doubles included); a score of the result beyond 64 bits raises an error.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import ceil

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tsproof.llm import shared

ROW_BYTES, QUERY_BYTES = 32 << 20, 8 << 20
#: Relative slack of bounds in single precision.
SLACK = 1e-5
#: Components from here on are scaled before statistics are taken.
LARGE = 2.0**40
#: Stands for scores below 64 bits.
LOWEST = -(1 << 63) + 1
STORED = "id long, x array<double>, e int, norm double, stats array<float>"


def levels_for(d: int) -> tuple[int, ...]:
    """Segments per level, coarse to fine: 4, 16, 64 ... and half the components."""
    out, s = [], 4
    while s < d // 2:
        out.append(s)
        s *= 4
    return (*out, d // 2) if d >= 2 else ()


def integers(vectors: np.ndarray) -> np.ndarray:
    """floor(256 x) as doubles (exact below 2**53; infinite beyond doubles)."""
    with np.errstate(over="ignore"):
        return np.floor(256.0 * vectors.astype(np.float64))


def exact_integer(x: float) -> int:
    return int(x) * 256 if abs(x) >= 2.0**45 else int(np.floor(256.0 * x))


def scaled(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Vectors whose components are of moderate size, and the power of two that each was divided by."""
    top = np.abs(x).max(axis=1, initial=0)
    e = np.where(top >= LARGE, np.frexp(top)[1], 0)
    return np.where(e[:, None] > 0, np.ldexp(x, -e[:, None]) * 256.0, integers(np.where(e[:, None] > 0, 0.0, x))), e


def statistics(x: np.ndarray, segments: int) -> np.ndarray:
    """sqrt(w) * (means, deviations) of each segment: the inner product of two such rows bounds that of the vectors.
    Segments differ by one in width if the length isn't a multiple."""
    cuts = np.linspace(0, x.shape[1], min(segments, x.shape[1]) + 1).astype(int)
    width = np.diff(cuts)
    mean = np.add.reduceat(x, cuts[:-1], axis=1) / width
    centred = x - np.repeat(mean, width, axis=1)
    spread = np.sqrt(np.add.reduceat(centred * centred, cuts[:-1], axis=1) / width)
    return np.concatenate((mean, spread), axis=1) * np.sqrt(np.concatenate((width, width)))


class Vectors:
    """Ids, raw components, integers, and per level the statistics of some vectors of one length."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, e: np.ndarray, norm: np.ndarray, stats: np.ndarray):
        self.ids, self.x, self.e, self.norm, self.stats = ids, x, e, norm, stats
        with np.errstate(over="ignore"):
            self.whole, self.top = integers(x), np.abs(x).max(axis=1, initial=0) * 256.0

    @classmethod
    def of(cls, table: pa.Table, d: int) -> Vectors:
        cols = {c: table.column(c).combine_chunks() for c in table.column_names}
        flat = lambda c, n: cols[c].flatten().to_numpy(zero_copy_only=False).reshape(len(table), n)
        width = sum(2 * s for s in levels_for(d))
        return cls(cols["id"].to_numpy(), flat("x", d), cols["e"].to_numpy(), cols["norm"].to_numpy(), flat("stats", width))

    def take(self, at) -> Vectors:
        return Vectors(self.ids[at], self.x[at], self.e[at], self.norm[at], self.stats[at])


def _store(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Each vector with its scale, norm and statistics."""
    names = [f.split()[0] for f in STORED.split(", ")]
    for batch in batches:
        sizes = np.asarray(batch.column(1).value_lengths())
        for d in np.unique(sizes).tolist():
            b = batch.filter(pa.array(sizes == d))
            x, e = scaled(b.column(1).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, d))
            parts = [statistics(x, s) for s in levels_for(d)] or [np.zeros((b.num_rows, 0))]
            stats = np.concatenate(parts, axis=1).astype(np.float32)
            listed = pa.ListArray.from_arrays(pa.array(np.arange(b.num_rows + 1) * stats.shape[1], pa.int32()), pa.array(stats.reshape(-1)))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(e, pa.int32()), pa.array(np.sqrt((x * x).sum(axis=1))), listed], names=names)


class Best:
    """The k best (score, id) of each query, ties to the smaller id."""

    def __init__(self, count: int, k: int):
        self.k = k
        self.score = np.full((count, k), LOWEST, dtype=np.int64)
        self.ids = np.full((count, k), np.iinfo(np.int64).max, dtype=np.int64)
        self.filled = np.zeros(count, np.int64)

    def floor(self) -> np.ndarray:
        return np.where(self.filled >= self.k, self.score[:, -1].astype(np.float64), -np.inf)

    def offer(self, q: np.ndarray, ids: np.ndarray, score: np.ndarray) -> None:
        rows = np.unique(q)
        old = np.repeat(rows, np.minimum(self.filled[rows], self.k))
        kept = np.concatenate([np.arange(n) for n in np.minimum(self.filled[rows], self.k)] or [np.zeros(0, np.int64)]).astype(np.int64)
        q, ids, score = np.concatenate((old, q)), np.concatenate((self.ids[old, kept], ids)), np.concatenate((self.score[old, kept], score))
        order = np.lexsort((ids, -score, q))
        q, ids, score = q[order], ids[order], score[order]
        start = np.searchsorted(q, rows)
        rank = np.arange(len(q)) - np.repeat(start, np.diff([*start, len(q)]))
        top = rank < self.k
        self.score[q[top], rank[top]], self.ids[q[top], rank[top]] = score[top], ids[top]
        np.maximum.at(self.filled, q[top], rank[top] + 1)


def _reaches(bound: np.ndarray, power: np.ndarray, floor: np.ndarray) -> np.ndarray:
    """Bounds times powers of two that aren't below the floor; what overflows isn't."""
    with np.errstate(over="ignore"):
        return ~(np.ldexp(bound, power) < floor)


def _scores(q: Vectors, x: Vectors, mask: np.ndarray) -> np.ndarray:
    """Exact scores of the pairs in the mask: a product of doubles where all its sums are exact, else whole numbers."""
    with np.errstate(over="ignore", invalid="ignore"):
        unsure = mask & ~(np.outer(q.top, x.top) * max(x.x.shape[1], 1) < 2.0**53)
        fine_q, fine_x = np.where(np.isfinite(q.whole), q.whole, 0.0), np.where(np.isfinite(x.whole), x.whole, 0.0)
        out = fine_q @ fine_x.T
        out = np.where(np.abs(out) < 2.0**53, out, 0.0).astype(np.int64)
    for i, j in zip(*np.nonzero(unsure), strict=True):
        s = sum(exact_integer(a) * exact_integer(b) for a, b in zip(q.x[i].tolist(), x.x[j].tolist(), strict=True))
        if s >= 1 << 63:
            raise OverflowError(f"the score of {q.ids[i]} and {x.ids[j]} exceeds 64 bits")
        out[i, j] = max(s, LOWEST)
    return out


def candidates(q: Vectors, x: Vectors, floor: np.ndarray, shares: list | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query, row, score) of the pairs that reach the query's floor at every level.  ``shares`` collects the pairs left
    before each level and at the end."""
    qi, xi = np.arange(len(q.ids)), np.arange(len(x.ids))
    mask, at = q.ids[:, None] != x.ids[None, :], 0
    left = [int(mask.sum())]
    for s in (*levels_for(x.x.shape[1]), None):
        rows, cols = mask.any(axis=1), mask.any(axis=0)
        mask, qi, xi = mask[np.ix_(rows, cols)], qi[rows], xi[cols]
        if not mask.size:
            break
        if s is None:
            score = _scores(q.take(qi), x.take(xi), mask)
            mask &= score >= floor[qi][:, None]
            left.append(int(mask.sum()))
            break
        bound = (q.stats[qi, at : at + 2 * s] @ x.stats[xi, at : at + 2 * s].T).astype(np.float64) + SLACK * np.outer(q.norm[qi], x.norm[xi])
        mask &= _reaches(bound, q.e[qi][:, None] + x.e[xi][None, :], floor[qi][:, None])
        left.append(int(mask.sum()))
        at += 2 * s
    if shares is not None:
        shares.append(left)
    if not mask.size:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    a, b = np.nonzero(mask)
    return qi[a], xi[b], score[a, b]


def search(q: Vectors, x: Vectors, k: int, shares: list | None = None) -> Best:
    """The k best rows of each query.  The first rows are scored with no floor, which lifts the floors that prune the rest."""
    best = Best(len(q.ids), k)
    cuts = [0, *range(min(32, len(x.ids)), len(x.ids), 1024), len(x.ids)]
    for lo, hi in zip(cuts, cuts[1:]):
        part = x.take(slice(lo, hi))
        for c in range(0, len(q.ids), 1024):
            some = q.take(slice(c, c + 1024))
            qi, xi, score = candidates(some, part, best.floor()[c : c + 1024], shares if lo else None)
            if len(qi):
                best.offer(qi + c, part.ids[xi], score)
    return best


def _cell(k: int):
    names = ["query_id", "vec_id", "score"]

    def run(key: tuple, rows: pa.Table, queries: pa.Table) -> pa.Table:
        if not len(rows) or not len(queries):
            return pa.table({n: pa.array([], pa.int64()) for n in names})
        d = key[0].as_py()
        q = Vectors.of(queries.drop_columns(["d", "cell"]), d)
        best = search(q, Vectors.of(rows.drop_columns(["d", "cell"]), d), k)
        at, r = np.nonzero(np.arange(k)[None, :] < best.filled[:, None])
        return pa.table({"query_id": q.ids[at], "vec_id": best.ids[at, r], "score": best.score[at, r]})

    return run


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 5, id_col: str = "vec_id", vector_col: str = "embedding", row_bytes: int = ROW_BYTES, query_bytes: int = QUERY_BYTES) -> DataFrame:
    """query_id, rank, vec_id, score: the k rows of ``vectors`` with the largest integer inner product with each query."""

    def stored(df: DataFrame) -> DataFrame:
        x = F.col(vector_col)
        ok = x.isNotNull() & ~F.exists(x, lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf")))
        df = df.where(ok).select(F.col(id_col).cast("long").alias("id"), x.cast("array<double>").alias("x"))
        return shared.written(shared.one_row_per_id(df, "id", "x").mapInArrow(_store, STORED)).withColumn("d", F.size("x"))

    rows, asked = stored(vectors), stored(queries)
    size = [int(df.agg(F.coalesce(F.sum(8 * (F.size("x") + 2)), F.lit(0))).first()[0]) for df in (rows, asked)]
    # enough cells for all tasks, but none for less than a megabyte of rows
    r = max(1, ceil(size[0] / row_bytes), min(shared.partitions(vectors.sparkSession), size[0] >> 20))
    s = max(1, ceil(size[1] / query_bytes))
    group = lambda n: F.pmod(F.xxhash64("id", F.lit(5)), F.lit(n))
    left = rows.withColumn("_i", group(r)).withColumn("cell", F.explode(F.transform(F.sequence(F.lit(0), F.lit(s - 1)), lambda j: F.col("_i") * s + j))).drop("_i")
    right = asked.withColumn("_j", group(s)).withColumn("cell", F.explode(F.transform(F.sequence(F.lit(0), F.lit(r - 1)), lambda i: i * s + F.col("_j")))).drop("_j")
    found = left.groupBy("d", "cell").cogroup(right.groupBy("d", "cell")).applyInArrow(_cell(k), "query_id long, vec_id long, score long")
    rank = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    out = found.withColumn("rank", F.row_number().over(rank).cast("int")).where(F.col("rank") <= k)
    score = F.when(F.col("score") == LOWEST, F.raise_error(F.lit("a score lies below 64 bits")).cast("long")).otherwise(F.col("score"))
    return out.select("query_id", "rank", "vec_id", score.alias("score"))
