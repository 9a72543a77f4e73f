"""Benchmark decontamination by greedy string tiling.

Words are lower-cased (A-Z) with ASCII punctuation as blanks.  Rolling hashes of every run of ``seed`` words in a document
meet the seed table of the benchmark; only (document, item) pairs that share a seed are tiled.  Tiling takes the longest
common run of unmarked words, marks it on both sides, and goes on until no run of ``seed`` words is left, so passages
that were cut and reordered still add up.  The words of each tile are compared themselves, so equal hashes of different
words never count.  Coverage is the share of the item's words inside tiles; an item is leaked
if coverage reaches ``threshold``.

Equal seeds of a pair are listed only while they are few (in proportion to its words); pairs of repetitive texts look for
each longest run by bisection on its length instead, in memory of the two texts' size.  Both give the same tiles.

The benchmark passes through the driver in blocks of checked size, one at a time: a block's seed table is sent to all
tasks, documents never move, and where there are further blocks the documents with their best item so far are written
before the next block is sent and the last one's broadcast is dropped.

Defined cases: null and empty texts and items have no words and match nothing; an item of fewer words than a seed counts
as covered if all of it occurs as one run, or, if it has fewer than ``shortest`` words, if it is the whole document; ties
go to the smaller item_id; repeated rows are judged each; null ids are kept; benchmark rows with null ids are left out.
"""

from __future__ import annotations

import heapq
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tsproof.llm import shared, textkit

U64 = np.uint64
BLOCK_BYTES = 8 << 20
FOUND = "_leak_item long, _leak_coverage double, _leak_tiles int, _leak_words long"


Same = Callable[[int, int, int], np.ndarray]


def _listed(doc: np.ndarray, item: np.ndarray, size: int, most: int) -> tuple[np.ndarray, np.ndarray] | None:
    """All pairs of equal ``size``-word runs, if there are at most ``most``."""
    d, i = textkit.windows(doc, size), textkit.windows(item, size)
    order = np.argsort(i, kind="stable")
    lo, hi = np.searchsorted(i[order], d, "left"), np.searchsorted(i[order], d, "right")
    n = hi - lo
    if n.sum() > most:
        return None
    at = np.repeat(np.arange(len(d)), n)
    nth = np.arange(len(at)) - np.repeat(np.cumsum(n) - n, n)
    return at, order[lo[at] + nth]


def _by_diagonals(seeds: tuple[np.ndarray, np.ndarray], doc: np.ndarray, item: np.ndarray, size: int, same: Same) -> list[tuple[int, int, int]]:
    """Tiles from listed seeds: the longest runs of each diagonal first, cut where words are marked meanwhile."""
    d, i = seeds
    order = np.lexsort((d, d - i))
    d, i = d[order], i[order]
    first = np.flatnonzero(np.concatenate(([True], (np.diff(d) != 1) | (np.diff(d - i) != 0)))) if len(d) else np.zeros(0, np.int64)
    length = np.diff([*first, len(d)]) + size - 1
    heap = list(zip((-length).tolist(), d[first].tolist(), i[first].tolist(), strict=True))
    heapq.heapify(heap)
    used_doc, used_item = np.zeros(len(doc), bool), np.zeros(len(item), bool)
    out = []
    while heap:
        n, x, y = heapq.heappop(heap)
        n = -n
        free = ~(used_doc[x : x + n] | used_item[y : y + n])
        if free.all() and (free := same(x, y, n)).all():
            used_doc[x : x + n] = used_item[y : y + n] = True
            out.append((x, y, n))
            continue
        for a, b in zip(*textkit.runs(free), strict=True):
            if b - a >= size:
                heapq.heappush(heap, (-int(b - a), int(x + a), int(y + a)))
    return out


def _by_length(doc: np.ndarray, item: np.ndarray, size: int, same: Same) -> list[tuple[int, int, int]]:
    """The same tiles without a list of seeds: a common run of n unmarked words implies one of n - 1."""
    doc, item = doc.copy(), item.copy()
    used_doc, used_item = np.zeros(len(doc), bool), np.zeros(len(item), bool)

    def open_runs(words: np.ndarray, used: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
        marked = np.concatenate(([0], np.cumsum(used)))
        at = np.flatnonzero(marked[n:] == marked[: len(marked) - n]) if n <= len(words) else np.zeros(0, np.int64)
        return textkit.windows(words, n)[at], at

    def longest(n: int) -> tuple[int, int] | None:
        (hd, d), (hi, i) = open_runs(doc, used_doc, n), open_runs(item, used_item, n)
        both = np.flatnonzero(np.isin(hd, hi))
        return (int(d[both[0]]), int(i[np.flatnonzero(hi == hd[both[0]])[0]])) if len(both) else None

    out, top = [], min(len(doc), len(item))
    while found := longest(size):
        lo, hi = size, top
        while lo < hi:
            mid = (lo + hi + 1) // 2
            if at := longest(mid):
                lo, found = mid, at
            else:
                hi = mid - 1
        top, (x, y) = lo, found
        equal = same(x, y, lo)
        if equal.all():
            used_doc[x : x + lo] = used_item[y : y + lo] = True
            out.append((x, y, lo))
        else:  # different words of equal hashes: the document's get others
            bad = x + np.flatnonzero(~equal)
            doc[bad] = textkit.mix(doc[bad] + U64(len(out) + 1))
    return out


def tiles(doc: np.ndarray, item: np.ndarray, size: int, same: Same | None = None, most: int | None = None) -> list[tuple[int, int, int]]:
    """Greedy tiling of two word-hash arrays: (doc start, item start, length), longest first, ties to the earlier document
    and item position.  ``same`` says which words of two runs are equal themselves."""
    same = same or (lambda x, y, n: np.ones(n, bool))
    seeds = _listed(doc, item, size, 65_536 + 4 * (len(doc) + len(item)) if most is None else most)
    return _by_length(doc, item, size, same) if seeds is None else _by_diagonals(seeds, doc, item, size, same)


class Block:
    """Items of one block with the table of their seeds, and of the whole runs of items shorter than a seed."""

    def __init__(self, rows: list[tuple[int, str]], seed: int):
        self.ids, self.seed = np.array([r[0] for r in rows], np.int64), seed
        self.w = textkit.Words(pa.array([r[1] for r in rows], pa.large_string()), table=textkit.PLAIN)
        self.words, self.first = self.w.hashes(), self.w.first
        self.tables = {}
        counts = self.w.counts()
        for size in range(1, seed + 1):
            at = textkit.inside(self.first, size)
            row = np.searchsorted(self.first, at, "right") - 1
            keep = counts[row] >= seed if size == seed else counts[row] == size
            at, row = at[keep], row[keep]
            if len(at):
                h = textkit.windows(self.words, size)[at]
                order = np.lexsort((row, h))
                h, row = h[order], row[order]
                one = np.concatenate(([True], (h[1:] != h[:-1]) | (row[1:] != row[:-1])))
                maybe = np.zeros(1 << 20, bool)
                maybe[h >> U64(44)] = True
                self.tables[size] = (h[one], row[one], maybe)

    def item(self, k: int) -> slice:
        return slice(self.first[k], self.first[k + 1])


def _same(a: textkit.Words, at: int, b: textkit.Words, to: int) -> Same:
    """Compares words themselves: those of ``a`` from ``at`` on with those of ``b`` from ``to`` on."""

    def run(x: int, y: int, n: int) -> np.ndarray:
        i, j = np.arange(at + x, at + x + n), np.arange(to + y, to + y + n)
        words = lambda w, k: [w.data[s:e].tobytes() for s, e in zip(w.start[k].tolist(), w.end[k].tolist(), strict=True)]
        return np.array([p == q for p, q in zip(words(a, i), words(b, j), strict=True)], bool)

    return run


def _pairs(w: textkit.Words, words: np.ndarray, table: tuple, size: int, whole: bool) -> np.ndarray:
    """Distinct (row, item, first place in the row) with a common run of ``size`` words, or whose whole row is that run."""
    h, item, maybe = table
    at = textkit.inside(w.first, size)
    if whole:
        at = at[w.counts()[np.searchsorted(w.first, at, "right") - 1] == size]
    seeds = textkit.windows(words, size)[at] if len(at) else np.zeros(0, U64)
    hit = np.flatnonzero(maybe[seeds >> U64(44)])
    at, seeds = at[hit], seeds[hit]
    lo, hi = np.searchsorted(h, seeds, "left"), np.searchsorted(h, seeds, "right")
    some = hi > lo
    at, lo, hi = at[some], lo[some], hi[some]
    row = np.searchsorted(w.first, at, "right") - 1
    # a seed that a row repeats meets its items once
    _, once = np.unique(np.stack((row, lo)), axis=1, return_index=True) if len(at) else (None, np.zeros(0, np.int64))
    row, at, lo, n = row[once], at[once], lo[once], (hi - lo)[once]
    take = np.repeat(lo, n) + np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
    found = np.stack((np.repeat(row, n), item[take], np.repeat(at, n)), axis=1)
    found = found[np.lexsort((found[:, 2], found[:, 1], found[:, 0]))]
    first = np.ones(len(found), bool)
    first[1:] = (found[1:, :2] != found[:-1, :2]).any(axis=1)
    return found[first]


def judge(arr: pa.Array, block: Block, shortest: int) -> list[tuple]:
    """(item, coverage, tiles, words in the item) of the best item of each row, or Nones."""
    w = textkit.Words(arr, table=textkit.PLAIN)
    words = w.hashes()
    best: list[tuple] = [(None, None, None, None)] * len(arr)
    for size, table in block.tables.items():
        for row, k, at in _pairs(w, words, table, size, size < shortest).tolist():
            own = block.item(k)
            n = int(own.stop - own.start)
            if size < block.seed:
                found = [(0, 0, size)] if _same(w, at, block.w, own.start)(0, 0, size).all() else []
            else:
                mine = slice(w.first[row], w.first[row + 1])
                found = tiles(words[mine], block.words[own], size, _same(w, mine.start, block.w, own.start))
            now = (int(block.ids[k]), sum(t[2] for t in found) / n, len(found), n)
            if found and (best[row][0] is None or (-now[1], now[0]) < (-best[row][1], best[row][0])):
                best[row] = now
    return best


def _pass(sent, seed: int, shortest: int, again: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = Block(sent.value, seed)
        types = [pa.int64(), pa.float64(), pa.int32(), pa.int64()]
        names = ["_leak_item", "_leak_coverage", "_leak_tiles", "_leak_words"]
        for batch in batches:
            for b in textkit.pieces(batch, "text"):
                best = judge(b.column(b.schema.get_field_index("text")), block, shortest)
                n = b.num_columns - (4 if again else 0)
                if again:
                    before = zip(*[b.column(n + i).to_pylist() for i in range(4)], strict=True)
                    best = [x if x[0] is not None and (y[0] is None or (-x[1], x[0]) < (-y[1], y[0])) else y for x, y in zip(best, before, strict=True)]
                found = [pa.array(c, t) for c, t in zip(list(zip(*best, strict=True)) or [()] * 4, types, strict=True)]
                yield pa.RecordBatch.from_arrays([b.column(i) for i in range(n)] + found, names=[*b.schema.names[:n], *names])

    return run


def _blocks(benchmark: DataFrame, limit: int) -> Iterator[list[tuple[int, str]]]:
    block, size = [], 0
    for r in benchmark.where("item_id is not null and text is not null").select(F.col("item_id").cast("long"), "text").orderBy("item_id", "text").toLocalIterator():
        if block and size + len(r[1]) > limit:
            yield block
            block, size = [], 0
        block.append((r[0], r[1]))
        size += len(r[1])
    yield block


def find_leaks(docs: DataFrame, benchmark: DataFrame, seed: int = 5, shortest: int = 3, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """All columns of ``docs`` and, for the item with the largest coverage: _leak_item, _leak_coverage (null if no seed is
    shared), _leak_tiles, _leak_words.  Columns of these names are replaced."""
    spark, docs = docs.sparkSession, docs.drop("_leak_item", "_leak_coverage", "_leak_tiles", "_leak_words")
    base = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema) + ", " + FOUND
    last = None
    for block in _blocks(benchmark, block_bytes):
        if last is not None:
            docs = shared.written(docs)
            last.destroy()
        again, last = last is not None, spark.sparkContext.broadcast(block)
        docs = docs.mapInArrow(_pass(last, seed, shortest, again), base)
    return docs


def decontaminate(docs: DataFrame, benchmark: DataFrame, threshold: float = 0.5, **options) -> DataFrame:
    """Rows of ``docs`` without leaked items."""
    found = find_leaks(docs, benchmark, **options)
    return found.where(F.coalesce(F.col("_leak_coverage"), F.lit(0.0)) < threshold).select(*docs.columns)
