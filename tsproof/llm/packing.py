"""Best-fit packing of documents into sequences of several permitted lengths.

Texts longer than the largest length are cut into pieces of that length.  Documents are dealt into shards of about
``shard_rows`` rows by a hash of the id, and each shard is packed on its own, pieces in decreasing length.  The sizes are
chosen jointly, by comparing whole plans of a shard under the cost of its final bins:

* best fit with a set of sizes that may be opened, for every set that holds the largest: a piece goes to the open bin with
  the smallest room that fits it; where none fits, the smallest size of the set that holds it is opened;
* fill: every bin is opened for the longest piece left, in the size that has the least cost per token once it is filled
  with the longest pieces still unplaced that fit.

In each plan every bin shrinks at the end to the smallest permitted length that holds its contents, and the cheapest plan
is taken.  Cost of a bin of c tokens: ``overhead + c + attention * c**2``.  Only ids and lengths are shuffled, and texts
are read once.

Defined cases: null and empty texts have 0 tokens, one row, and no bin; null ids are packed as rows of their own;
repeated rows are packed each; shards of an empty table give no rows.
"""

from __future__ import annotations

import math
from bisect import bisect_right
from collections.abc import Callable, Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tsproof.llm import shared, textkit

CAPACITIES = (512, 1024, 2048, 4096)
SCHEMA = "doc_id long, piece int, start long, n_tokens long, bin_id long, capacity int, bin_offset int"


def cost(capacity: int, overhead: float = 64.0, attention: float = 1e-5) -> float:
    return overhead + capacity + attention * capacity**2


Price = Callable[[int], float]
Packed = tuple[np.ndarray, np.ndarray, np.ndarray]


def _shrunk(used: list[int], capacities: tuple[int, ...]) -> np.ndarray:
    return np.array([next(c for c in capacities if c >= u) for u in used], np.int64)


def place(lengths: np.ndarray, capacities: tuple[int, ...], opened: tuple[int, ...]) -> Packed:
    """Best fit in decreasing length; a new bin has the smallest size of ``opened`` that holds its piece."""
    bins, offsets = np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64)
    used: list[int] = []
    stacks: dict[int, list[int]] = {}
    rooms = 0  # bit r is set if an open bin has room r
    for k in np.argsort(-lengths, kind="stable").tolist():
        n = int(lengths[k])
        fit = rooms >> n
        if fit:
            room = n + (fit & -fit).bit_length() - 1
            b = stacks[room].pop()
            if not stacks[room]:
                rooms &= ~(1 << room)
        else:
            b, room = len(used), next(c for c in opened if c >= n)
            used.append(0)
        bins[k], offsets[k] = b, used[b]
        used[b] += n
        room -= n
        if room:
            stacks.setdefault(room, []).append(b)
            rooms |= 1 << room
    return bins, offsets, _shrunk(used, capacities)


def fill(lengths: np.ndarray, capacities: tuple[int, ...], price: Price) -> Packed:
    """Bins one by one: the longest piece left, with the longest others that fit, in the size that is then cheapest a token."""
    left: dict[int, list[int]] = {}
    for k in range(len(lengths) - 1, -1, -1):
        left.setdefault(int(lengths[k]), []).append(k)
    kinds = sorted(left)  # lengths with a piece left
    bins, offsets = np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64)
    used: list[int] = []

    def contents(size: int) -> list[int]:
        taken, room, at = [], size, len(kinds) - 1
        while at >= 0:
            some = min(len(left[kinds[at]]), room // kinds[at])
            taken += [kinds[at]] * some
            room -= some * kinds[at]
            at = min(at, bisect_right(kinds, room)) - 1
        return taken

    while kinds:
        tried = []
        for size in capacities:
            if size >= kinds[-1]:
                taken = contents(size)
                load = sum(taken)
                tried.append((price(next(c for c in capacities if c >= load)) / load, size, taken))
        at = 0
        for n in min(tried)[2]:
            k = left[n].pop()
            bins[k], offsets[k], at = len(used), at, at + n
            if not left[n]:
                del left[n]
                kinds.pop(bisect_right(kinds, n) - 1)
        used.append(at)
    return bins, offsets, _shrunk(used, capacities)


def least_per_token(capacities: tuple[int, ...], price: Price) -> tuple[int, ...]:
    """The sizes that best fit opens if each piece takes the size of least cost per token that holds it."""
    return tuple(sorted({min((x for x in capacities if x >= c), key=lambda x: (price(x) / x, x)) for c in capacities}))


def pack(lengths: np.ndarray, capacities: tuple[int, ...] = CAPACITIES, price: Price = cost) -> Packed:
    """(bin, offset) of each piece, in the given order, and the capacity of each bin, of the cheapest plan.  Lengths are in
    1..max capacity."""
    capacities = tuple(sorted(capacities))
    small, most = capacities[:-1], capacities[-1:]
    sets = [least_per_token(capacities, price), *[(*some, *most) for k in range(len(small) + 1) for some in combinations(small, k)]]
    plans = [place(lengths, capacities, s) for s in dict.fromkeys(sets)] + [fill(lengths, capacities, price)]
    return min(plans, key=lambda p: sum(price(int(c)) * int(n) for c, n in zip(*np.unique(p[2], return_counts=True), strict=True)))


def _measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for b in textkit.pieces(batch, "text"):
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(textkit.Words(b.column(1)).counts())], names=["doc_id", "n_tokens"])


def word_lengths(docs: DataFrame) -> DataFrame:
    """doc_id, n_tokens: words of the whole text."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_measure, "doc_id long, n_tokens long")


def _packer(capacities: tuple[int, ...]):
    most = max(capacities)

    def run(key: tuple, group: pa.Table) -> pa.Table:
        group = group.sort_by([("n_tokens", "descending"), ("doc_id", "ascending")])
        total = group.column("n_tokens").to_numpy()
        pieces = np.maximum(-(-total // most), 1)
        row = np.repeat(np.arange(len(total)), pieces)
        piece = np.arange(len(row)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        length = np.minimum(total[row] - piece * most, most)
        some = length > 0
        bins, offsets, caps = pack(length[some], capacities)
        out_bin, out_cap, out_off = (np.zeros(len(row), np.int64) for _ in range(3))
        out_bin[some], out_off[some] = bins, offsets
        out_cap[some] = caps[bins] if len(caps) else 0
        hide = ~some
        return pa.table({
            "doc_id": group.column("doc_id").combine_chunks().take(pa.array(row)), "piece": pa.array(piece, pa.int32()), "start": pa.array(piece * most), "n_tokens": pa.array(length),
            "bin_id": pa.array((int(key[0].as_py()) << 32) + out_bin, pa.int64(), mask=hide), "capacity": pa.array(out_cap, pa.int32(), mask=hide), "bin_offset": pa.array(out_off, pa.int32(), mask=hide),
        })

    return run


def best_fit(lengths: DataFrame, capacities: tuple[int, ...] = CAPACITIES, shard_rows: int = 5000) -> DataFrame:
    """doc_id, piece, start, n_tokens, bin_id, capacity, bin_offset for rows (doc_id, n_tokens)."""
    lengths = shared.written(lengths)  # counted and dealt without reading the texts again
    shards = max(1, math.ceil(lengths.count() / shard_rows))
    # rows without an id are spread over all shards
    shard = F.pmod(F.xxhash64(F.coalesce(F.col("doc_id"), F.monotonically_increasing_id())), F.lit(shards))
    dealt = lengths.select(F.col("doc_id").cast("long").alias("doc_id"), F.greatest(F.coalesce("n_tokens", F.lit(0)), F.lit(0)).cast("long").alias("n_tokens"), shard.alias("shard"))
    return dealt.groupBy("shard").applyInArrow(_packer(tuple(capacities)), SCHEMA)
