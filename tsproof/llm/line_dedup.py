"""Line deduplication by pairwise alignment.

Seeds are hashes of runs of consecutive non-blank lines (stripped): from each line on, and up to each line, the shortest
run of at least ``chars`` characters (blanks between words counted once), which is one line if it is long enough.  A
seed that two to ``rare`` documents hold is rare; it links each later document with the first (smallest doc_id) that
holds it.  Each linked pair is aligned with patience diff: lines unique on both sides and equal are anchors, their
longest increasing chain splits the pair, and matches grow from the anchors; where no unique line is left the common
prefix and suffix match.  Aligned common blocks of at least ``chars`` characters are deleted from the later document, and
so are rare seeds of the pair that alignment leaves because a passage repeats or comes in another order.

Frequent seeds need no partner: a seed is a common block itself, so its lines go from every document but the first that
holds it.  They are settled by hash alone, and hot lines neither make pairs nor move texts.

Together: a line goes if, and only if, it lies in a run of consecutive non-blank lines of at least ``chars`` characters
that some earlier document holds.  (Each line of such a block lies in a seed of the block, and every seed is settled
with its first holder.)  So the choice of ``rare`` and of partners changes the work, never the result.
All documents are judged on the input, so the result doesn't depend on the order of work.

Defined cases: null texts stay null, and are no one's partner; a text whose lines all go becomes empty; rows with a null
doc_id are kept unchanged; of rows that share a doc_id the smallest text is aligned, and its deletions
apply to the rows of that id with the same text; other columns pass
through, but for ones named as the two counts that the result adds.
"""

from __future__ import annotations

from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tsproof.llm import shared, textkit


def line_hashes(arr: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash of each line of each row (stripped; 0 if blank), its characters with single blanks between words, and row
    offsets into them."""
    data, offsets = textkit.buffers(arr)
    n = len(arr)
    # words of a line decide its hash, so blanks at its ends or in repetition don't
    w = textkit.Words(arr)
    cut = np.flatnonzero(data == 10)
    row_of_cut = np.searchsorted(offsets, cut, "right") - 1
    lines_before = np.searchsorted(cut, w.start) + (np.searchsorted(offsets, w.start, "right") - 1)
    total = len(cut) + n
    place = textkit.mix(w.hashes())
    rank = np.zeros(len(place), np.int64)
    sizes = np.zeros(total, np.int64)
    if len(place):
        new = np.concatenate(([True], lines_before[1:] != lines_before[:-1]))
        starts = np.flatnonzero(new)
        rank = np.arange(len(place)) - np.repeat(starts, np.diff([*starts, len(place)]))
        mixed = textkit.mix(place + rank.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
        sums = np.add.reduceat(mixed, starts)
        out = np.zeros(total, np.uint64)
        out[lines_before[starts]] = textkit.mix(sums) | np.uint64(1)
        letters = np.concatenate(([0], np.cumsum((data & 0xC0) != 0x80)))
        sizes[lines_before[starts]] = np.add.reduceat(letters[w.end] - letters[w.start] + 1, starts) - 1
    else:
        out = np.zeros(total, np.uint64)
    first = np.concatenate(([0], np.cumsum(1 + np.bincount(row_of_cut, minlength=n)))) if n else np.zeros(1, np.int64)
    return out, sizes, first


def _lists(values: np.ndarray, first: np.ndarray, kind: pa.DataType) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(first, pa.int32()), pa.array(values, kind))


def _lines(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Per document: hash, characters (single blanks) and place of its non-blank lines."""
    for batch in batches:
        for b in textkit.pieces(batch, "text"):
            h, words, first = line_hashes(b.column(1))
            solid = np.flatnonzero(h)
            before = np.concatenate(([0], np.cumsum(h != 0)))[first]
            place = np.arange(len(h)) - np.repeat(first[:-1], np.diff(first))
            lists = [_lists(h[solid].view(np.int64), before, pa.int64()), *[_lists(x[solid], before, pa.int32()) for x in (words, place)]]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), *lists], names=["doc_id", "mark", "h", "words", "place"])


def _flat(arr: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Values of a list column and row offsets into them."""
    return arr.flatten().to_numpy(zero_copy_only=False), np.concatenate(([0], np.cumsum(arr.value_lengths().to_numpy(zero_copy_only=False)))).astype(np.int64)


def _slices(batch: pa.RecordBatch, column: str, limit: int = 1 << 15) -> Iterator[pa.RecordBatch]:
    """Slices of a batch whose lists hold about ``limit`` lines (one row at least)."""
    if not batch.num_rows:
        return
    n = batch.column(batch.schema.get_field_index(column)).value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    cuts = np.flatnonzero(np.diff((np.cumsum(n) - n) // limit)) + 1
    for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), batch.num_rows], strict=True):
        yield batch.slice(a, b - a)


def _runs(words: np.ndarray, first: np.ndarray, chars: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row, start and end of the runs of lines that are seeds, each once."""
    n = len(words)
    total = np.concatenate(([0], np.cumsum(words, dtype=np.int64)))
    lo, hi = (np.repeat(x, np.diff(first)) for x in (first[:-1], first[1:]))
    line = np.arange(n)
    end = np.searchsorted(total, total[:-1] + chars, "left")
    start = np.searchsorted(total, total[1:] - chars, "right") - 1
    on, back = end <= hi, start >= lo
    back &= ~(on[np.maximum(start, 0)] & (end[np.maximum(start, 0)] == line + 1))  # the same run from either side
    starts, ends = np.concatenate((line[on], start[back])), np.concatenate((end[on], line[back] + 1))
    return np.searchsorted(first, starts, "right") - 1, starts, ends


def _seeds(chars: int, spans: bool):
    """doc_id, seed of each document's distinct seeds; with ``spans`` all of them, and their lines (from, to)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in _slices(batch, "h"):
                (h, first), (words, _) = _flat(b.column(1)), _flat(b.column(2))
                row, start, end = _runs(words, first, chars)
                seed = textkit.spans(h.view(np.uint64), start, end).view(np.int64)
                ids = b.column(0).to_numpy()
                if spans:
                    lines = [pa.array((x - first[row]).astype(np.int32)) for x in (start, end)]
                    yield pa.RecordBatch.from_arrays([pa.array(ids[row]), pa.array(seed), *lines], names=["doc_id", "seed", "start", "stop"])
                    continue
                order = np.lexsort((seed, row))
                row, seed = row[order], seed[order]
                one = np.ones(len(row), bool)
                one[1:] = (row[1:] != row[:-1]) | (seed[1:] != seed[:-1])
                yield pa.RecordBatch.from_arrays([pa.array(ids[row[one]]), pa.array(seed[one])], names=["doc_id", "seed"])

    return run


def patience(a: list[int], b: list[int]) -> list[tuple[int, int]]:
    """Matched index pairs of two sequences, increasing on both sides."""
    out, todo = [], [(0, len(a), 0, len(b))]
    while todo:
        alo, ahi, blo, bhi = todo.pop()
        while alo < ahi and blo < bhi and a[alo] == b[blo]:
            out.append((alo, blo))
            alo, blo = alo + 1, blo + 1
        while alo < ahi and blo < bhi and a[ahi - 1] == b[bhi - 1]:
            ahi, bhi = ahi - 1, bhi - 1
            out.append((ahi, bhi))
        if alo >= ahi or blo >= bhi:
            continue
        ca, cb = Counter(a[alo:ahi]), Counter(b[blo:bhi])
        where = {x: i for i, x in enumerate(a[alo:ahi], alo) if ca[x] == 1 and cb.get(x) == 1}
        common = [(where[x], j) for j, x in enumerate(b[blo:bhi], blo) if x in where and cb[x] == 1]
        tails: list[int] = []
        back: list[int] = []
        ends: list[int] = []
        for k, (i, _) in enumerate(common):
            p = bisect_left(tails, i)
            back.append(ends[p - 1] if p else -1)
            if p == len(tails):
                tails.append(i)
                ends.append(k)
            else:
                tails[p], ends[p] = i, k
        chain, k = [], ends[-1] if ends else -1
        while k >= 0:
            chain.append(common[k])
            k = back[k]
        if not chain:
            continue
        pa_, pb = alo, blo
        for i, j in reversed(chain):
            todo.append((pa_, i, pb, j))
            out.append((i, j))
            pa_, pb = i + 1, j + 1
        todo.append((pa_, ahi, pb, bhi))
    return sorted(out)


def common_blocks(a: list[int], b: list[int], words: list[int], chars: int) -> list[int]:
    """Lines of b inside aligned common blocks; ``a`` and ``b`` are hashes of non-blank lines, ``words`` characters of b's."""
    out, run = [], []
    for pair in [*patience(a, b), None]:
        if run and (pair is None or pair[0] != run[-1][0] + 1 or pair[1] != run[-1][1] + 1):
            lines = [j for _, j in run]
            if sum(words[j] for j in lines) >= chars:
                out += lines
            run = []
        if pair:
            run.append(pair)
    return out


def _align(chars: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in _slices(batch, "h"):
                (ha, fa), (wa, _), (hb, fb), (wb, _), (place, _) = (_flat(b.column(x)) for x in ("h_a", "words_a", "h", "words", "place"))
                ra, ia, ja = _runs(wa, fa, chars)
                rb, ib, jb = _runs(wb, fb, chars)
                # a seed of the pair's other side is the same hash in the same row
                key_a, key_b = (textkit.spans(h.view(np.uint64), i, j) ^ textkit.mix(r + 1) for h, i, j, r in ((ha, ia, ja, ra), (hb, ib, jb, rb)))
                hit = np.isin(key_b, key_a)
                edge = np.zeros(len(hb) + 1, np.int64)
                np.add.at(edge, ib[hit], 1)
                np.add.at(edge, jb[hit], -1)
                goes = np.cumsum(edge)[:-1] > 0
                for k in range(b.num_rows):
                    mine = slice(fb[k], fb[k + 1])
                    cut = common_blocks(ha[fa[k] : fa[k + 1]].tolist(), hb[mine].tolist(), wb[mine].tolist(), chars)
                    goes[fb[k] + np.array(cut, np.int64)] = True
                n = np.concatenate(([0], np.cumsum(goes)))[fb]
                some = pa.array(np.diff(n) > 0)
                out = pa.RecordBatch.from_arrays([b.column("b"), b.column("mark"), _lists(place[goes], n, pa.int32())], names=["doc_id", "mark", "gone"])
                yield out.filter(some)

    return run


def line_dedup(docs: DataFrame, chars: int = 60, rare: int = 8) -> DataFrame:
    """All columns of ``docs`` with the shortened ``text``, and _lines (in the input) and _lines_removed.  ``rare``: the
    most documents that may hold a seed which is aligned (0: none is, all are settled by hash)."""
    docs = docs.drop("_lines", "_lines_removed")
    own = shared.one_row_per_id(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").where("text is not null"), "doc_id", "text")
    # alignment needs hashes and sizes of lines only, so no text is shuffled for it
    lines = shared.written(own.withColumn("mark", F.xxhash64("text")).mapInArrow(_lines, "doc_id long, mark long, h array<long>, words array<int>, place array<int>"))
    hashes = lines.select("doc_id", "h", "words")
    counted = hashes.mapInArrow(_seeds(chars, False), "doc_id long, seed long").groupBy("seed").agg(F.min("doc_id").alias("a"), F.count("*").alias("n"))
    # written, so that the join reads plain shuffles and a hot seed's rows can be split
    counted = shared.written(counted.where("n > 1").select("seed", "a", (F.col("n") <= rare).alias("rare")))
    held = hashes.mapInArrow(_seeds(chars, True), "doc_id long, seed long, start int, stop int").join(counted, "seed").where("doc_id > a")
    # one row per document, with at most one partner and one span per line of it
    found = held.groupBy("doc_id").agg(F.collect_set(F.when(F.col("rare"), F.col("a"))).alias("partners"), F.collect_list(F.when(~F.col("rare"), F.struct("start", "stop"))).alias("spans"))
    found = shared.written(found)
    right = found.where("size(partners) > 0").join(lines, "doc_id").select(F.col("doc_id").alias("b"), F.explode("partners").alias("a"), "mark", "h", "words", "place")
    both = right.join(lines.select(F.col("doc_id").alias("a"), F.col("h").alias("h_a"), F.col("words").alias("words_a")).hint("merge"), "a")
    aligned = both.select("b", "mark", "h", "words", "place", "h_a", "words_a").mapInArrow(_align(chars), "doc_id long, mark long, gone array<int>")
    inside = F.transform(F.col("spans"), lambda x: F.slice(F.col("place"), x["start"] + 1, x["stop"] - x["start"]))
    settled = found.where("size(spans) > 0").join(lines.select("doc_id", "mark", "place"), "doc_id").select("doc_id", "mark", F.array_distinct(F.flatten(inside)).alias("gone"))
    gone = aligned.union(settled).groupBy(F.col("doc_id").alias("_id"), F.col("mark").alias("_mark")).agg(F.array_distinct(F.flatten(F.collect_list("gone"))).alias("_gone"))
    out = docs.join(gone.hint("merge"), (docs["doc_id"].cast("long") == gone["_id"]) & (F.xxhash64(docs["text"]) == gone["_mark"]), "left")
    split, cuts = F.split(docs["text"], "\n", -1), gone["_gone"]
    kept = F.array_join(F.filter(F.transform(split, lambda x, i: F.when(~F.array_contains(cuts, i), x)), lambda x: x.isNotNull()), "\n")
    text = F.when(cuts.isNull(), docs["text"]).otherwise(kept)
    counts = [F.greatest(F.coalesce(F.size(c), F.lit(0)), F.lit(0)).cast("long") for c in (split, cuts)]
    return out.select(*[text.alias(c) if c == "text" else docs[c] for c in docs.columns], counts[0].alias("_lines"), counts[1].alias("_lines_removed"))
