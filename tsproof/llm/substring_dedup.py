"""Exact removal of repeated word windows, found through difference-cover anchors.

A set D of residues modulo v is a difference cover if every residue is a difference of two members.  Anchors are
windows of ``width - v + 1`` words that start at positions p with ``p mod v`` in D.  For any two equal windows of
``width`` words, at i and j, some shift below v puts both i + shift and j + shift on cover positions, so the pair
shares an aligned anchor.  Three steps follow:

1. anchors go, packed by hash bucket, to the tasks that own their bucket; repeated ones return, packed by document
   range, to their documents;
2. each repeated anchor extends to the full windows around it, which are hashed with 96 bits and dealt by bucket;
   the earliest (doc_id, start) of each window stays, every other occurrence is a repeat;
3. words covered by repeats are removed, and the rest is joined by one space.

Each task combines its own rows before it sends them (one row per distinct hash and slice; the others are already
known to be repeats), so a passage shared by a third of all documents sends a few rows per task and never meets in
one group.  Nothing is capped.  Texts are shuffled once: both joins use the same exchange.

Defined cases: null or blank texts have no words; rows with a null doc_id are left out; of rows that share a doc_id
the one with the smallest text counts; fewer words than ``width`` are kept whole; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tsproof.llm import shared, textkit

#: Smallest difference covers by modulus (fixed values).
COVERS = {1: (0,), 3: (0, 1), 7: (0, 1, 3), 13: (0, 1, 3, 9), 21: (0, 1, 4, 14, 16)}
SCHEMA = "doc_id long, n_words long, n_removed long, kept_sha256 string"


def planes(a: np.ndarray) -> bytes:
    """Bytes of equal weight together: sorted ids then hold long runs of equal bytes, which the shuffle compresses."""
    return np.ascontiguousarray(a.view(np.uint8).reshape(len(a), a.itemsize).T).tobytes()


def unplanes(blobs: list[bytes], dtype: type) -> np.ndarray:
    k = np.dtype(dtype).itemsize
    parts = [np.ascontiguousarray(np.frombuffer(b, np.uint8).reshape(k, -1).T).reshape(-1) for b in blobs]
    return np.concatenate(parts).view(dtype) if parts else np.zeros(0, dtype)


PACKED = "bucket int, known boolean, h1 binary, h2 binary, doc binary, pos binary"


class Packer:
    """Rows (hash, document, position) of one slice, combined and packed by bucket."""

    def __init__(self, buckets: int):
        self.buckets, self.rows = buckets, []

    def add(self, h1: np.ndarray, h2: np.ndarray, doc: np.ndarray, pos: np.ndarray, earliest: bool) -> None:
        order = np.lexsort((pos, doc, h2, h1))
        h1, h2, doc, pos = h1[order], h2[order], doc[order], pos[order]
        head = np.ones(len(h1), bool)
        head[1:] = (h1[1:] != h1[:-1]) | (h2[1:] != h2[:-1])
        known = ~head
        if not earliest:  # every occurrence of a repeated anchor is wanted, so its first is known as well
            known[:-1] |= ~head[1:]
        self._known(doc[known], pos[known])
        h1, h2, doc, pos = h1[head], h2[head], doc[head], pos[head]
        bucket = (h1 % np.uint64(self.buckets)).astype(np.int64)
        order = np.lexsort((pos, doc, bucket))
        bucket = bucket[order]
        cuts = np.flatnonzero(np.diff(bucket)) + 1
        for part in np.split(order, cuts) if len(order) else []:
            self.rows.append((int(h1[part[0]] % np.uint64(self.buckets)), False, planes(h1[part]), planes(h2[part]), planes(doc[part]), planes(pos[part])))

    def _known(self, doc: np.ndarray, pos: np.ndarray) -> None:
        order = np.lexsort((pos, doc))
        doc, pos = doc[order], pos[order]
        for i in range(0, len(doc), 4096):
            at = int(textkit.mix(doc[i : i + 1].view(np.uint64))[0] % np.uint64(self.buckets))
            self.rows.append((at, True, b"", b"", planes(doc[i : i + 4096]), planes(pos[i : i + 4096])))

    def flush(self) -> pa.RecordBatch:
        cols = list(zip(*self.rows, strict=True)) or [()] * 6
        self.rows = []
        types = [pa.int32(), pa.bool_(), pa.binary(), pa.binary(), pa.binary(), pa.binary()]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=["bucket", "known", "h1", "h2", "doc", "pos"])


def by_document(doc: np.ndarray, pos: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Positions packed per document."""
    if not len(doc):
        return
    order = np.lexsort((pos, doc))
    doc, pos = doc[order], pos[order].astype(np.uint32)
    cuts = np.concatenate(([0], np.flatnonzero(np.diff(doc)) + 1, [len(doc)]))
    packed = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(cuts) - 1, [None, pa.py_buffer((cuts * 4).astype(np.int64)), pa.py_buffer(np.ascontiguousarray(pos))])
    yield pa.RecordBatch.from_arrays([pa.array(doc[cuts[:-1]]), packed.cast(pa.binary())], names=["doc_id", "at"])


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[list[list]]:
    """Columns of each run of rows with equal first column (rows arrive sorted by it)."""
    key, cols = None, []
    for b in batches:
        rows = [b.column(i).to_pylist() for i in range(b.num_columns)]
        for row in zip(*rows, strict=True):
            if cols and row[0] != key:
                yield cols
                cols = []
            key = row[0]
            cols = cols or [[] for _ in row]
            for c, x in zip(cols, row, strict=True):
                c.append(x)
    if cols:
        yield cols


def _gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The owner of a range of documents: one row for each document."""
    for _, doc, pos in _runs(batches):
        yield from by_document(unplanes(doc, np.int64), unplanes(pos, np.uint32))


#: Positions gathered over buckets before they are packed and sent.
FLUSH = 1 << 20


def _settle(earliest: bool, owners: int):
    """The owner of some buckets, one after the other: which of their rows are repeats, packed for the owners of their
    documents."""

    def repeats(cols: list[list]) -> tuple[np.ndarray, np.ndarray]:
        _, known, *parts = cols
        fresh = [[x for x, k in zip(c, known, strict=True) if not k] for c in parts]
        sure = [[x for x, k in zip(c, known, strict=True) if k] for c in parts[2:]]
        h1, h2, doc, pos = (unplanes(p, t) for p, t in zip(fresh, (np.uint64, np.uint32, np.int64, np.uint32), strict=True))
        order = np.lexsort((pos, doc, h2, h1))
        same = (h1[order][1:] == h1[order][:-1]) & (h2[order][1:] == h2[order][:-1])
        repeat = np.zeros(len(order), bool)
        repeat[1:] = same
        if not earliest:
            repeat[:-1] |= same
        picked = order[repeat]
        return np.concatenate((doc[picked], unplanes(sure[0], np.int64))), np.concatenate((pos[picked], unplanes(sure[1], np.uint32)))

    def packed(found: list[tuple[np.ndarray, np.ndarray]]) -> pa.RecordBatch:
        doc, pos = (np.concatenate([x[i] for x in found]) for i in (0, 1))
        owner = (textkit.mix(doc.view(np.uint64)) % np.uint64(owners)).astype(np.int64)
        order = np.lexsort((pos, doc, owner))
        rows = [(int(owner[x[0]]), planes(doc[x]), planes(pos[x])) for x in np.split(order, np.flatnonzero(np.diff(owner[order])) + 1) if len(x)]
        types = (pa.int32(), pa.binary(), pa.binary())
        cols = list(zip(*rows, strict=True)) or [()] * 3
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=["owner", "doc", "pos"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found, held = [], 0
        for cols in _runs(batches):
            found.append(repeats(cols))
            held += len(found[-1][0])
            if held >= FLUSH:
                yield packed(found)
                found, held = [], 0
        if found:
            yield packed(found)

    return run


def _anchors(width: int, modulus: int, buckets: int):
    cover = np.zeros(modulus, bool)
    cover[list(COVERS[modulus])] = True
    size = width - modulus + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer = Packer(buckets)
        for batch in batches:
            for b in textkit.pieces(batch, "text"):
                w = textkit.Words(b.column(1))
                at = textkit.inside(w.first, size)
                row = np.repeat(np.arange(b.num_rows), w.counts())[at] if len(at) else at
                pos = at - w.first[row]
                on = cover[pos % modulus]
                at, row, pos = at[on], row[on], pos[on]
                h = textkit.windows(w.hashes(), size)[at]
                packer.add(h, np.zeros(len(h), np.uint32), b.column(0).to_numpy()[row], pos.astype(np.uint32), False)
                yield packer.flush()

    return run


def _positions(column: pa.Array, w: textkit.Words) -> tuple[np.ndarray, np.ndarray]:
    """Row number and global word index of the packed positions."""
    raw, offsets = textkit.buffers(column)
    pos = np.frombuffer(raw.tobytes(), np.uint32).astype(np.int64)
    rows = np.repeat(np.arange(len(column)), np.diff(offsets) // 4)
    return rows, pos + w.first[rows]


def _extend(width: int, modulus: int, buckets: int):
    reach = modulus - 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer = Packer(buckets)
        for batch in batches:
            for b in textkit.pieces(batch, "text"):
                w = textkit.Words(b.column(1))
                rows, anchors = _positions(b.column(2), w)
                spread = np.zeros(int(w.first[-1]) + 1, np.int32)
                np.add.at(spread, np.maximum(anchors - reach, w.first[rows]), 1)
                np.add.at(spread, anchors + 1, -1)
                at = textkit.inside(w.first, width)
                at = at[np.cumsum(spread)[at] > 0]
                row = np.searchsorted(w.first, at, "right") - 1
                words = w.hashes()
                h1 = textkit.windows(words, width)[at]
                h2 = (textkit.windows(words, width, 1)[at] >> np.uint64(32)).astype(np.uint32)
                packer.add(h1, h2, b.column(0).to_numpy()[row], (at - w.first[row]).astype(np.uint32), True)
                yield packer.flush()

    return run


def removed_words(w: textkit.Words, starts: np.ndarray, width: int) -> np.ndarray:
    spread = np.zeros(int(w.first[-1]) + 1, np.int32)
    np.add.at(spread, starts, 1)
    np.add.at(spread, starts + width, -1)
    return np.cumsum(spread)[:-1] > 0


def kept_texts(w: textkit.Words, removed: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Kept words of each row joined by one space: bytes and offsets."""
    n = len(w.data)
    keep = ~removed
    row = np.repeat(np.arange(len(w.offsets) - 1), w.counts())
    start, end, row = w.start[keep], w.end[keep], row[keep]
    follows = np.zeros(len(row), bool)
    follows[:-1] = row[1:] == row[:-1]
    spread = np.zeros(n + 1, np.int8)
    spread[start] += 1
    np.add.at(spread, end, -1)
    mask = np.cumsum(spread, dtype=np.int8)[:-1].astype(bool)
    gaps = end[follows]  # a blank stands right after a word that another word follows
    data = w.data.copy()
    data[gaps] = 0x20
    mask[gaps] = True
    sizes = np.concatenate(([0], np.cumsum(mask)))
    return data[mask], sizes[w.offsets]


def _finish(width: int, text: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in textkit.pieces(batch, "text"):
                w = textkit.Words(b.column(1))
                gone = removed_words(w, _positions(b.column(2), w)[1], width)
                data, offsets = kept_texts(w, gone)
                raw = data.tobytes()
                kept = [raw[x:y] for x, y in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
                lost = np.concatenate(([0], np.cumsum(gone)))[w.first]
                cols = [b.column(0), pa.array(w.counts()), pa.array(np.diff(lost)), pa.array([hashlib.sha256(x).hexdigest() for x in kept])]
                names = ["doc_id", "n_words", "n_removed", "kept_sha256"]
                if text:
                    cols, names = [*cols, pa.array([x.decode() for x in kept])], [*names, "kept_text"]
                yield pa.RecordBatch.from_arrays(cols, names=names)

    return run


def substring_dedup(docs: DataFrame, width: int = 20, modulus: int = 13, with_text: bool = False) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 (and kept_text): each word covered by a window of ``width`` words that
    also starts earlier is removed.  ``modulus`` (1, 3, 7, 13 or 21, at most ``width``) trades anchors for reach."""
    spark = docs.sparkSession
    n = shared.partitions(spark)
    buckets = max(1024, 4 * n)
    docs = shared.one_row_per_id(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), "doc_id", "text")

    def settled(rows: DataFrame, earliest: bool) -> DataFrame:
        # sorted, so that a task holds one bucket (or one owner's range) at a time
        packed = rows.repartition(n, "bucket").sortWithinPartitions("bucket").mapInArrow(_settle(earliest, max(512, 4 * n)), "owner int, doc binary, pos binary")
        return packed.repartition(n, "owner").sortWithinPartitions("owner").mapInArrow(_gather, "doc_id long, at binary")

    repeated = settled(docs.mapInArrow(_anchors(width, modulus, buckets), PACKED), False)
    around = docs.join(repeated.hint("merge"), "doc_id").select("doc_id", "text", "at")
    repeats = settled(around.mapInArrow(_extend(width, modulus, buckets), PACKED), True)
    full = docs.join(repeats.hint("merge"), "doc_id", "left").select("doc_id", "text", "at")
    return full.mapInArrow(_finish(width, with_text), SCHEMA + (", kept_text string" if with_text else ""))
