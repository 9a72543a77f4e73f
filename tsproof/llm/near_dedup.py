"""Near-duplicate groups: fast similarity sketches, banding, exact verification, connected components.

Sketch: ``coords`` bins filled in rounds.  In each of the first ``coords`` rounds every shingle is thrown into one
hashed bin with a value that grows with the round; in the next ``coords`` rounds round i puts every shingle into bin i.
A document stops as soon as all its bins are full, so every coordinate fills, small sets included, and the time is near
linear in the set.  Two sketches agree in a coordinate with probability equal to the Jaccard similarity.

Links are found in two passes and each is confirmed on the full shingle sets:

* equal sets are one class (digest of the whole set); only the smallest id of a class goes on;
* pass 1: within each band bucket every member is compared with the smallest member.  A bucket of near copies then
  falls into one component with one comparison per member;
* pass 2: a bucket that still holds more than one component is cut into blocks of bounded members and shingles, those
  of the smallest member's component apart from the others, and every pair of blocks that can hold a new link is a group
  of its own (comparing inside a component would change nothing, so blocks of the first kind never meet each other).
  In a group, members are compared, on full sets, with those of other components whose sizes and sketches allow the
  similarity, most typical members first, and only links that join components come out.

With 128 coordinates in bands of 4 a pair at similarity 0.8 misses all bands with probability 5e-8; the sketch filter of
pass 2 (0.6) stands 5.6 standard deviations below 0.8.  No pairs inside a group are listed, nothing is capped.

Defined cases: texts without words (null, empty, blank) have an empty set, linked with nothing; fewer words than a
shingle form one shingle; null doc_ids are left out; of rows that share a doc_id the smallest text counts.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tsproof.llm import shared, textkit
from tsproof.llm.components import components

U64 = np.uint64
ROWS = 4000  # rows a slice holds at most, so that the row number fits above a 52-bit shingle
AGREE = 0.6
#: A block of a bucket holds about so many members and shingles at most; groups of pass 2 are pairs of blocks.
MEMBERS, SHINGLES = 256, 1 << 19
SALTS = 32


def shingle_sets(arr: pa.Array, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct 52-bit shingles of each row, concatenated, and the row offsets."""
    w = textkit.Words(arr, lower=True)
    words = w.hashes()
    at = textkit.inside(w.first, size)
    row = np.searchsorted(w.first, at, "right") - 1
    h = textkit.windows(words, size)[at]
    counts = w.counts()
    for k in range(1, size):  # shorter texts: the whole sequence is the shingle
        short = np.flatnonzero(counts == k)
        if len(short):
            h = np.concatenate((h, textkit.windows(words, k, 1)[w.first[short]]))
            row = np.concatenate((row, short))
    key = np.sort((row.astype(U64) << U64(52)) | (h >> U64(12)))
    if len(key):
        key = key[np.concatenate(([True], key[1:] != key[:-1]))]
    row = (key >> U64(52)).astype(np.int64)
    return key & U64((1 << 52) - 1), np.searchsorted(row, np.arange(len(arr) + 1))


def sketch(items: np.ndarray, offsets: np.ndarray, coords: int) -> np.ndarray:
    """(rows, coords) 64-bit coordinates; rows without items keep the largest value."""
    n = len(offsets) - 1
    full = np.full(n * coords, np.iinfo(np.uint64).max, dtype=U64)
    row = np.repeat(np.arange(n), np.diff(offsets))
    base = textkit.mix(items)
    salts = textkit.stream_of(11, 2 * coords)
    for i in range(2 * coords):
        if not len(row):
            break
        h = textkit.mix(base ^ salts[i])
        where = ((h >> U64(32)) * U64(coords) >> U64(32)).astype(np.int64) if i < coords else np.full(len(row), i - coords)
        np.minimum.at(full, row * coords + where, U64(i << 32) | (h & U64(0xFFFFFFFF)))
        if i == 0 or i % 4 == 3 or i >= coords:
            open_rows = (full.reshape(n, coords) == np.iinfo(np.uint64).max).any(axis=1)
            go = open_rows[row]
            row, base = row[go], base[go]
    return textkit.mix(full ^ np.tile(textkit.stream_of(13, coords), n)).reshape(n, coords)


def _sketcher(size: int, coords: int, per_band: int):
    bands = coords // per_band
    names = ["doc_id", "n_shingles", "d1", "d2", "bands", "sketch"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for piece in textkit.pieces(batch, "text", 2 << 20):
                for at in range(0, piece.num_rows, ROWS):
                    b = piece.slice(at, ROWS)
                    items, offsets = shingle_sets(b.column(1), size)
                    n = np.diff(offsets)
                    s = sketch(items, offsets, coords)
                    key = textkit.stream_of(17, bands)[None, :].repeat(len(n), 0)
                    for j in range(per_band):
                        key = textkit.mix(key ^ s[:, j::per_band])
                    sums = [np.concatenate((np.zeros(1, U64), np.cumsum(textkit.mix(items ^ U64(x)), dtype=U64))) for x in (3, 5)]
                    d = [(x[offsets[1:]] - x[offsets[:-1]]).view(np.int64) for x in sums]
                    some = n > 0
                    listed = pa.ListArray.from_arrays(np.concatenate(([0], np.cumsum(some * bands))).astype(np.int32), key[some].reshape(-1).view(np.int64))
                    raw = np.ascontiguousarray((s & U64(255)).astype(np.uint8))
                    packed = pa.Array.from_buffers(pa.binary(), len(n), [None, pa.py_buffer((np.arange(len(n) + 1) * coords).astype(np.int32)), pa.py_buffer(raw)])
                    yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n), pa.array(d[0]), pa.array(d[1]), listed, packed], names=names)

    return run


def _confirm(size: int, per_cent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b in textkit.pieces(batch, "text_b", 1 << 20):
                a, c = b.column(0).to_numpy(), b.column(1).to_numpy()
                turn = np.concatenate(([True], a[1:] != a[:-1]))  # rows of one hub stand together: its set is made once
                hub = np.cumsum(turn) - 1
                left, lo = _sets(b.column(2).take(pa.array(np.flatnonzero(turn))), size)
                right, ro = _sets(b.column(3), size)
                good = np.zeros(len(a), bool)
                for i, h in enumerate(hub):
                    x, y = left[lo[h] : lo[h + 1]], right[ro[i] : ro[i + 1]]
                    if min(len(x), len(y)) * 100 >= per_cent * max(len(x), len(y)) and len(x):
                        at = np.minimum(np.searchsorted(x, y), len(x) - 1)
                        both = int((x[at] == y).sum())
                        good[i] = 100 * both >= per_cent * (len(x) + len(y) - both)
                yield pa.RecordBatch.from_arrays([pa.array(a[good]), pa.array(c[good])], names=["a", "b"])

    return run


def _sets(arr: pa.Array, size: int) -> tuple[np.ndarray, np.ndarray]:
    parts = [shingle_sets(arr.slice(i, ROWS), size) for i in range(0, len(arr), ROWS)]
    offsets, total = [np.zeros(1, np.int64)], 0
    for items, o in parts:
        offsets.append(o[1:] + total)
        total += len(items)
    return np.concatenate([p[0] for p in parts]), np.concatenate(offsets)


def _bits(items: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Rows of packed bits over the shingles that at least two sets hold."""
    kinds, at, count = np.unique(items, return_inverse=True, return_counts=True)
    place = np.cumsum(count > 1) - 1
    width = max(64, -(-int((count > 1).sum()) // 64) * 64)
    out = []
    for i in range(0, len(offsets) - 1, 256):
        end = min(i + 256, len(offsets) - 1)
        own = at[offsets[i] : offsets[end]]
        row = np.repeat(np.arange(end - i), np.diff(offsets[i : end + 1]))
        some = count[own] > 1
        plain = np.zeros((end - i, width), bool)
        plain[row[some], place[own[some]]] = True
        out.append(np.packbits(plain, axis=1).view(U64))
    return np.concatenate(out)


def join_components(ids: np.ndarray, comp: np.ndarray, sketches: np.ndarray, items: np.ndarray, offsets: np.ndarray, per_cent: int, least: int) -> list[tuple[int, int]]:
    """Confirmed links of one bucket that join different components, one for each join.

    Members that look most like the rest come first, so that a group around one text closes after one round; a member is
    compared with those outside its component only, on full sets, if sizes and sketches allow the similarity.
    """
    m, size, root = len(ids), np.diff(offsets), comp.copy()
    probe = sketches[:: max(1, m // 64)]
    order = np.argsort(-sum((sketches == p).sum(axis=1) for p in probe), kind="stable")
    bits, links = _bits(items, offsets), []
    for n, i in enumerate(order[:-1].tolist()):
        other = order[n + 1 :]
        other = other[root[other] != root[i]]
        if not len(other):
            continue
        lo, hi = np.minimum(size[other], size[i]), np.maximum(size[other], size[i])
        other = other[100 * lo >= per_cent * hi]
        other = other[(sketches[other] == sketches[i]).sum(axis=1) >= least]
        for k in range(0, len(other), 1024):
            some = other[k : k + 1024]
            both = np.bitwise_count(bits[some] & bits[i]).sum(axis=1).astype(np.int64)
            for j in some[100 * both >= per_cent * (size[some] + size[i] - both)].tolist():
                if root[j] != root[i]:
                    links.append((int(ids[i]), int(ids[j])))
                    root[root == root[j]] = root[i]
    return links


def _across(size: int, per_cent: int, coords: int):
    def run(group: pa.Table) -> pa.Table:
        ids, comp = group.column("doc_id").to_numpy(), group.column("component_id").to_numpy()
        s = np.frombuffer(b"".join(group.column("sketch").to_pylist()), np.uint8).reshape(len(ids), coords)
        items, offsets = _sets(group.column("text").combine_chunks(), size)
        links = join_components(ids, comp, s, items, offsets, per_cent, int(AGREE * coords))
        return pa.table({"a": pa.array([x[0] for x in links], pa.int64()), "b": pa.array([x[1] for x in links], pa.int64())})

    return run


def blocks_of(placed: DataFrame, members: int, shingles: int) -> DataFrame:
    """(key, sub, doc_id, component_id) of every group of pass 2, for rows (key, hub, doc_id, n_shingles, component_id).

    Block numbers 0.. of the hub's component come first, those of the other members after them; a group is a pair of one
    block of each kind, or of two blocks of others.  A bucket of one block of each kind is one group.
    """
    home = F.max(F.when(F.col("doc_id") == F.col("hub"), F.col("component_id")))
    mixed = placed.groupBy("key").agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("doc_id")).alias("mark"), F.min("component_id").alias("lo"), F.max("component_id").alias("hi"), home.alias("home"))
    # pass 1 has settled buckets of two; equal buckets of several bands count once
    alike = mixed.where("lo < hi and n > 2").groupBy("n", "mark").agg(F.min_by(F.struct("key", "home"), "key").alias("x")).select("x.*")
    opened = shared.written(placed.join(alike, "key").select("key", "doc_id", "n_shingles", "component_id", (F.col("component_id") == F.col("home")).alias("own")))
    side = opened.groupBy("key", "own").agg(F.greatest(F.ceil(F.count("*") / members), F.ceil(F.sum("n_shingles") / shingles)).cast("int").alias("c"))
    cuts = side.groupBy("key").agg(F.max(F.when(F.col("own"), F.col("c"))).alias("k"), F.max(F.when(~F.col("own"), F.col("c"))).alias("l"))
    # met in salted parts, so that the rows of one bucket are no single task's
    salts = F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))
    opened = opened.withColumn("salt", F.pmod(F.xxhash64("doc_id", F.lit(2)), F.lit(SALTS)).cast("int")).join(cuts.withColumn("salt", salts).hint("merge"), ["key", "salt"]).withColumn("at", F.pmod(F.xxhash64("doc_id", F.lit(1)), F.when(F.col("own"), F.col("k")).otherwise(F.col("l"))).cast("int"))
    total = F.col("k") + F.col("l")
    with_own = F.transform(F.sequence(F.lit(0), F.col("k") - 1), lambda x: x * total + F.col("k") + F.col("at"))
    with_rest = F.transform(F.sequence(F.lit(0), F.col("l") - 1), lambda x: (F.col("k") + F.least(x, F.col("at"))) * total + F.col("k") + F.greatest(x, F.col("at")))
    # two members of one block of others meet in that block's group with block 0 of the hub's component
    with_rest = F.filter(with_rest, lambda x: x != (F.col("k") + F.col("at")) * (total + 1))
    own_side = F.transform(F.sequence(F.lit(0), F.col("l") - 1), lambda x: F.col("at") * total + F.col("k") + x)
    subs = F.when(F.col("own"), own_side).otherwise(F.concat(with_own, with_rest))
    return opened.withColumn("sub", F.explode(subs)).select("key", "sub", "doc_id", "component_id")


def across(placed: DataFrame, made: DataFrame, texts: DataFrame, size: int, per_cent: int, coords: int, members: int, shingles: int) -> DataFrame:
    """Pass 2: (a, b) of confirmed links between components that share a bucket."""
    opened = blocks_of(placed, members, shingles).join(made.select("doc_id", "sketch"), "doc_id").join(texts, "doc_id")
    return opened.groupBy("key", "sub").applyInArrow(_across(size, per_cent, coords), "a long, b long").distinct()


def near_duplicates(docs: DataFrame, shingle: int = 5, per_cent: int = 80, coords: int = 128, per_band: int = 4, members: int = MEMBERS, shingles: int = SHINGLES) -> DataFrame:
    """doc_id, n_shingles, component_id, kept: groups of documents linked by Jaccard similarity of word shingles of at
    least ``per_cent`` hundredths; words are lower-cased in A-Z only.  ``members`` and ``shingles`` bound the blocks of
    pass 2 and change the work's cut, never the result."""
    docs = shared.one_row_per_id(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), "doc_id", "text")
    made = docs.mapInArrow(_sketcher(shingle, coords, per_band), "doc_id long, n_shingles long, d1 long, d2 long, bands array<long>, sketch binary")
    made = shared.written(made)
    some = made.where("n_shingles > 0")

    classes = some.groupBy("n_shingles", "d1", "d2").agg(F.min("doc_id").alias("head"), F.count("*").alias("copies"))
    heads = some.join(classes.select(F.col("head").alias("doc_id")), "doc_id", "left_semi")

    dealt = heads.select("doc_id", "n_shingles", F.explode("bands").alias("key"))
    shared_keys = dealt.groupBy("key").agg(F.min("doc_id").alias("hub"), F.count("*").alias("size")).where("size > 1")
    bucketed = shared.written(dealt.join(shared_keys, "key").select("key", "hub", "doc_id", "n_shingles"))
    texts = shared.written(docs.join(bucketed.select("doc_id").distinct(), "doc_id", "left_semi"))

    def confirmed(pairs: DataFrame) -> DataFrame:
        right = pairs.join(texts.select(F.col("doc_id").alias("b"), F.col("text").alias("text_b")), "b")
        both = right.join(texts.select(F.col("doc_id").alias("a"), F.col("text").alias("text_a")).hint("merge"), "a")
        return both.select("a", "b", "text_a", "text_b").mapInArrow(_confirm(shingle, per_cent), "a long, b long")

    first = bucketed.where("doc_id != hub").select(F.col("hub").alias("a"), F.col("doc_id").alias("b")).distinct()
    links = shared.written(confirmed(first))
    comp = components(links)

    placed = bucketed.join(comp, "doc_id", "left").withColumn("component_id", F.coalesce("component_id", "doc_id"))
    extra = shared.written(across(placed, made, texts, shingle, per_cent, coords, members, shingles))
    if not extra.isEmpty():
        comp = components(links.union(extra))

    # heads find their component by id; copies, of which one class may hold most, find that of their class in salted parts
    settled = classes.where("copies > 1").join(comp.withColumnRenamed("doc_id", "head"), "head", "left")
    settled = settled.select("n_shingles", "d1", "d2", F.coalesce("component_id", "head").alias("of_class"), F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    final = made.select("doc_id", "n_shingles", "d1", "d2", F.pmod(F.xxhash64("doc_id", F.lit(2)), F.lit(SALTS)).cast("int").alias("salt"))
    final = final.join(settled.hint("merge"), ["n_shingles", "d1", "d2", "salt"], "left").join(comp, "doc_id", "left")
    final = final.withColumn("component_id", F.coalesce("of_class", "component_id", "doc_id"))
    return final.select("doc_id", "n_shingles", "component_id", (F.col("doc_id") == F.col("component_id")).alias("kept"))
