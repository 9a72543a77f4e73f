"""Trees of hash-bound aggregates over dense leaf orders, many streams at once.

A pass builds up to ``chunk`` levels: leaves are dealt by (stream, aligned chunk) and sorted once, and a task folds its
chunks as they stream past.  All levels of a pass share one shuffle and one sort, and no level is computed twice.  Chunk
roots are the leaves of the next pass, f^chunk times fewer.  ``lift`` is the same pass as window functions: level k + 1 leads
level k by f^k, 2 f^k ... rows, evaluated at aligned rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tsproof.functions import cover, encoding
from tsproof.sources import written

COLUMNS = ["sid", "lvl", "idx", *encoding.ALPHA, "eta"]


def record_leaves(records: DataFrame) -> DataFrame:
    """Leaves of the tree over records."""
    zero = F.lit(0).cast("decimal(38,0)")
    return records.select("sid", F.col("pos").alias("idx"), F.col("v").cast("decimal(38,0)").alias("s"), F.lit(1).cast("long").alias("n"), F.col("v").alias("mn"), F.col("v").alias("mx"), F.col("t").alias("t_lo"), F.col("t").alias("t_hi"), zero.alias("w"), encoding.record_hash().alias("eta"))


def segment_leaves(segments: DataFrame) -> DataFrame:
    """Leaves of the tree over segments: sums and extremes of reconstructions, value slack, time extent."""
    a, b, c = (F.col(x).cast("decimal(38,0)") for x in ("a", "b", "c"))
    last = a * (F.col("c") - 1).cast("decimal(19,0)") + b
    s = (a * (F.col("c") * (F.col("c") - 1) / 2).cast("decimal(38,0)") + b * c).cast("decimal(38,0)")
    mn, mx = F.least(b, last).cast("long"), F.greatest(b, last).cast("long")
    w = (F.col("eps_v").cast("decimal(19,0)") * F.col("c").cast("decimal(19,0)")).cast("decimal(38,0)")
    return segments.select("sid", F.col("j").alias("idx"), s.alias("s"), F.col("c").alias("n"), mn.alias("mn"), mx.alias("mx"), F.col("tau_lo").alias("t_lo"), F.col("tau_hi").alias("t_hi"), w.alias("w"), encoding.segment_hash().alias("eta"))


def _node(c: Column) -> Column:
    return c.cast(encoding.NODE)


def combine(children: list[Column]) -> Column:
    """Fold of up to f children (nulls: missing) into their parent."""
    first = children[0]
    add = lambda x, zero: reduce(lambda p, q: p + q, [F.coalesce(c[x], zero) for c in children])
    d0, l0 = F.lit(0).cast("decimal(38,0)"), F.lit(0).cast("long")
    pick = (lambda fn, x: fn(*[c[x] for c in children])) if len(children) > 1 else (lambda fn, x: first[x])
    return _node(F.struct(add("s", d0).cast("decimal(38,0)").alias("s"), add("n", l0).alias("n"), pick(F.least, "mn").alias("mn"), pick(F.greatest, "mx").alias("mx"), first["t_lo"].alias("t_lo"), pick(F.greatest, "t_hi").alias("t_hi"), add("w", d0).cast("decimal(38,0)").alias("w"), encoding.node_hash(children).alias("eta")))


def lift(level: DataFrame, f: int, levels: int) -> DataFrame:
    """Nodes of this level (lvl 0 here) and of the next ``levels`` within aligned chunks of f^levels."""
    width = f**levels
    df = level.select("sid", "idx", _node(F.struct(*encoding.ALPHA, "eta")).alias("n0"), F.expr(f"idx div {width}").alias("chunk"))
    w = Window.partitionBy("sid", "chunk").orderBy("idx")
    for k in range(levels):
        step = f**k
        kids = [F.col(f"n{k}"), *[F.lead(f"n{k}", j * step).over(w) for j in range(1, f)]]
        df = df.withColumns({f"c{j}": c for j, c in enumerate(kids)})
        df = df.withColumn(f"n{k + 1}", F.when(F.col("idx") % (step * f) == 0, combine([F.col(f"c{j}") for j in range(f)])))
    rows = F.array(*[F.struct(F.lit(k).alias("lvl"), F.col(f"n{k}").alias("nd")) for k in range(levels + 1)])
    out = df.select("sid", "idx", F.explode(F.filter(rows, lambda x: x["nd"].isNotNull())).alias("x"))
    return out.select("sid", F.col("x.lvl").alias("lvl"), F.floor(F.col("idx") / F.pow(F.lit(f), F.col("x.lvl"))).cast("long").alias("idx"), "x.nd.*")


#: Leaves of a chunk that a task folds at a time, unless ``build`` is told the levels of a pass.
WIDTH = 4096
_FOLDED = "sid string, lvl int, idx long, s string, n long, mn long, mx long, t_lo long, t_hi long, w string, eta string"


def _fold_chunks(rows: list[tuple], f: int, levels: int) -> Iterator[tuple]:
    """Nodes above sorted leaves (sid, idx, s, n, mn, mx, t_lo, t_hi, w, eta) of whole chunks, level by level.  A node left
    alone at index 0 is its stream's root: below a full chunk's top there are always more."""
    text = lambda r: f"{r[9]}|{r[2]}:{r[3]}:{'~' if r[4] is None else r[4]}:{'~' if r[5] is None else r[5]}:{'~' if r[6] is None else r[6]}:{'~' if r[7] is None else r[7]}:{r[8]}"
    least = lambda xs, fn: fn((x for x in xs if x is not None), default=None)
    for lvl in range(1, levels + 1):
        up, i, m = [], 0, len(rows)
        while i < m:
            sid, idx = rows[i][0], rows[i][1] // f
            j = i + 1
            while j < m and rows[j][1] // f == idx and rows[j][0] == sid:
                j += 1
            kids, i = rows[i:j], j
            if len(kids) == 1 and kids[0][1] == 0 and (j == m or rows[j][0] != sid):
                continue
            eta = encoding.sha("N|" + "|".join(map(text, kids)))
            up.append((sid, idx, sum(r[2] for r in kids), sum(r[3] for r in kids), least([r[4] for r in kids], min), least([r[5] for r in kids], max), kids[0][6], least([r[7] for r in kids], max), sum(r[8] for r in kids), eta))
        for r in up:
            yield (r[0], lvl, *r[1:])
        rows = up


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = {"long": pa.int64(), "int": pa.int32(), "string": pa.string()}
    schema = pa.schema([(name, kinds[kind]) for name, kind in (x.split() for x in _FOLDED.split(", "))])
    columns = list(zip(*rows)) or [()] * len(schema)
    as_text = lambda f, c: [str(x) for x in c] if f.name in ("s", "w") else c
    return pa.RecordBatch.from_arrays([pa.array(as_text(f, c), f.type) for f, c in zip(schema, columns, strict=True)], schema=schema)


def _integers(x: pa.ChunkedArray) -> np.ndarray:
    """Integers given as text; 64 bits where any sum of them fits, else Python's."""
    try:
        out = x.cast(pa.int64()).to_numpy()
        if np.abs(out.astype(np.float64)).sum() < 2.0**62:
            return out
    except pa.ArrowInvalid:
        pass
    return np.array([int(y) for y in x.to_pylist()], object)


def _fold_table(rows: pa.Table, f: int, levels: int) -> pa.RecordBatch:
    """What ``_fold_chunks`` makes, column by column: numbers of a level are folded at once, only hashes node by node."""
    numbers = ("n", "mn", "mx", "t_lo", "t_hi")
    if any(rows.column(c).null_count for c in (*numbers, "s", "w")):
        columns = {c: rows.column(c).to_pylist() for c in rows.column_names}
        columns |= {c: [0 if x is None else int(x) for x in columns[c]] for c in ("s", "w")}
        return _batch(list(_fold_chunks(list(zip(*columns.values())), f, levels)))
    streams = rows.column("sid").combine_chunks().dictionary_encode(null_encoding="encode")
    streams = streams.combine_chunks() if isinstance(streams, pa.ChunkedArray) else streams
    sid, idx = streams.indices.to_numpy(), rows.column("idx").to_numpy()
    g = {c: rows.column(c).to_numpy() for c in numbers} | {c: _integers(rows.column(c)) for c in ("s", "w")}
    eta, made = rows.column("eta").to_pylist(), []
    fold_of = {"s": np.add, "n": np.add, "mn": np.minimum, "mx": np.maximum, "t_hi": np.maximum, "w": np.add}
    for lvl in range(1, levels + 1):
        if not len(idx):
            break
        up = idx // f
        start = np.flatnonzero(np.concatenate(([True], (up[1:] != up[:-1]) | (sid[1:] != sid[:-1]))))
        end = np.append(start[1:], len(idx))
        # a node left alone at index 0 is its stream's root
        alone = (end - start == 1) & (idx[start] == 0) & (np.append(sid[start[1:]], -1) != sid[start])
        texts = [f"{e}|{s}:{n}:{mn}:{mx}:{lo}:{hi}:{w}" for e, s, n, mn, mx, lo, hi, w in zip(eta, *[g[c].tolist() for c in ("s", *numbers, "w")])]
        g = {c: (fold_of[c].reduceat(x, start) if c in fold_of else x[start])[~alone] for c, x in g.items()}
        start, end = start[~alone], end[~alone]
        eta = [encoding.sha("N|" + "|".join(texts[i:j])) for i, j in zip(start.tolist(), end.tolist())]
        sid, idx = sid[start], up[start]
        text = lambda x: pa.array([str(y) for y in x.tolist()], pa.string())
        made.append(pa.table({"sid": streams.dictionary.take(pa.array(sid)), "lvl": np.full(len(idx), lvl, np.int32), "idx": idx, "s": text(g["s"]), **{c: g[c] for c in numbers}, "w": text(g["w"]), "eta": pa.array(eta, pa.string())}))
    out = pa.concat_tables(made) if made else pa.Table.from_batches([_batch([])])
    return out.combine_chunks().to_batches()[0] if len(out) else _batch([])


def fold(level: DataFrame, f: int, levels: int) -> DataFrame:
    """Nodes of the next ``levels`` above this one (lvl 0, left out) within aligned chunks of f^levels, up to each stream's
    root: one shuffle, one sort, and in a task no more than a batch and an open chunk."""
    width = f**levels

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.Table | None = None
        for b in batches:
            if not len(b):
                continue
            rows = pa.Table.from_batches([b])
            held = rows if held is None or not len(held) else pa.concat_tables([held, rows])
            chunk = held.column("idx").to_numpy() // width
            last = held.column("sid")[len(held) - 1]
            same = pc.equal(held.column("sid"), last) if last.is_valid else pc.is_null(held.column("sid"))
            # the last chunk may go on in the next batch; rows are sorted, so it is the tail
            cut = len(held) - int(np.count_nonzero((chunk == chunk[-1]) & pc.fill_null(same, False).to_numpy()))
            if cut:
                yield _fold_table(held.slice(0, cut), f, levels)
                held = held.slice(cut)
        if held is not None and len(held):
            yield _fold_table(held, f, levels)

    rows = level.select("sid", "idx", F.col("s").cast("string").alias("s"), "n", "mn", "mx", "t_lo", "t_hi", F.col("w").cast("string").alias("w"), "eta")
    dealt = rows.repartition(F.col("sid"), F.expr(f"idx div {width}")).sortWithinPartitions("sid", "idx")
    out = dealt.mapInArrow(run, _FOLDED)
    return out.withColumns({c: F.col(c).cast("decimal(38,0)") for c in ("s", "w")})


def build(leaves: DataFrame, fanout: int = 2, chunk: int | None = None) -> DataFrame:
    """All nodes (sid, lvl, idx, aggregate, eta) up to each stream's root; written once per pass of ``chunk`` levels."""
    level = written(leaves.select("sid", F.lit(0).alias("lvl"), "idx", *encoding.ALPHA, "eta"))
    per_pass = chunk or max(1, cover.depth_of(WIDTH, fanout))
    most = level.agg(F.max("idx")).first()[0]
    deepest = 0 if most is None else cover.depth_of(most + 1, fanout)
    parts, base = [level], 0
    while base < deepest:
        levels = min(per_pass, deepest - base)
        made = written(fold(level, fanout, levels))
        parts.append(made.withColumn("lvl", F.col("lvl") + base))
        base += levels
        level = made.where(F.col("lvl") == levels)
    return reduce(lambda x, y: x.unionByName(y), parts).select(*COLUMNS)


def build_by_groups(leaves: DataFrame, fanout: int = 2) -> DataFrame:
    """The same nodes by one aggregation per level: the reference that the window build is held against."""
    level = written(leaves.select("sid", F.lit(0).alias("lvl"), "idx", *encoding.ALPHA, "eta"))
    parts = [level]
    while level.groupBy("sid").count().where("count > 1").limit(1).count():
        many = level.join(level.groupBy("sid").count().where("count > 1").select("sid"), "sid", "left_semi")
        node = F.struct("idx", _node(F.struct(*encoding.ALPHA, "eta")).alias("nd"))
        up = many.withColumn("up", F.expr(f"idx div {fanout}")).groupBy("sid", "up").agg(F.max("lvl").alias("l"), F.array_sort(F.collect_list(node)).alias("kids"))
        kids = [F.try_element_at("kids", F.lit(j + 1))["nd"] for j in range(fanout)]
        up = up.select("sid", (F.col("l") + 1).alias("lvl"), F.col("up").alias("idx"), combine(kids).alias("nd"))
        level = written(up.select("sid", "lvl", "idx", "nd.*"))
        parts.append(level)
    return reduce(lambda x, y: x.unionByName(y), parts).select(*COLUMNS)


def roots(nodes: DataFrame) -> DataFrame:
    """Top node of each stream."""
    top = nodes.groupBy("sid").agg(F.max_by(F.struct(*encoding.ALPHA, "eta"), "lvl").alias("x"))
    return top.select("sid", "x.*")


def shortened(nodes: DataFrame, sizes: DataFrame, fanout: int = 2) -> DataFrame:
    """The trees as they were when streams held their first n records (sid, n): sealed blocks stay, and the nodes on the
    right edge, one a level, are folded anew from the spine alone."""

    def run(group: pa.Table) -> pa.Table:
        rows: dict[int, list[tuple]] = {}
        for r in group.to_pylist():
            rows.setdefault(r["lvl"], []).append((r["sid"], r["idx"], int(r["s"]), *[r[c] for c in ("n", "mn", "mx", "t_lo", "t_hi")], int(r["w"]), r["eta"]))
        made, carry, lvl, top = [], [], 0, max(rows)
        while lvl <= top or carry:
            up = list(_fold_chunks(sorted(rows.get(lvl, []), key=lambda r: r[1]) + carry, fanout, 1))
            made += [(r[0], lvl + 1, *r[2:]) for r in up]
            carry, lvl = [(r[0], *r[2:]) for r in up], lvl + 1
        return pa.Table.from_batches([_batch(made)])

    edge = spine(nodes, sizes, fanout).groupBy("sid").applyInArrow(run, _FOLDED)
    edge = written(edge.withColumns({"s": F.col("s").cast("decimal(38,0)"), "w": F.col("w").cast("decimal(38,0)")}).select(*COLUMNS))
    whole = nodes.select(*COLUMNS).join(F.broadcast(sizes.select("sid", F.col("n").alias("_n"))), "sid")
    sealed = (F.col("idx") + 1) * F.pow(F.lit(fanout), F.col("lvl")).cast("long") <= F.col("_n")
    return whole.where(sealed).select(*COLUMNS).unionByName(edge)


def alpha_text() -> Column:
    return F.concat_ws(":", *[F.col(c).cast("string") for c in encoding.ALPHA])


def anchor(raw_nodes: DataFrame, seg_nodes: DataFrame | None = None, segments: DataFrame | None = None, fanout: int = 2, height: int = 0) -> DataFrame:
    """One row per stream: what the chain would hold, and its digest."""
    out = roots(raw_nodes).select("sid", F.lit(height).cast("long").alias("height"), F.lit(fanout).alias("fanout"), F.col("n").alias("raw_n"), F.col("eta").alias("raw_root"), alpha_text().alias("raw_alpha"), F.col("mn").alias("raw_min"))
    if seg_nodes is not None:
        caps = segments.groupBy("sid").agg(F.max("eps_v").alias("cap"), F.count("*").alias("seg_n"))
        seg = roots(seg_nodes).select("sid", F.col("eta").alias("seg_root"), alpha_text().alias("seg_alpha")).join(caps, "sid")
        out = out.join(seg, "sid", "left")
    else:
        out = out.withColumns({"cap": F.lit(None).cast("long"), "seg_n": F.lit(None).cast("long"), "seg_root": F.lit(None).cast("string"), "seg_alpha": F.lit(None).cast("string")})
    return out.withColumn("digest", encoding.anchor_digest())


def spine(nodes: DataFrame, sizes: DataFrame, fanout: int = 2) -> DataFrame:
    """Full blocks on the right edge of streams of the given sizes (sid, n): at most f - 1 nodes a level, and all that an
    append has to read of the old tree."""
    w = F.pow(F.lit(fanout), F.col("lvl")).cast("long")
    edge = nodes.select(*COLUMNS).join(sizes.select("sid", F.col("n").alias("_n")), "sid").withColumn("_w", w)
    sealed = (F.col("idx") + 1) * F.col("_w") <= F.col("_n")
    wanted = F.expr(f"idx div {fanout}") == F.floor(F.col("_n") / (F.col("_w") * fanout))
    return edge.where(sealed & wanted).select(*COLUMNS)


def grow(nodes: DataFrame, leaves: DataFrame, fanout: int = 2) -> DataFrame:
    """The nodes that appended leaves make or change; ``nodes`` holds the spine at least.

    Full blocks of the old tree are sealed: the spine stands in for them, level by level, and only nodes on the right
    edge are made anew: O(m + log n) rows of work for m new leaves.
    """
    first = leaves.groupBy("sid").agg(F.min("idx").alias("n"), F.count("*").alias("_new"))
    front = written(spine(nodes, first, fanout))
    top = written(first.select("sid", cover.depth_column(F.col("n") + F.col("_new"), fanout).alias("_depth")))
    deepest = top.agg(F.max("_depth")).first()[0] or 0
    level = written(leaves.select("sid", F.lit(0).alias("lvl"), "idx", *encoding.ALPHA, "eta"))
    parts = [level]
    for k in range(deepest):
        both = level.unionByName(front.where(F.col("lvl") == k))
        kids = both.withColumn("up", F.expr(f"idx div {fanout}")).groupBy("sid", "up").agg(F.array_sort(F.collect_list(F.struct("idx", _node(F.struct(*encoding.ALPHA, "eta")).alias("nd")))).alias("kids"))
        up = kids.select("sid", F.lit(k + 1).alias("lvl"), F.col("up").alias("idx"), combine([F.try_element_at("kids", F.lit(j + 1))["nd"] for j in range(fanout)]).alias("nd"))
        level = written(up.join(top, "sid").where("lvl <= _depth").select("sid", "lvl", "idx", "nd.*"))
        parts.append(level)
    return reduce(lambda x, y: x.unionByName(y), parts).select(*COLUMNS)


def append(nodes: DataFrame, leaves: DataFrame, fanout: int = 2) -> DataFrame:
    """All nodes after appending leaves whose idx continues each stream."""
    made = grow(nodes, leaves, fanout)
    return nodes.select(*COLUMNS).join(made, ["sid", "lvl", "idx"], "left_anti").select(*COLUMNS).unionByName(made)
