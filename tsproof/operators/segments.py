"""Model segments: encoders, sealing, certification by replay, corrupt encoders."""

from __future__ import annotations

from collections.abc import Iterator
from decimal import Decimal
from math import ceil

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tsproof.functions.lines import T, V
from tsproof.sources import small, written

SCHEMA = "stream string, sid string, pos_lo long, c long, a long, b long, mu long, beta long, tau_lo long, t_last long, eps_v long, eps_t long"
CHUNK = 65_536


class Band:
    """Slopes and intercepts of the lines that pass within eps of all points so far (x = 0, 1, 2 ...).

    ``hull`` keeps the convex hulls of the upper and lower ends, so that a line is found if one exists; ``cone`` pins the
    line to the first point and keeps a slope interval only.
    """

    def __init__(self, eps: float, fit: str):
        self.eps, self.fit, self.n = eps, fit, 0
        self.low, self.high = -np.inf, np.inf
        self.up: list[tuple[int, float]] = []
        self.down: list[tuple[int, float]] = []

    def test(self, y: float) -> tuple | None:
        """What taking the next point would change; None if no line stays within eps.  Changes nothing."""
        x, hi, lo = self.n, y + self.eps, y - self.eps
        if x == 0:
            return ()
        if self.fit == "cone":
            low, high = max(self.low, (lo - self.first) / x), min(self.high, (hi - self.first) / x)
        else:
            # a line must pass above every lower end and below every upper end: its slope is at least that from any
            # earlier upper end to this lower end, and at most that from any earlier lower end to this upper end
            low, high = max(self.low, self._extreme(self.up, x, lo, 1)), min(self.high, self._extreme(self.down, x, hi, -1))
        return None if low > high else (low, high)

    def take(self, y: float, found: tuple) -> None:
        """Adds a point by what ``test`` found."""
        x, hi, lo = self.n, y + self.eps, y - self.eps
        if x == 0:
            self.first = y
            self.up, self.down = [(x, hi)], [(x, lo)]
        else:
            self.low, self.high = found
            if self.fit != "cone":
                self._push(self.up, (x, hi), 1)
                self._push(self.down, (x, lo), -1)
        self.n += 1

    def add(self, y: float) -> bool:
        """Takes the next point, or leaves the band as it is and returns False."""
        found = self.test(y)
        if found is None:
            return False
        self.take(y, found)
        return True

    def copy(self) -> Band:
        out = Band(self.eps, self.fit)
        out.n, out.low, out.high, out.up, out.down = self.n, self.low, self.high, self.up[:], self.down[:]
        if self.n:
            out.first = self.first
        return out

    @staticmethod
    def _extreme(hull: list[tuple[int, float]], x: int, y: float, sign: int) -> float:
        """Largest (sign 1) or smallest slope from a hull point to (x, y), by bisection: slopes along a hull have one peak."""
        a, b = 0, len(hull) - 1
        while a < b:
            m = (a + b) // 2
            p, q = hull[m], hull[m + 1]
            if sign * ((y - p[1]) / (x - p[0])) < sign * ((y - q[1]) / (x - q[0])):
                a = m + 1
            else:
                b = m
        p = hull[a]
        return (y - p[1]) / (x - p[0])

    @staticmethod
    def _push(hull: list[tuple[int, float]], p: tuple[int, float], sign: int) -> None:
        """Upper ends keep their lower hull, lower ends their upper hull."""
        while len(hull) >= 2 and sign * ((hull[-1][0] - hull[-2][0]) * (p[1] - hull[-2][1]) - (hull[-1][1] - hull[-2][1]) * (p[0] - hull[-2][0])) <= 0:
            hull.pop()
        hull.append(p)

    def line(self) -> tuple[float, float]:
        if self.n == 1:
            return 0.0, self.first
        if self.fit == "cone":
            return (self.low + self.high) / 2, self.first
        slope = (self.low + self.high) / 2
        top = min(y - slope * x for x, y in self.up)
        bottom = max(y - slope * x for x, y in self.down)
        return slope, (top + bottom) / 2


def _grow(tl: list[int], vl: list[int], n: int, start: int, eps_v: float, eps_t: float, fit: str) -> tuple[int, tuple, tuple]:
    """End of the segment that begins at ``start``, its value line and its arrival line, record by record."""
    values, arrivals = Band(eps_v, fit), Band(eps_t, fit)
    end = start
    while end < n:
        stop = end + 1
        while stop < n and tl[stop] == tl[end]:
            stop += 1
        if stop == end + 1:  # one record: both bands are asked before either changes
            v_found = values.test(vl[end])
            t_found = None if v_found is None else arrivals.test(float(tl[end] - tl[start]))
            if t_found is None:
                break
            values.take(vl[end], v_found)
            arrivals.take(float(tl[end] - tl[start]), t_found)
            end = stop
            continue
        kept = (values.copy(), arrivals.copy()) if end > start else None
        ok = True
        for k in range(end, stop):
            ok = (values.add(vl[k]) and arrivals.add(float(tl[k] - tl[start]))) and ok
            if kept and not ok:
                break
        if kept and not ok:
            values, arrivals = kept
            break
        end = stop
        if not ok:  # a tie run that no line fits stays whole; its bound is what replay finds
            break
    return end, values.line(), arrivals.line()


#: Starts that are grown side by side, and slopes a record that this may cost; longer segments are grown one by one.
LANES, SLOPES = 4096, 40


def _grow_all(t: np.ndarray, v: np.ndarray, eps_v: np.ndarray, eps_t: np.ndarray) -> tuple[np.ndarray, ...]:
    """Per position that may begin a segment (the first of its instant): records that the segment would take, and the least
    and largest slope of its value and arrival lines.  0 records: left to ``_grow``.

    All starts take their next record in step; a slope interval shrinks by the slopes to all records taken before."""
    n = len(t)
    y = v.astype(np.float64)
    parts = np.flatnonzero(np.concatenate((t[1:] != t[:-1], [True])))
    last = np.zeros(n, bool)
    last[parts] = True
    firsts = np.concatenate(([0], parts[:-1] + 1))
    count, slopes = np.zeros(n, np.int64), [np.zeros(n) for _ in range(4)]
    for block in (firsts[x : x + LANES] for x in range(0, len(firsts), LANES)):
        at, room = block, SLOPES * int(block[-1] - block[0] + 1)
        alive = np.ones(len(at), bool)
        ev, et, t0 = eps_v[at], eps_t[at], t[at]
        found = [np.full(len(at), x) for x in (-np.inf, np.inf, -np.inf, np.inf)]
        ends: list[list[np.ndarray]] = [[], [], [], []]  # upper and lower ends of values, of arrivals
        k = 0
        while len(at):
            j = np.minimum(at + k, n - 1)
            alive &= at + k < n
            for band, x, eps in ((0, y[j], ev), (2, (t[j] - t0).astype(np.float64), et)):
                hi, lo, up, down = x + eps, x - eps, ends[band], ends[band + 1]
                for q in range(k):
                    np.maximum(found[band], (lo - up[q]) / (k - q), out=found[band])
                    np.minimum(found[band + 1], (hi - down[q]) / (k - q), out=found[band + 1])
                up.append(hi)
                down.append(lo)
                alive &= found[band] <= found[band + 1]
            whole = np.flatnonzero(alive & last[j])
            count[at[whole]] = k + 1
            for kept, x in zip(slopes, found):
                kept[at[whole]] = x[whole]
            k += 1
            room -= k * len(at)
            if room < 0:  # what still grows is left to be grown alone
                count[at[alive]] = 0
                break
            stay = np.flatnonzero(alive)
            if len(stay) < 0.8 * len(at):
                at, alive, ev, et, t0 = at[stay], alive[stay], ev[stay], et[stay], t0[stay]
                found, ends = [x[stay] for x in found], [[x[stay] for x in e] for e in ends]
            elif not len(stay):
                break
    return count, *slopes


def _walk(t: np.ndarray, v: np.ndarray, eps_v: np.ndarray, eps_t: np.ndarray, fit: str) -> tuple[np.ndarray, np.ndarray, tuple, dict]:
    """Starts and counts of the greedy segments, the slopes known to all starts, and lines of those grown alone."""
    n = len(t)
    count, *slopes = _grow_all(t, v, eps_v, eps_t) if fit == "hull" and n else (np.zeros(n, np.int64), *[np.zeros(n)] * 4)
    known, starts, alone, at = count.tolist(), [], {}, 0
    tl, vl = (None, None) if all(known) else (t.tolist(), v.tolist())
    while at < n:
        starts.append(at)
        if known[at]:
            at += known[at]
            continue
        tl, vl = tl or t.tolist(), vl or v.tolist()
        end, *lines = _grow(tl, vl, n, at, float(eps_v[at]), float(eps_t[at]), fit)
        alone[len(starts) - 1] = lines
        at = end
    starts = np.array(starts, np.int64)
    return starts, np.diff(np.append(starts, n)), tuple(slopes), alone


def _whole(x: np.ndarray) -> np.ndarray:
    """Nearest integers, half to even; in Python's integers where 64 bits don't hold them."""
    return np.rint(x).astype(np.int64) if np.abs(x).max(initial=0) < _FITS else np.array([round(y) for y in x.tolist()], object)


def _encode(t: np.ndarray, v: np.ndarray, eps_v: np.ndarray, eps_t: np.ndarray, gap: float, fit: str) -> tuple[np.ndarray, ...]:
    """Columns start, count, a, b, mu, beta of one run of records."""
    starts, counts, (v_low, v_high, t_low, t_high), alone = _walk(t, v, eps_v, eps_t, fit)
    seg = np.repeat(np.arange(len(starts)), counts)
    x = (np.arange(len(t)) - starts[seg]).astype(np.float64)

    def line(y: np.ndarray, eps: np.ndarray, low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        slope = np.zeros(len(starts))
        many = counts > 1
        slope[many] = (low[starts[many]] + high[starts[many]]) / 2
        e, across = eps[starts][seg], slope[seg] * x
        level = (np.minimum.reduceat(y + e - across, starts) + np.maximum.reduceat(y - e - across, starts)) / 2
        return slope, np.where(many, level, y[starts])

    a, b = line(v.astype(np.float64), eps_v, v_low, v_high)
    mu, beta = line((t - t[starts][seg]).astype(np.float64), eps_t, t_low, t_high)
    for at, (value_line, arrival_line) in alone.items():
        (a[at], b[at]), (mu[at], beta[at]) = value_line, arrival_line
    mu[counts == 1], beta[counts == 1] = gap, 0.0
    return starts, counts, _whole(a * V), _whole(b * V), np.maximum(_whole(mu * T), 1), _whole(beta * T)


def encode_chunk(t: np.ndarray, v: np.ndarray, eps_v: np.ndarray, eps_t: np.ndarray, gap: float, fit: str) -> list[tuple[int, int, int, int, int, int]]:
    """Segments (start, count, a, b, mu, beta) of one run of records.

    A segment grows as far as one value line and one arrival line stay within the budgets of its first record.  Records
    with equal times never part.
    """
    return list(zip(*[x.tolist() for x in _encode(t, v, eps_v, eps_t, gap, fit)]))


def _chunks(records: DataFrame, budgets: DataFrame, chunk: int, variants: bool) -> tuple[DataFrame, DataFrame]:
    """Records and budgets by (sid, chunk); a tie belongs to the chunk of its first record.  Budgets of variants
    (sid: ``variant|sid``) go to the records of the stream, which aren't repeated."""
    first = records.groupBy("sid", "t").agg(F.min("pos").alias("_tie"))
    rows = records.select("stream", "sid", "t", "v", "pos")
    rows = rows.join(first, ["sid", "t"]) if _has_ties(records) else rows.withColumn("_tie", F.col("pos"))
    rows = rows.withColumn("chunk", F.expr(f"_tie div {chunk}")).drop("_tie")
    mine = F.expr("substring(sid, instr(sid, '|') + 1)") if variants else F.col("sid")
    b = budgets.select(mine.alias("sid"), F.col("sid").alias("name"), F.col("region").cast("long").alias("region"), F.col("eps_v").cast("double").alias("eps_v"), F.col("eps_t").cast("double").alias("eps_t"), F.col("gap").cast("double").alias("gap"), F.col("region_size").cast("long").alias("region_size"))
    spans = rows.groupBy("sid").agg(F.max("chunk").alias("_last"))
    return rows, b.join(small(spans), "sid").withColumn("chunk", F.explode(F.sequence(F.lit(0).cast("long"), "_last"))).drop("_last")


def _each(rows: pa.Table, budgets: pa.Table) -> Iterator[tuple[str, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray, float]]:
    """(name, pos, t, v, eps_v, eps_t, gap) of one chunk under each of its budgets."""
    rows, budgets = rows.sort_by("pos"), budgets.sort_by([("name", "ascending"), ("region", "ascending")])
    if not len(rows) or not len(budgets):
        return
    t, v, pos = (rows.column(c).to_numpy() for c in ("t", "v", "pos"))
    b = {c: budgets.column(c).to_numpy(zero_copy_only=False) for c in ("name", "region", "eps_v", "eps_t", "gap", "region_size")}
    cuts = [*np.flatnonzero(np.concatenate(([True], b["name"][1:] != b["name"][:-1]))), len(budgets)]
    for lo, hi in zip(cuts, cuts[1:]):
        at = lo + np.searchsorted(b["region"][lo:hi], np.minimum(pos // b["region_size"][lo:hi].max(), b["region"][hi - 1]))
        yield b["name"][lo], pos, t, v, b["eps_v"][at], b["eps_t"][at], float(b["gap"][at[0]] or 1.0)


def counts(records: DataFrame, budgets: DataFrame, fit: str = "hull", chunk: int = CHUNK, variants: bool = False) -> DataFrame:
    """Segments that ``greedy`` would make (sid, count), without their lines."""
    rows, b = _chunks(records, budgets, chunk, variants)

    def run(key: tuple, rows: pa.Table, budgets: pa.Table) -> pa.Table:
        found = [(name, len(_walk(t, v, ev, et, fit)[0])) for name, _, t, v, ev, et, _ in _each(rows, budgets)]
        return pa.table({"sid": pa.array([x for x, _ in found], pa.string()), "count": pa.array([x for _, x in found], pa.int64())})

    made = rows.groupBy("sid", "chunk").cogroup(b.groupBy("sid", "chunk")).applyInArrow(run, "sid string, count long")
    return made.groupBy("sid").agg(F.sum("count").alias("count"))


def greedy(records: DataFrame, budgets: DataFrame, fit: str = "hull", chunk: int = CHUNK, bound: str = "residual", variants: bool = False) -> DataFrame:
    """Segments of all streams.  budgets: (sid, region, eps_v, eps_t, gap), region = region of the position, of
    ``regions`` equal ones, as given by a column region_size.  Chunks of positions are encoded apart, which adds at most
    one segment per chunk; the cut moves to the next distinct time.  With ``variants``, budgets have sids ``variant|sid``
    and each makes a stream of that name from the records of ``sid``.
    """
    rows, b = _chunks(records, budgets, chunk, variants)
    names = [*[x.split()[0] for x in SCHEMA.split(", ")], "chunk"]
    types = [pa.string(), pa.string(), *[pa.int64()] * 11]

    def run(key: tuple, rows: pa.Table, budgets: pa.Table) -> pa.Table:
        made = [pa.table({n: pa.array([], k) for n, k in zip(names, types)})]
        for name, pos, t, v, eps_v, eps_t, gap in _each(rows, budgets):
            start, count, a, b, mu, beta = _encode(t, v, eps_v, eps_t, gap, fit)
            seg = {"pos_lo": pos[start], "a": a, "b": b, "mu": mu, "beta": beta, "tau_lo": t[start]}
            dv, dt = _residuals(seg, np.repeat(np.arange(len(start)), count), pos, t, v)
            ev, et = np.maximum.reduceat(dv, start), np.maximum.reduceat(dt, start)
            if bound == "budget":
                ev, et = ([max(int(x), ceil(y * scale)) for x, y in zip(e, eps[start].tolist())] for e, eps, scale in ((ev, eps_v, V), (et, eps_t, T)))
            n = len(start)
            columns = [[rows.column("stream")[0].as_py()] * n, [name] * n, pos[start], count, a, b, mu, beta, t[start], t[start + count - 1], ev, et, [key[1].as_py()] * n]
            made.append(pa.table({c: pa.array(x, k) for c, k, x in zip(names, types, columns, strict=True)}))
        return pa.concat_tables(made)

    # numbered chunk by chunk: offsets and the next chunk's first instant come from a table of one row per chunk
    made = written(rows.groupBy("sid", "chunk").cogroup(b.groupBy("sid", "chunk")).applyInArrow(run, SCHEMA + ", chunk long"))
    along = Window.partitionBy("sid").orderBy("chunk")
    parts = made.groupBy("sid", "chunk").agg(F.count("*").alias("_c"), F.min("tau_lo").alias("_first"))
    parts = parts.select("sid", "chunk", F.coalesce(F.sum("_c").over(along.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"), F.lead("_first").over(along).alias("_next"))
    w = Window.partitionBy("sid", "chunk").orderBy("pos_lo")
    out = made.join(parts, ["sid", "chunk"])
    out = out.withColumns({"j": F.row_number().over(w).cast("long") - 1 + F.col("_before"), "tau_hi": F.coalesce(F.lead("tau_lo").over(w), F.col("_next"), F.col("t_last") + 1)})
    return out.select(*[x.split()[0] for x in SCHEMA.split(", ") if not x.startswith("t_last")], "j", "tau_hi")


def _has_ties(records: DataFrame) -> bool:
    return not records.groupBy("sid", "t").count().where("count > 1").limit(1).isEmpty()


SEEN = "sid string, j long, dv decimal(38,0), dt decimal(38,0), seen long, t_min long, t_max long"
_FITS = 2.0**62


def _residuals(seg: dict[str, np.ndarray], at: np.ndarray, pos: np.ndarray, t: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """|value error| and |arrival error| of records against their segments, exact: in 64 bits where no product can leave
    them, else in Python's integers."""
    g = {c: x[at] for c, x in seg.items()}
    p = pos - g["pos_lo"]
    big = lambda x: float(np.abs(x.astype(np.float64)).max(initial=0))
    most = max(big(g["a"]) * big(p) + big(g["b"]) + big(v) * V, big(g["mu"]) * big(p) + big(g["beta"]) + big(t - g["tau_lo"]) * T)
    if most >= _FITS:
        g, p, v, t = {c: x.astype(object) for c, x in g.items()}, p.astype(object), v.astype(object), t.astype(object)
    return abs(g["a"] * p + g["b"] - v * V), abs(g["mu"] * p + g["beta"] - (t - g["tau_lo"]) * T)


def _replay_chunk(key: tuple, segs: pa.Table, rows: pa.Table) -> pa.Table:
    """One merge by position of a chunk's records with the segments that reach into it."""
    segs, rows = segs.sort_by("pos_lo"), rows.sort_by("pos")
    seg = {c: segs.column(c).to_numpy() for c in ("j", "pos_lo", "c", "a", "b", "mu", "beta", "tau_lo")}
    pos, t, v = (rows.column(c).to_numpy() for c in ("pos", "t", "v"))
    at = np.searchsorted(seg["pos_lo"], pos, "right") - 1
    inside = at >= 0
    inside[inside] = pos[inside] < (seg["pos_lo"] + seg["c"])[at[inside]]
    at, pos, t, v = at[inside], pos[inside], t[inside], v[inside]
    kinds = ([pa.string(), pa.int64(), pa.decimal128(38, 0), pa.decimal128(38, 0), *[pa.int64()] * 3], [x.split()[0] for x in SEEN.split(", ")])
    if not len(at):
        return pa.table({n: pa.array([], k) for k, n in zip(*kinds, strict=True)})
    dv, dt = _residuals(seg, at, pos, t, v)
    first = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
    most = lambda x: [Decimal(int(y)) for y in np.maximum.reduceat(x, first)]
    out = [[key[0].as_py()] * len(first), seg["j"][at[first]], most(dv), most(dt), np.diff([*first, len(at)]), np.minimum.reduceat(t, first), np.maximum.reduceat(t, first)]
    return pa.table({n: pa.array(x, k) for x, k, n in zip(out, *kinds, strict=True)})


def replay(segments: DataFrame, records: DataFrame, chunk: int = 16_384) -> DataFrame:
    """What validators do: each segment's records against both bounds, its count and the tiling of time.

    One vectorised merge per chunk of positions, constant work a record; neighbours and counts of segments meet by
    equality on (sid, j), so no task orders a stream.
    Result per segment: valid and the first reason (slope, tiling, count, value, arrival).
    """
    spans = segments.select("sid", "j", "pos_lo", "c", "a", "b", "mu", "beta", "tau_lo").withColumn("chunk", F.explode(F.sequence(F.expr(f"pos_lo div {chunk}"), F.expr(f"greatest(pos_lo + c - 1, pos_lo) div {chunk}"))))
    rows = records.select("sid", "pos", "t", "v", F.expr(f"pos div {chunk}").alias("chunk"))
    seen = spans.groupBy("sid", "chunk").cogroup(rows.groupBy("sid", "chunk")).applyInArrow(_replay_chunk, SEEN)
    seen = seen.groupBy("sid", "j").agg(F.max("dv").alias("_dv"), F.max("dt").alias("_dt"), F.sum("seen").alias("_c"), F.min("t_min").alias("_tlo"), F.max("t_max").alias("_thi"))
    after = segments.select("sid", (F.col("j") - 1).alias("j"), F.col("tau_lo").alias("_next"))
    whole = segments.groupBy("sid").agg(F.sum("c").alias("_sum"), F.count("*").alias("_segs"), F.min("j").alias("_first"), F.max("j").alias("_last"))
    whole = whole.join(records.groupBy("sid").agg(F.count("*").alias("_n")), "sid", "left")
    s = segments.join(seen, ["sid", "j"], "left").join(after, ["sid", "j"], "left").join(small(whole), "sid")
    odd = (F.col("_first") != 0) | (F.col("_segs") != F.col("_last") + 1) | (F.col("_sum") != F.coalesce("_n", F.lit(0)))
    reason = (
        F.when(F.col("mu") <= 0, "slope")
        .when(odd | (F.col("j") < F.col("_last")) & (F.col("_next").isNull() | (F.col("_next") != F.col("tau_hi"))), "tiling")
        .when(F.coalesce("_c", F.lit(0)) != F.col("c"), "count")
        .when((F.col("_tlo") < F.col("tau_lo")) | (F.col("_thi") >= F.col("tau_hi")), "tiling")
        .when(F.col("_dv") > F.col("eps_v"), "value")
        .when(F.col("_dt") > F.col("eps_t"), "arrival")
        .otherwise("ok")
    )
    return s.select("sid", "j", reason.alias("reason"), (reason == "ok").alias("valid"))


CORRUPTIONS = ("value_bound", "arrival_bound", "count", "gap", "overlap", "slope")


def bad_encoder(segments: DataFrame, kind: str) -> DataFrame:
    """Segments of a misbehaving encoder; each kind must fail the replay."""
    odd = F.col("j") == 1
    change = {
        "value_bound": {"eps_v": F.when(odd, F.floor(F.col("eps_v") / 2) - 1).otherwise(F.col("eps_v")).cast("long")},
        "arrival_bound": {"eps_t": F.when(odd, F.floor(F.col("eps_t") / 2) - 1).otherwise(F.col("eps_t")).cast("long")},
        "count": {"c": F.when(odd, F.col("c") + 1).otherwise(F.col("c"))},
        "gap": {"tau_hi": F.when(odd, F.col("tau_hi") - 1).otherwise(F.col("tau_hi"))},
        "overlap": {"tau_lo": F.when(odd, F.col("tau_lo") - 1).otherwise(F.col("tau_lo"))},
        "slope": {"mu": F.when(odd, F.lit(0)).otherwise(F.col("mu")).cast("long")},
    }[kind]
    return segments.withColumns(change)


def from_table(df: DataFrame) -> DataFrame:
    """Segments of any outside encoder, by schema only; certify them before use."""
    return df.select("stream", "sid", "j", "pos_lo", "c", "a", "b", "mu", "beta", "tau_lo", "tau_hi", "eps_v", "eps_t")


def minimal_count(v: list[int], eps: float) -> int:
    """Fewest value segments by dynamic programming, for small checks."""
    best = [0]
    for end in range(1, len(v) + 1):
        least = end
        for start in range(end - 1, -1, -1):
            band = Band(eps, "hull")
            if not all(band.add(x) for x in v[start:end]):
                break
            least = min(least, best[start] + 1)
        best.append(least)
    return best[-1]

