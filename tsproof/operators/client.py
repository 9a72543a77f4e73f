"""The client: plain functions of (query, proof, anchor) and nothing else, plus their batch form.

Checks run in order and the first that fails is named: anchor (digest), covering (shape, contiguity, times), root, fold.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from typing import Any

import pyarrow as pa
from pyspark.sql import DataFrame

from tsproof.functions import cover, encoding, lines


class Rejected(Exception):
    """The name of the check that failed."""


@dataclass
class Verdict:
    accepted: bool
    reason: str
    s: int = 0
    n: int = 0
    mn: int | None = None
    mx: int | None = None
    hashes: int = 0
    records: list[dict] = field(default_factory=list)
    pieces: lines.Pieces | None = None


def _width(lvl: int, n: int, f: int) -> int:
    return -(-n // f**lvl)


def plain(item: dict) -> dict:
    """Integers for decimals, dicts for maps."""
    out = dict(item)
    if out.get("alpha") is not None:
        out["alpha"] = {k: int(v) if v is not None else None for k, v in out["alpha"].items()}
    if out.get("rec") is not None:
        out["rec"] = dict(out["rec"])
    return out


def _leaf(item: dict, sid: str) -> tuple[str, dict]:
    """Hash and aggregate of an opened leaf, computed from its content."""
    if item.get("seg") is not None:
        g = item["seg"]
        last = g["a"] * (g["c"] - 1) + g["b"]
        alpha = {"s": lines.line_sum(g["a"], g["b"], 0, g["c"] - 1), "n": g["c"], "mn": min(g["b"], last), "mx": max(g["b"], last), "t_lo": g["tau_lo"], "t_hi": g["tau_hi"], "w": g["eps_v"] * g["c"]}
        return encoding.py_segment_hash(sid, item["idx"], g), alpha
    r = item["rec"]
    return encoding.py_record_hash(sid, item["idx"], r), {"s": r["v"], "n": 1, "mn": r["v"], "mx": r["v"], "t_lo": r["t"], "t_hi": r["t"], "w": 0}


def check_anchor(anchor: dict | None, sid: str) -> None:
    if anchor is None or anchor["sid"] != sid or encoding.py_anchor_digest(anchor) != anchor["digest"]:
        raise Rejected("anchor")


def check_covering(query: dict, items: list[dict], n: int, f: int, half_open: bool = False, extent: bool = True) -> None:
    """All parts tile 0..n-1; window parts are contiguous; what lies beside them is outside; what they hold is inside."""
    spans = []
    for x in items:
        if not (0 <= x["lvl"] <= cover.depth_of(n, f) and 0 <= x["idx"] < _width(x["lvl"], n, f)):
            raise Rejected("covering")
        if x["role"] in ("edge", "record") and (x["lvl"] or (x.get("rec") is None and x.get("seg") is None)):
            raise Rejected("covering")
        lo = x["idx"] * f ** x["lvl"]
        spans.append((lo, min(lo + f ** x["lvl"], n) - 1, x))
    spans.sort(key=lambda s: s[0])
    at = 0
    for lo, hi, _ in spans:
        if lo != at:
            raise Rejected("covering")
        at = hi + 1
    if at != n:
        raise Rejected("covering")
    inner = [s for s in spans if s[2]["role"] in ("cover", "record")]
    edges = [s for s in spans if s[2]["role"] == "edge"]
    if any(b[0] != a[1] + 1 for a, b in zip(inner, inner[1:])):
        raise Rejected("covering")
    t_s, t_e = query["t_s"], query["t_e"]
    slack = 1 if half_open else 0  # extents of segments end one after their last instant

    def times(x: dict) -> tuple[int, int]:
        if x.get("seg") is not None:
            return x["seg"]["tau_lo"], x["seg"]["tau_hi"]
        if x.get("rec") is not None:
            return x["rec"]["t"], x["rec"]["t"]
        return x["alpha"]["t_lo"], x["alpha"]["t_hi"]

    if inner:
        lo, hi = inner[0][0], inner[-1][1]
        left, right = [e for e in edges if e[1] == lo - 1], [e for e in edges if e[0] == hi + 1]
    else:
        if not edges and n:
            raise Rejected("covering")
        if len(edges) == 2 and edges[1][0] != edges[0][1] + 1:
            raise Rejected("covering")
        if half_open:
            left = right = edges
        else:
            left = [e for e in edges if times(e[2])[1] < t_s]
            right = [e for e in edges if times(e[2])[0] > t_e]
            if len(left) + len(right) != len(edges):
                raise Rejected("covering")
        lo = left[-1][1] + 1 if left else 0
        hi = right[0][0] - 1 if right else n - 1
        if not half_open and lo != hi + 1:
            raise Rejected("covering")
    if half_open:
        # what isn't opened or folded must not overlap the window
        for x in (s[2] for s in spans if s[2]["role"] == "sibling"):
            a, b = times(x)
            if a <= t_e and b > t_s:
                raise Rejected("covering")
        bad_edge = False
    else:
        bad_edge = (lo > 0 and not (left and times(left[-1][2])[1] < t_s)) or (hi < n - 1 and not (right and times(right[0][2])[0] > t_e))
    if bad_edge:
        raise Rejected("covering")
    for s in inner if extent else ():
        a, b = times(s[2])
        if a < t_s or b - slack > t_e:
            raise Rejected("covering")


def check_root(items: list[dict], sid: str, n: int, f: int, root: str, alpha: str) -> int:
    """Rebuilds the root from the parts; returns the number of hashes."""
    level: dict[int, tuple[str, dict]] = {}
    by_level: dict[int, list[dict]] = {}
    hashes = 0
    for x in items:
        by_level.setdefault(x["lvl"], []).append(x)
    for lvl in range(cover.depth_of(n, f) + 1):
        for x in by_level.get(lvl, ()):
            if x["idx"] in level:
                raise Rejected("root")
            if x.get("rec") is not None or x.get("seg") is not None:
                level[x["idx"]] = _leaf(x, sid)
                hashes += 1
            else:
                level[x["idx"]] = (x["eta"], x["alpha"])
        if lvl == cover.depth_of(n, f):
            break
        above: dict[int, tuple[str, dict]] = {}
        for up in {i // f for i in level}:
            kids = [level.get(i) for i in range(up * f, min(up * f + f, _width(lvl, n, f)))]
            if any(k is None for k in kids):
                raise Rejected("root")
            a = [k[1] for k in kids]
            folded = {"s": sum(x["s"] for x in a), "n": sum(x["n"] for x in a), "mn": min(x["mn"] for x in a), "mx": max(x["mx"] for x in a), "t_lo": a[0]["t_lo"], "t_hi": max(x["t_hi"] for x in a), "w": sum(x["w"] for x in a)}
            above[up] = (encoding.py_node_hash(kids), folded)
            hashes += 1
        level = above
    if set(level) != {0} or level[0][0] != root or encoding.py_alpha_text(level[0][1]) != alpha:
        raise Rejected("root")
    return hashes


def _answer(query: dict, proof: list[dict] | None, anchor: dict | None, seg: bool, extent: bool = True) -> Verdict:
    try:
        check_anchor(anchor, query["sid"])
        items = [plain(x) for x in proof or []]
        n, root, alpha = (anchor["seg_n"], anchor["seg_root"], anchor["seg_alpha"]) if seg else (anchor["raw_n"], anchor["raw_root"], anchor["raw_alpha"])
        f = anchor["fanout"]
        check_covering(query, items, n, f, half_open=seg, extent=extent)
        hashes = check_root(items, query["sid"], n, f, root, alpha)
    except Rejected as r:
        return Verdict(False, str(r))
    except (KeyError, TypeError, AttributeError, ValueError, ZeroDivisionError):
        return Verdict(False, "covering")
    out = Verdict(True, "ok", hashes=hashes)
    if seg:
        p = lines.Pieces()
        for x in items:
            if x["role"] == "cover":
                p.add_node(x["alpha"] if x.get("seg") is None else _leaf(x, query["sid"])[1])
            elif x["role"] == "record":
                p.add_segment(x["seg"], query["t_s"], query["t_e"])
            elif x["role"] == "edge":
                p.add_segment(x["seg"], query["t_s"], query["t_e"])
        out.pieces = p
        return out
    inside = [x["alpha"] if x["role"] == "cover" else _leaf(x, query["sid"])[1] for x in items if x["role"] in ("cover", "record")]
    out.s, out.n = sum(a["s"] for a in inside), sum(a["n"] for a in inside)
    if inside:
        out.mn, out.mx = min(a["mn"] for a in inside), max(a["mx"] for a in inside)
    out.records = [{"pos": x["idx"], **x["rec"]} for x in sorted(items, key=lambda x: x["idx"]) if x["role"] == "record"]
    return out


def verify(query: dict, proof: list[dict] | None, anchor: dict | None, claimed: dict | None = None, extent: bool = True) -> Verdict:
    """Exact aggregate: covering, root, fold.  ``claimed`` is the server's answer, if it sent one.  ``extent=False``
    leaves out the check of cover times and is kept as a negative control only."""
    v = _answer(query, proof, anchor, False, extent)
    if v.accepted and claimed is not None and any(claimed[k] != getattr(v, k) for k in ("s", "n", "mn", "mx") if k in claimed):
        return Verdict(False, "fold", hashes=v.hashes)
    return v


def verify_tagged(query: dict, proof: list[dict] | None, anchor: dict | None, predicate: Callable[[dict], bool]) -> Verdict:
    """Range proof first; the tag filter runs on verified records only."""
    v = _answer(query, proof, anchor, False)
    if v.accepted:
        rows = [r for r in v.records if predicate(dict(r["tags"] or {}))]
        v.records, v.n, v.s = rows, len(rows), sum(r["v"] for r in rows)
        v.mn, v.mx = (min(r["v"] for r in rows), max(r["v"] for r in rows)) if rows else (None, None)
    return v


AGGREGATES = ("SUM", "COUNT", "MIN", "MAX", "AVG")


def verify_approx(query: dict, proof: list[dict] | None, anchor: dict | None, reported: dict | None = None, cap: int | None = None, bound: str = "cap") -> tuple[Verdict, dict[str, tuple]]:
    """Segment proof, then intervals that the client derives itself.  ``reported`` (per aggregate) and ``cap`` are what
    the server claims; either must equal what the client derives.  The slack of extremes is the anchored cap, or, with
    ``bound="opened"``, the largest bound among the opened segments, which needs a proof that folds none."""
    v = _answer(query, proof, anchor, True)
    if not v.accepted:
        return v, {}
    if cap is not None and cap != anchor["cap"]:
        return Verdict(False, "anchor"), {}
    if bound == "opened" and any(x["role"] == "cover" and x.get("seg") is None for x in proof or []):
        return Verdict(False, "covering"), {}
    nonneg = int(anchor["raw_alpha"].split(":")[2]) >= 0
    out = {f: lines.bounds(v.pieces, f, anchor["cap"] if bound == "cap" else v.pieces.eps, nonneg) for f in AGGREGATES}
    if reported is not None and any(tuple(reported[f]) != out[f] for f in reported):
        return Verdict(False, "interval"), {}
    return v, out


def verify_approx_range(query: dict, proof: list[dict] | None, anchor: dict | None) -> tuple[Verdict, list[dict]]:
    """Range retrieval over segments: from the proof alone, the records that can lie in the window, each with its position
    and the intervals that hold its value and time (rounded outwards); ``certain`` says that it does lie in the window."""
    v = _answer(query, proof, anchor, True)
    if not v.accepted:
        return v, []
    f, at, out = anchor["fanout"], 0, []
    for x in sorted((plain(x) for x in proof or []), key=lambda x: x["idx"] * f ** x["lvl"]):
        if x.get("seg") is None:
            if x["role"] == "cover":
                return Verdict(False, "covering"), []
            at += x["alpha"]["n"]
            continue
        g = x["seg"]
        r = lines.resolve(g, query["t_s"], query["t_e"])
        for p in range(r.q0, r.q1 + 1):
            y, t = g["a"] * p + g["b"], g["mu"] * p + g["beta"]
            t_lo, t_hi = g["tau_lo"] + (t - g["eps_t"]) // lines.T, g["tau_lo"] - (-(t + g["eps_t"]) // lines.T)
            out.append({"pos": at + p, "v_lo": (y - g["eps_v"]) // lines.V, "v_hi": -(-(y + g["eps_v"]) // lines.V), "t_lo": max(t_lo, g["tau_lo"]), "t_hi": min(t_hi, g["tau_hi"] - 1), "certain": r.p0 <= p <= r.p1})
        at += g["c"]
    return v, out


def verify_paths(query: dict, entries: list[dict] | None, anchor: dict | None) -> Verdict:
    """The baseline of one path per record: every record (pos, rec, path) is led to the root by its own siblings; positions
    must be contiguous and end at a record outside the window or at the stream's end."""
    try:
        check_anchor(anchor, query["sid"])
        n, f, hashes = anchor["raw_n"], anchor["fanout"], 0
        rows = sorted(entries or [], key=lambda e: e["pos"])
        for e in rows:
            at, (eta, alpha) = e["pos"], _leaf({"idx": e["pos"], "rec": e["rec"]}, query["sid"])
            hashes += 1
            path: dict[int, list[dict]] = {}
            for x in e["path"] or []:
                path.setdefault(x["lvl"], []).append(plain(x))
            for lvl in range(cover.depth_of(n, f)):
                kids = sorted([(at, (eta, alpha)), *[(x["idx"], (x["eta"], x["alpha"])) for x in path.get(lvl, [])]], key=lambda k: k[0])
                first = at // f * f
                if [k[0] for k in kids] != list(range(first, min(first + f, _width(lvl, n, f)))):
                    raise Rejected("root")
                a = [k[1][1] for k in kids]
                alpha = {"s": sum(x["s"] for x in a), "n": sum(x["n"] for x in a), "mn": min(x["mn"] for x in a), "mx": max(x["mx"] for x in a), "t_lo": a[0]["t_lo"], "t_hi": max(x["t_hi"] for x in a), "w": sum(x["w"] for x in a)}
                eta, at, hashes = encoding.py_node_hash([k[1] for k in kids]), at // f, hashes + 1
            if at or eta != anchor["raw_root"] or encoding.py_alpha_text(alpha) != anchor["raw_alpha"]:
                raise Rejected("root")
        at = [e["pos"] for e in rows]
        if not rows or at != list(range(at[0], at[0] + len(at))):
            raise Rejected("covering")
        if at[0] > 0 and rows[0]["rec"]["t"] >= query["t_s"] or at[-1] < n - 1 and rows[-1]["rec"]["t"] <= query["t_e"]:
            raise Rejected("covering")
    except Rejected as r:
        return Verdict(False, str(r))
    except (KeyError, TypeError, AttributeError, ValueError):
        return Verdict(False, "covering")
    v = [e["rec"]["v"] for e in rows if query["t_s"] <= e["rec"]["t"] <= query["t_e"]]
    return Verdict(True, "ok", s=sum(v), n=len(v), mn=min(v, default=None), mx=max(v, default=None), hashes=hashes)


SCHEMA = "qid long, accepted boolean, reason string, s long, n long, mn long, mx long, hashes long"


def batch_verify(wire: DataFrame, claims: bool = False) -> DataFrame:
    """Verdicts for rows of ``to_wire``; a proof is tens of rows, so rows go through Arrow one proof at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for r in b.to_pylist():
                v = verify(r, r["proof"], r["anchor"], {k: r[f"claim_{k}"] for k in ("s", "n", "mn", "mx")} if claims else None)
                rows.append({"qid": r["qid"], "accepted": v.accepted, "reason": v.reason, "s": v.s, "n": v.n, "mn": v.mn, "mx": v.mx, "hashes": v.hashes})
            yield pa.RecordBatch.from_pylist(rows, schema=pa.schema([("qid", pa.int64()), ("accepted", pa.bool_()), ("reason", pa.string()), *[(c, pa.int64()) for c in ("s", "n", "mn", "mx", "hashes")]]))

    return wire.mapInArrow(run, SCHEMA)


def _in_arrow(wire: DataFrame, schema: str, rows_of: Callable[[dict], list[dict]]) -> DataFrame:
    """Rows that a plain function makes of each row of a wire table."""
    kinds = {"long": pa.int64(), "string": pa.string(), "boolean": pa.bool_(), "double": pa.float64(), "map<string,string>": pa.map_(pa.string(), pa.string())}
    fields = pa.schema([(x.split()[0], kinds[x.split()[1]]) for x in schema.split(", ")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_pylist([x for r in b.to_pylist() for x in rows_of(r)], schema=fields)

    return wire.mapInArrow(run, schema)


def batch_records(wire: DataFrame) -> DataFrame:
    """The records of verified range proofs, to be filtered by any columns; a rejected or empty answer is one row without
    a position."""

    def rows(r: dict) -> list[dict]:
        v = verify(r, r["proof"], r["anchor"])
        base = {"qid": r["qid"], "accepted": v.accepted, "reason": v.reason}
        return [base | {"pos": x["pos"], "t": x["t"], "v": x["v"], "tags": list(dict(x["tags"] or {}).items())} for x in v.records] or [base]

    return _in_arrow(wire, "qid long, accepted boolean, reason string, pos long, t long, v long, tags map<string,string>", rows)


def batch_approx_range(wire: DataFrame) -> DataFrame:
    """One row per record that can lie in the window, rebuilt from the proof; a rejected or empty answer is one row
    without a position."""

    def rows(r: dict) -> list[dict]:
        v, found = verify_approx_range(r, r["proof"], r["anchor"])
        base = {"qid": r["qid"], "accepted": v.accepted, "reason": v.reason}
        return [base | x for x in found] or [base]

    return _in_arrow(wire, "qid long, accepted boolean, reason string, pos long, v_lo long, v_hi long, t_lo long, t_hi long, certain boolean", rows)


def batch_paths(wire: DataFrame) -> DataFrame:
    def rows(r: dict) -> list[dict]:
        v = verify_paths(r, r["entries"], r["anchor"])
        return [{"qid": r["qid"], "accepted": v.accepted, "reason": v.reason, "s": v.s, "n": v.n, "hashes": v.hashes}]

    return _in_arrow(wire, "qid long, accepted boolean, reason string, s long, n long, hashes long", rows)


def batch_tagged(wire: DataFrame, predicate: Callable[[dict], bool]) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for r in b.to_pylist():
                v = verify_tagged(r, r["proof"], r["anchor"], predicate)
                rows.append({"qid": r["qid"], "accepted": v.accepted, "reason": v.reason, "s": v.s, "n": v.n, "mn": v.mn, "mx": v.mx, "hashes": v.hashes})
            yield pa.RecordBatch.from_pylist(rows, schema=pa.schema([("qid", pa.int64()), ("accepted", pa.bool_()), ("reason", pa.string()), *[(c, pa.int64()) for c in ("s", "n", "mn", "mx", "hashes")]]))

    return wire.mapInArrow(run, SCHEMA)


APPROX = "qid long, f string, accepted boolean, reason string, lo double, hi double, lo_floor long, hi_ceil long, sure long, undecided long, k_formula long, dv double, dt double"


def batch_approx(wire: DataFrame, bound: str = "cap") -> DataFrame:
    """One row per query and aggregate: the derived interval."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split()[0] for x in APPROX.split(", ")]
        kinds = [{"long": pa.int64(), "string": pa.string(), "boolean": pa.bool_(), "double": pa.float64()}[x.split()[1]] for x in APPROX.split(", ")]
        for b in batches:
            rows: list[dict[str, Any]] = []
            for r in b.to_pylist():
                v, found = verify_approx(r, r["proof"], r["anchor"], bound=bound)
                p = v.pieces
                for f in AGGREGATES:
                    lo, hi = found.get(f, (None, None))
                    row = {"qid": r["qid"], "f": f, "accepted": v.accepted, "reason": v.reason, "lo": None if lo is None else float(lo), "hi": None if hi is None else float(hi), "lo_floor": None if lo is None else lo.__floor__(), "hi_ceil": None if hi is None else hi.__ceil__()}
                    row |= {"sure": p.sure, "undecided": p.undecided, "k_formula": p.formula, "dv": p.dv / lines.V, "dt": p.dt / lines.V} if p else dict.fromkeys(("sure", "undecided", "k_formula", "dv", "dt"))
                    rows.append(row)
            yield pa.RecordBatch.from_pylist(rows, schema=pa.schema(list(zip(names, kinds))))

    return wire.mapInArrow(run, APPROX)
