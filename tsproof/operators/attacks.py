"""Forgeries of proofs and answers, and the check each should fall to."""

from __future__ import annotations

import copy
from fractions import Fraction

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tsproof.operators import client

#: kind -> checks that may catch it (fixed values).
EXACT = {
    "sum_raised": ("root",), "hash_replaced": ("root",), "node_dropped": ("covering",), "outer_altered": ("root",), "extreme_reduced": ("root",),
    "wrong_total": ("fold",), "other_window": ("covering",), "other_stream": ("covering", "root"), "stretched_cover": ("covering",), "older_height": ("covering", "root"),
}
APPROX = {"line_moved": ("root",), "bound_halved": ("root",), "segment_dropped": ("covering",), "interval_tightened": ("interval",), "cap_halved": ("anchor",)}
RANGE = {"record_dropped": ("covering",), "record_altered": ("root",), "record_fabricated": ("covering",)}
APPROX_RANGE = {"range_line_moved": ("root",), "range_segment_dropped": ("covering",)}


def _first(proof: list[dict], *roles: str) -> dict:
    return next(x for role in roles for x in proof if x["role"] == role)


def forge_exact(kind: str, query: dict, proof: list[dict], anchor: dict) -> client.Verdict:
    """``query`` may bring ``other_proof`` (of another stream) and ``older_proof`` (of the stream's past)."""
    q, p, a = dict(query), [client.plain(copy.deepcopy(x)) for x in proof], dict(anchor)
    honest = client.verify(q, p, a)
    claim = {"s": honest.s, "n": honest.n}
    node = _first(p, "cover")
    if kind == "sum_raised":
        node["alpha"]["s"] += 100
        claim["s"] += 100
    elif kind == "hash_replaced":
        node["eta"] = "0" * 64
    elif kind == "node_dropped":
        p.remove(node)
        claim = {"s": claim["s"] - node["alpha"]["s"], "n": claim["n"] - node["alpha"]["n"]}
    elif kind == "outer_altered":
        _first(p, "edge")["rec"]["v"] += 1
    elif kind == "extreme_reduced":
        node["alpha"]["mx"] -= 1
    elif kind == "wrong_total":
        claim["s"] += 1
    elif kind == "other_window":
        q["t_s"], q["t_e"] = q["t_s"] - (q["t_e"] - q["t_s"]) - 10**7, q["t_s"] - 1
    elif kind == "other_stream":  # an honest proof of another stream's window
        p, claim = query["other_proof"], None
    elif kind == "stretched_cover":  # the record after the window, true as it is, is passed off as inside
        last = max((x for x in p if x["role"] == "edge"), key=lambda x: x["idx"])
        last["role"] = "record"
        claim = {"s": claim["s"] + last["rec"]["v"], "n": claim["n"] + 1}
    elif kind == "older_height":  # an honest proof of the past held against the later anchor
        p, claim = query["older_proof"], None
    return client.verify(q, p, a, claim)


def forge_range(kind: str, query: dict, proof: list[dict], anchor: dict) -> client.Verdict:
    p = [client.plain(copy.deepcopy(x)) for x in proof]
    row = _first(p, "record")
    if kind == "record_dropped":
        p.remove(row)
    elif kind == "record_fabricated":
        p.append(copy.deepcopy(row) | {"rec": row["rec"] | {"v": row["rec"]["v"] + 7, "i": row["rec"]["i"] + 1}})
    else:
        row["rec"]["v"] += 1
    return client.verify(query, p, anchor)


def forge_approx_range(kind: str, query: dict, proof: list[dict], anchor: dict) -> client.Verdict:
    p = [client.plain(copy.deepcopy(x)) for x in proof]
    row = _first(p, "record", "edge")
    if kind == "range_segment_dropped":
        p.remove(row)
    else:
        row["seg"] = dict(row["seg"]) | {"b": row["seg"]["b"] + (1 << 20)}
    return client.verify_approx_range(query, p, anchor)[0]


def forge_approx(kind: str, query: dict, proof: list[dict], anchor: dict) -> client.Verdict:
    p = [client.plain(copy.deepcopy(x)) for x in proof]
    report, cap = dict(client.verify_approx(query, p, anchor)[1]), None
    seg = _first(p, "edge")
    seg["seg"] = dict(seg["seg"])
    if kind == "line_moved":
        seg["seg"]["b"] += 1 << 20
    elif kind == "bound_halved":
        seg["seg"]["eps_v"] = seg["seg"]["eps_v"] // 2 - 1
    elif kind == "segment_dropped":
        p.remove(_first(p, "cover", "edge"))
    elif kind == "interval_tightened":
        lo, hi = report["SUM"]
        report["SUM"] = (lo + Fraction(1, 2), hi - Fraction(1, 2))
    elif kind == "cap_halved":
        cap = anchor["cap"] // 2 - 1
    return client.verify_approx(query, p, anchor, report, cap)[0]


def tamper(wire: DataFrame, kinds: dict[str, tuple[str, ...]], forge) -> DataFrame:
    """(stream, kind, attempts, rejected, caught_as_expected) over rows of a wire table."""

    def run(batches):
        for b in batches:
            out = []
            for r in b.to_pylist():
                for kind, expected in kinds.items():
                    v = forge(kind, r, r["proof"], r["anchor"])
                    out.append({"stream": r["stream"], "kind": kind, "rejected": not v.accepted, "expected": v.reason in expected})
            yield pa.RecordBatch.from_pylist(out, schema=pa.schema([("stream", pa.string()), ("kind", pa.string()), ("rejected", pa.bool_()), ("expected", pa.bool_())]))

    # a wire table is small in bytes and would end in one task
    spread = wire.repartition(int(wire.sparkSession.conf.get("spark.sql.shuffle.partitions")), "qid")
    rows = spread.mapInArrow(run, "stream string, kind string, rejected boolean, expected boolean")
    return rows.groupBy("stream", "kind").agg(F.count("*").alias("attempts"), F.count_if("rejected").alias("rejected"), F.count_if("expected").alias("as_expected"))
