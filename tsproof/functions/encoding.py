"""Commitments: canonical texts under SHA-256, as columns and as plain Python for clients.

Prefixes keep kinds of text apart: L record leaf, G segment leaf, N inner node, A anchor.  The aggregate of a node is
(s, n, mn, mx, t_lo, t_hi, w): sum, count, extremes, time extent and, for segments, value slack.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

ALPHA = ("s", "n", "mn", "mx", "t_lo", "t_hi", "w")
NODE = "struct<s:decimal(38,0),n:bigint,mn:bigint,mx:bigint,t_lo:bigint,t_hi:bigint,w:decimal(38,0),eta:string>"
SEGMENT = ("tau_lo", "tau_hi", "a", "b", "mu", "beta", "eps_v", "eps_t", "c")


def _text(c: Column) -> Column:
    return F.coalesce(c.cast("string"), F.lit("~"))


def tags_text(tags: Column) -> Column:
    pairs = F.array_sort(F.transform(F.map_entries(tags), lambda e: F.concat(e["key"], F.lit("="), F.coalesce(e["value"], F.lit("~")))))
    return F.coalesce(F.array_join(pairs, ","), F.lit(""))


def record_hash() -> Column:
    return F.sha2(F.concat_ws("|", F.lit("L"), *[_text(F.col(c)) for c in ("sid", "pos", "t", "height", "i", "v")], tags_text(F.col("tags"))), 256)


def segment_hash() -> Column:
    return F.sha2(F.concat_ws("|", F.lit("G"), F.col("sid"), *[_text(F.col(c)) for c in ("j", *SEGMENT)]), 256)


def child_text(node: Column) -> Column:
    """Hash and aggregate of a child, as its parent binds them; null for a missing child."""
    parts = F.concat_ws("|", node["eta"], F.concat_ws(":", *[_text(node[c]) for c in ALPHA]))
    return F.when(node.isNotNull(), parts)


def node_hash(children: list[Column]) -> Column:
    return F.sha2(F.concat_ws("|", F.lit("N"), *[child_text(c) for c in children]), 256)


def sha(text: str) -> str:
    return hashlib.sha256(text.encode()).hexdigest()


def py_record_hash(sid: str, pos: int, r: dict) -> str:
    tags = ",".join(sorted(f"{k}={'~' if x is None else x}" for k, x in dict(r["tags"] or {}).items()))
    return sha("|".join(["L", sid, *["~" if x is None else str(x) for x in (pos, r["t"], r["height"], r["i"], r["v"])], tags]))


def py_segment_hash(sid: str, j: int, g: dict) -> str:
    return sha("|".join(["G", sid, str(j), *[str(g[c]) for c in SEGMENT]]))


def py_alpha_text(alpha: dict) -> str:
    return ":".join(str(alpha[c]) for c in ALPHA)


def py_node_hash(children: list[tuple[str, dict]]) -> str:
    return sha("|".join(["N", *[f"{eta}|{py_alpha_text(alpha)}" for eta, alpha in children]]))


ANCHOR = ("sid", "height", "fanout", "raw_n", "raw_root", "raw_alpha", "seg_n", "seg_root", "seg_alpha", "cap")


def py_anchor_digest(a: dict) -> str:
    return sha("|".join(["A", *["~" if a[c] is None else str(a[c]) for c in ANCHOR]]))


def anchor_digest() -> Column:
    return F.sha2(F.concat_ws("|", F.lit("A"), *[_text(F.col(c)) for c in ANCHOR]), 256)
