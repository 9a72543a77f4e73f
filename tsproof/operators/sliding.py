"""Sequences of overlapping windows: what each slide must ship, and the client that keeps what it has verified."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tsproof.operators import client


def delta_proofs(vo: DataFrame, windows: DataFrame, cache: str = "all") -> DataFrame:
    """Adds ``fresh``: whether a part must be shipped with its slide.  ``all``: everything the client has authenticated
    stays known, so a part is shipped once per sequence; ``current``: only the last window's parts are known."""
    rows = vo.join(windows.select("qid", "seq_id", "i"), "qid")
    opened = F.col("rec").isNotNull()
    w = Window.partitionBy("seq_id", "lvl", "idx", opened).orderBy("i")
    if cache == "all":
        return rows.withColumn("fresh", F.row_number().over(w) == 1)
    return rows.withColumn("fresh", F.coalesce(F.lag("i").over(w) != F.col("i") - 1, F.lit(True)))


class SlidingClient:
    """Keeps verified parts of one stream under one anchor; each slide brings keys of all parts, content of new ones."""

    def __init__(self, anchor: dict, keep: str = "all"):
        self.anchor, self.keep, self.known = anchor, keep, {}

    def slide(self, query: dict, parts: list[dict]) -> client.Verdict:
        full = []
        for x in parts:
            key = (x["lvl"], x["idx"], bool(x["opened"]))
            content = x if x["fresh"] else self.known.get(key)
            if content is None:
                return client.Verdict(False, "covering")
            full.append({**content, "role": x["role"], "lvl": x["lvl"], "idx": x["idx"]})
        verdict = client.verify(query, full, self.anchor)
        if verdict.accepted:
            if self.keep == "current":
                self.known = {}
            self.known |= {(x["lvl"], x["idx"], x.get("rec") is not None): x for x in full}
        return verdict


def verify_sequence(vo: DataFrame, windows: DataFrame, anchors: DataFrame, cache: str = "all") -> DataFrame:
    """Verdicts of a client per sequence: sequences run in parallel, slides of one in order."""
    import pyarrow as pa

    rows = delta_proofs(vo, windows, cache)
    content = lambda c: F.when(F.col("fresh"), F.col(c)).alias(c)
    part = F.struct("role", "lvl", "idx", "fresh", F.col("rec").isNotNull().alias("opened"), content("eta"), content("alpha"), content("rec"))
    slides = rows.groupBy("seq_id", "i", "qid").agg(F.collect_list(part).alias("parts")).join(windows.select("qid", "sid", "t_s", "t_e"), "qid")
    seqs = slides.groupBy("seq_id", "sid").agg(F.collect_list(F.struct("i", "qid", "t_s", "t_e", "parts")).alias("slides"))
    seqs = seqs.join(anchors.select("sid", F.struct(*anchors.columns).alias("anchor")), "sid")

    def run(batches):
        for b in batches:
            out = []
            for r in b.to_pylist():
                c = SlidingClient(r["anchor"], cache)
                for s in sorted(r["slides"], key=lambda x: x["i"]):
                    v = c.slide({"sid": r["sid"], "t_s": s["t_s"], "t_e": s["t_e"]}, s["parts"])
                    out.append({"seq_id": r["seq_id"], "i": s["i"], "accepted": v.accepted, "s": v.s, "n": v.n})
            yield pa.RecordBatch.from_pylist(out, schema=pa.schema([("seq_id", pa.int64()), ("i", pa.int64()), ("accepted", pa.bool_()), ("s", pa.int64()), ("n", pa.int64())]))

    return seqs.mapInArrow(run, "seq_id long, i long, accepted boolean, s long, n long")
