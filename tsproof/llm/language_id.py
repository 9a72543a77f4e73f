"""Language identification by prediction by partial matching.

For every language a context tree over bytes (contexts of up to three bytes) is counted on a bounded sample:
``per_lang`` documents per language, chosen by a hash of the id, with texts of at most ``longest`` characters.  The
probability of a byte after a context is count / (n + distinct); an unseen byte pays the escape distinct / (n + distinct)
and is coded by the next shorter context, down to a uniform byte.  The statistics are frozen, so the exact code length of
each (context, byte) is a constant: trees become one table from context node and byte to a code length per language, and
scoring a text is a sum of table rows.  Every context of the sample has a node; ``max_nodes`` can bound those of three
bytes (the most frequent stay, the others share the node of their last two bytes) where a sample has a very large alphabet.

Every document is scored on its whole text in one narrow pass.  The language with the shortest code wins (ties to the
smaller name); score is its posterior under equal priors.

Defined cases: null texts and texts without a letter give ``und`` with score 0; so does a model without languages; null
langs aren't learned; other columns are never read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tsproof.llm import shared, textkit

PAD = 32


class Model:
    """symbol: byte -> symbol; node: code of three symbols -> node; bits: (nodes * symbols, languages)."""

    def __init__(self, langs: list[str], symbol: np.ndarray, node: np.ndarray, bits: np.ndarray):
        self.langs, self.symbol, self.node, self.bits = langs, symbol, node, bits

    def code_lengths(self, arr: pa.Array) -> np.ndarray:
        """(rows, languages) code lengths in bits."""
        data, offsets = textkit.buffers(arr)
        n, size = len(offsets) - 1, np.diff(offsets)
        a = int(self.symbol.max()) + 1
        spread = np.full(len(data) + 3 * n, self.symbol[PAD], np.int32)
        starts = offsets[:-1] + 3 * np.arange(n)
        at = np.arange(len(data)) + np.repeat(3 * (np.arange(n) + 1), size)
        spread[at] = self.symbol[textkit._LOWER[data]]
        out = np.zeros((n, len(self.langs)))
        if not len(data):
            return out
        code = (spread[:-3] * a + spread[1:-2]) * a + spread[2:-1]
        row = self.node[code] * a + spread[3:]
        cost = self.bits[row[at - 3]]
        some = np.flatnonzero(size)
        out[some] = np.add.reduceat(cost, (starts - 3 * np.arange(n))[some], axis=0, dtype=np.float64)
        return out


def _counts(texts: list[bytes], symbol: np.ndarray, a: int) -> list[np.ndarray]:
    """Counts of (context, symbol) for contexts of 0 to 3 symbols, as dense arrays or (codes, counts)."""
    total = [np.zeros(a ** (k + 1), np.int64) for k in range(3)]
    codes = []
    for t in texts:
        s = symbol[textkit._LOWER[np.frombuffer(b"   " + t, np.uint8)]].astype(np.int64)
        c = s[3:]
        code = c
        for k in range(4):
            if k:
                code = code + s[3 - k : len(s) - k] * a**k
            if k < 3:
                total[k] += np.bincount(code, minlength=a ** (k + 1))
            else:
                codes.append(code)
    deep = np.unique(np.concatenate(codes) if codes else np.zeros(0, np.int64), return_counts=True)
    return [*total, deep]


def fit(samples: dict[str, list[bytes]], max_nodes: int | None = None) -> Model:
    langs = sorted(samples)
    seen = np.zeros(256, bool)
    seen[PAD] = True
    for texts in samples.values():
        for t in texts:
            seen[textkit._LOWER[np.frombuffer(t, np.uint8)]] = True
    symbol = np.zeros(256, np.int32)  # 0: bytes no sample has
    symbol[seen] = np.arange(1, int(seen.sum()) + 1)
    a = int(seen.sum()) + 1
    counted = {lang: _counts(samples[lang], symbol, a) for lang in langs}

    together: dict[str, np.ndarray] = {}
    codes = np.concatenate([counted[x][3][0] for x in langs] or [np.zeros(0, np.int64)]) // a
    weights = np.concatenate([counted[x][3][1] for x in langs] or [np.zeros(0, np.int64)])
    context, inverse = np.unique(codes, return_inverse=True)
    order = np.argsort(-np.bincount(inverse, weights, minlength=len(context)), kind="stable")[:max_nodes]
    deep = np.sort(context[order])
    pairs = np.flatnonzero(sum((counted[x][2].reshape(a * a, a).sum(1) for x in langs), np.zeros(a * a, np.int64)))
    # nodes: single symbols, then pairs, then triples; a context without a node has that of its longest suffix
    by_pair = np.tile(np.arange(a, dtype=np.int32), a)
    by_pair[pairs] = a + np.arange(len(pairs))
    node = np.tile(by_pair, a)
    node[deep] = a + len(pairs) + np.arange(len(deep))
    bits = np.zeros((a + len(pairs) + len(deep), a, len(langs)), np.float32)

    def level(counts: np.ndarray, shorter: np.ndarray) -> np.ndarray:
        n, u = counts.sum(-1, keepdims=True), (counts > 0).sum(-1, keepdims=True)
        with np.errstate(divide="ignore", invalid="ignore"):
            cost = np.where(counts > 0, -np.log2(counts / (n + u)), shorter - np.log2(u / (n + u)))
        return np.where(n > 0, cost, shorter)

    for i, lang in enumerate(langs):
        c = counted[lang]
        zero = level(c[0][None, :], np.full((1, a), 8.0))
        one = level(c[1].reshape(a, a), np.broadcast_to(zero, (a, a)))
        two = level(c[2].reshape(a * a, a)[pairs], one[pairs % a])
        bits[:a, :, i], bits[a : a + len(pairs), :, i] = one, two
        full = np.zeros((len(deep), a), np.int64)
        at = np.searchsorted(deep, c[3][0] // a)
        hit = (at < len(deep)) & (deep[np.minimum(at, max(len(deep) - 1, 0))] == c[3][0] // a) if len(deep) else np.zeros(len(at), bool)
        full[at[hit], c[3][0][hit] % a] = c[3][1][hit]
        bits[a + len(pairs) :, :, i] = level(full, two[by_pair[deep % (a * a)] - a]) if len(deep) else 0
    return Model(langs, symbol, node, bits.reshape(len(bits) * a, len(langs)))


def train(docs: DataFrame, held_out=None, per_lang: int = 500, longest: int = 20_000, max_nodes: int | None = None) -> Model:
    rows = docs.where("doc_id is not null and text is not null and lang is not null").where(F.length("text").between(1, longest))
    if held_out is not None:
        rows = rows.where(~held_out)
    # only ids whose hash lies in a share that yields about 4 * per_lang of a language are ranked, at any size of the corpus
    spread = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 40))
    share = rows.groupBy("lang").agg((F.lit(float(1 << 40)) * (4 * per_lang + 100) / F.count("*")).alias("_below"))
    near = rows.select("doc_id", "lang", spread.alias("_h")).join(F.broadcast(share), "lang").where("_h < _below")
    order = Window.partitionBy("lang").orderBy("_h", "doc_id")
    ids = near.withColumn("_r", F.row_number().over(order)).where(F.col("_r") <= per_lang).select("doc_id", "lang").distinct()
    picked = rows.select("doc_id", "lang", "text").join(F.broadcast(ids), ["doc_id", "lang"])
    samples: dict[str, list[bytes]] = {}
    for lang, text in picked.select("lang", "text").toPandas().sort_values(["lang", "text"]).itertuples(index=False):
        samples.setdefault(lang, []).append(text.encode())
    return fit(samples, max_nodes)


def _predict(model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = Model(*model.value)
        names = np.array([*m.langs, "und"], object)
        for batch in batches:
            for b in textkit.pieces(batch, "text", 2 << 20):
                letters = np.asarray(b.column(1).to_pylist(), bool)
                bits = m.code_lengths(b.column(b.schema.get_field_index("text")))
                if m.langs:
                    best = bits.argmin(axis=1)
                    odds = np.exp2(np.maximum(bits.min(axis=1, keepdims=True) - bits, -1000)).sum(axis=1)
                else:
                    best, odds, letters = np.zeros(b.num_rows, int), np.ones(b.num_rows), np.zeros(b.num_rows, bool)
                pred = names[np.where(letters, best, len(m.langs))]
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(pred.tolist(), pa.string()), pa.array(np.where(letters, 1 / odds, 0.0))], names=["doc_id", "lang_pred", "score"])

    return run


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, lang_pred, score for every row."""
    sent = docs.sparkSession.sparkContext.broadcast((model.langs, model.symbol, model.node, model.bits))
    letter = F.coalesce(F.col("text").rlike(r"\p{L}"), F.lit(False)).alias("_letter")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), letter, "text").mapInArrow(_predict(sent), "doc_id long, lang_pred string, score double")
