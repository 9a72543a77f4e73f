"""Toxicity scores from a counterfactual-regularised linear classifier.

Features are the presence of selected words and 5-byte pieces of the lower-cased text.  A bounded sample of labelled rows
(``positives`` + ``negatives`` rows with texts of at most ``longest`` characters, chosen by a hash of the id) fits a
logistic model; rows are weighted so that the sample has the class balance of all labelled rows.  Each sampled text that
names a group also gives counterfactuals in which the group's term is swapped; the squared change of the logit is
penalised, so a neutral mention of a group doesn't move the score.

Every document is scored on its whole text in one narrow pass; nothing is shuffled.

Defined cases: null or blank texts get the score of a text without features; null labels are not learned from; with
contradicting labels for one id the larger counts; without any positive or negative label the score is the share of
positives (0 if there are no labels).  Other columns are never read.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tsproof.llm import shared, textkit

U64 = np.uint64
#: Terms swapped within a pair, for the languages of the corpus (fixed values).
IDENTITIES = (
    ("women", "men"), ("woman", "man"), ("girl", "boy"), ("she", "he"), ("her", "his"), ("mother", "father"),
    ("black", "white"), ("asian", "european"), ("african", "american"), ("arab", "latino"),
    ("muslim", "christian"), ("muslims", "christians"), ("jewish", "buddhist"), ("hindu", "catholic"),
    ("gay", "straight"), ("lesbian", "heterosexual"), ("transgender", "cisgender"),
    ("immigrant", "citizen"), ("immigrants", "citizens"), ("disabled", "abled"), ("old", "young"),
    ("frauen", "männer"), ("frau", "mann"), ("mädchen", "junge"), ("mutter", "vater"), ("muslime", "christen"), ("jude", "hinduist"), ("juden", "hindus"),
    ("schwarze", "weiße"), ("schwule", "heteros"), ("türken", "schweden"), ("ausländer", "inländer"), ("behinderte", "gesunde"), ("flüchtlinge", "nachbarn"),
    ("femmes", "hommes"), ("femme", "homme"), ("fille", "garçon"), ("mère", "père"), ("elle", "il"), ("musulmans", "chrétiens"), ("musulmane", "chrétienne"), ("musulmanes", "chrétiennes"),
    ("juif", "bouddhiste"), ("juifs", "bouddhistes"), ("noirs", "blancs"), ("arabes", "bretons"), ("immigrés", "citoyens"), ("homosexuels", "hétérosexuels"), ("handicapés", "valides"),
    ("mujeres", "hombres"), ("mujer", "hombre"), ("niña", "niño"), ("madre", "padre"), ("ella", "él"), ("musulmán", "cristiano"), ("musulmanas", "cristianas"),
    ("judío", "budista"), ("judíos", "budistas"), ("judía", "católica"), ("negros", "blancos"), ("gitanos", "payos"), ("inmigrantes", "ciudadanos"), ("discapacitados", "sanos"),
)
THRESHOLD = 0.3
_BINS = 1 << 22
_WORD_TAG = U64(1 << 63)


def keys_of(arr: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Feature keys and row numbers, with repeats: words, then 5-byte pieces (white space as blanks)."""
    w = textkit.Words(arr, lower=True)
    words = w.hashes() | _WORD_TAG
    row = np.repeat(np.arange(len(arr)), w.counts())
    n = len(w.data) - 4
    if n <= 0:
        return words, row
    data = np.where((w.data >= 9) & (w.data <= 13), 32, w.data).astype(U64)
    piece = data[:n].copy()
    for i in range(1, 5):
        piece <<= U64(8)
        piece |= data[i : i + n]
    return np.concatenate((words, piece)), np.concatenate((row, _rows_of_pieces(w.offsets, n)))


def _rows_of_pieces(offsets: np.ndarray, n: int) -> np.ndarray:
    """Row of each piece, -1 where it would cross into the next row."""
    row = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
    return np.where(row[:n] == row[4 : 4 + n], row[:n], -1)


class Model:
    """Sorted feature keys, weights, bias and the weight of log text length."""

    def __init__(self, keys: np.ndarray, weights: np.ndarray, bias: float, length: float):
        self.keys, self.weights, self.bias, self.length = keys, weights, bias, length
        self.maybe = np.zeros(_BINS, bool)
        self.maybe[textkit.mix(keys) >> U64(42)] = True

    def present(self, arr: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Distinct (row, feature) pairs."""
        keys, row = keys_of(arr)
        at = np.flatnonzero(self.maybe[_fast(keys)]) if len(self.keys) else np.zeros(0, np.int64)
        keys, row = keys[at], row[at]
        found = np.minimum(np.searchsorted(self.keys, keys), max(len(self.keys) - 1, 0))
        good = (row >= 0) & (self.keys[found] == keys) if len(self.keys) else np.zeros(0, bool)
        pair = np.unique(row[good] * max(len(self.keys), 1) + found[good])
        return pair // max(len(self.keys), 1), pair % max(len(self.keys), 1)

    def scores(self, arr: pa.Array) -> np.ndarray:
        row, feature = self.present(arr)
        z = np.bincount(row, self.weights[feature] if len(row) else None, minlength=len(arr)) if len(row) else np.zeros(len(arr))
        return 1 / (1 + np.exp(-np.clip(z + self.bias + self.length * log_length(arr), -30, 30)))


def _fast(keys: np.ndarray) -> np.ndarray:
    return textkit.mix(keys) >> U64(42)


def log_length(arr: pa.Array) -> np.ndarray:
    return np.log1p(np.diff(textkit.buffers(arr)[1]) / 1000)


def counterfactuals(text: str, identities=IDENTITIES) -> str:
    """The text with every identity term replaced by its counterpart."""
    swap = {a: b for x, y in identities for a, b in ((x, y), (y, x))}
    return re.sub(r"\w+", lambda m: swap.get(m[0].lower(), m[0]), text)


def fit(texts: list[str], labels: np.ndarray, share: float, identities=IDENTITIES, penalty: float = 1.0, features: int = 600, ridge: float = 0.001, steps: int = 400) -> Model:
    """Full-batch fit on the sample; ``share`` is the share of positives among all labelled rows."""
    labels = labels.astype(np.float64)
    pos, neg = labels.sum(), len(labels) - labels.sum()
    if not pos or not neg:
        base = min(max(share, 0.0), 1.0)
        return Model(np.zeros(0, U64), np.zeros(0), float(np.log((base + 1e-9) / (1 - base + 1e-9))), 0.0)
    arr = pa.array(texts, pa.large_string())
    chunks = [arr.slice(i, 200) for i in range(0, len(arr), 200)]
    counts = np.zeros((2, _BINS), np.int32)
    for c, at in zip(chunks, range(0, len(arr), 200), strict=True):
        keys, row = keys_of(c)
        pair = np.unique((row[row >= 0].astype(np.int64) << 22) | _fast(keys[row >= 0]).astype(np.int64))
        y = labels[at + (pair >> 22)].astype(int)
        np.add.at(counts, (y, pair & (_BINS - 1)), 1)
    some = np.flatnonzero(counts.sum(0) >= 4)  # keeps the driver's arrays small
    c1, c0 = counts[1, some].astype(np.float64), counts[0, some].astype(np.float64)
    del counts
    p = (c1 + c0) / len(labels)
    z = (c1 / pos - c0 / neg) / np.sqrt(np.maximum(p * (1 - p), 1e-9) * (1 / pos + 1 / neg))
    best = np.argsort(-z, kind="stable")[:features]
    chosen = np.zeros(_BINS, bool)
    chosen[some[best[z[best] >= 3]]] = True
    named = {w for pair in identities for w in pair}
    terms = textkit.Words(pa.array(sorted(named)), lower=True).hashes() | _WORD_TAG
    chosen[_fast(terms)] = True  # so that the penalty can act on the terms themselves
    keys = np.unique(np.concatenate([np.unique(k[chosen[_fast(k)]]) for k in (keys_of(c)[0] for c in chunks)]))
    model = Model(keys, np.zeros(len(keys)), 0.0, 0.0)

    def matrix(items: list[str]) -> np.ndarray:
        x = np.zeros((len(items), len(keys) + 2), np.float32)
        for i in range(0, len(items), 200):
            part = pa.array(items[i : i + 200], pa.large_string())
            row, f = model.present(part)
            x[i + row, f] = 1
            x[i : i + 200, -1] = log_length(part)
        x[:, -2] = 1
        return x

    x = matrix(texts)
    swapped = [(i, s) for i, t in enumerate(texts) if (s := counterfactuals(t, identities)) != t]
    delta = x[[i for i, _ in swapped]] - matrix([s for _, s in swapped]) if swapped else None
    weight = np.where(labels == 1, share / pos, (1 - share) / neg)
    weight, labels = weight.astype(np.float32), labels.astype(np.float32)
    w, m, v = (np.zeros(x.shape[1], np.float32) for _ in range(3))
    w[-2] = np.log(max(share, 1e-6) / max(1 - share, 1e-6))
    ridges = np.full(x.shape[1], ridge, np.float32)
    ridges[-2:] = 0
    for step in range(1, steps + 1):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (weight * (p - labels)) + ridges * w
        if delta is not None:
            g += np.float32(2 * penalty / len(delta)) * (delta.T @ (delta @ w))
        m, v = np.float32(0.9) * m + np.float32(0.1) * g, np.float32(0.999) * v + np.float32(0.001) * g * g
        w -= np.float32(0.05) * (m / np.float32(1 - 0.9**step)) / (np.sqrt(v / np.float32(1 - 0.999**step)) + np.float32(1e-8))
    return Model(keys, w[:-2].astype(np.float64), float(w[-2]), float(w[-1]))


def train(docs: DataFrame, labels: DataFrame, held_out=None, positives: int = 1500, negatives: int = 4500, longest: int = 20_000, **options) -> Model:
    """Fits on at most ``positives`` + ``negatives`` rows; ``held_out`` is a condition on doc_id that is never learned."""
    labels = labels.where("doc_id is not null and toxic is not null")
    if held_out is not None:
        labels = labels.where(~held_out)
    labels = labels.groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    count, ones = labels.agg(F.count("*"), F.coalesce(F.sum((F.col("toxic") > 0).cast("long")), F.lit(0))).first()
    lengths = docs.select("doc_id", F.length("text").alias("_n")).where(F.col("_n") <= longest)
    usable = labels.join(lengths, "doc_id")
    picked = [usable.where(c).select("doc_id", "toxic", F.xxhash64("doc_id").alias("_h")).orderBy("_h").limit(n) for c, n in (("toxic > 0", positives), ("toxic <= 0", negatives))]
    sample = docs.select("doc_id", "text").join(F.broadcast(picked[0].union(picked[1]).select("doc_id", "toxic")), "doc_id")
    rows = sample.where("text is not null").select("doc_id", "text", "toxic").toPandas().sort_values(["doc_id", "text"])
    texts, toxic = rows["text"].tolist(), (rows["toxic"] > 0).to_numpy()
    del rows
    model = fit(texts, toxic, ones / max(count, 1), **options)
    del texts
    shared.give_back()
    return model


def _scorer(model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = Model(*model.value)
        for batch in batches:
            for b in textkit.pieces(batch, "text", 1 << 20):
                cols = [b.column(i) for i in range(b.num_columns)]
                s = m.scores(b.column(b.schema.get_field_index("text")))
                yield pa.RecordBatch.from_arrays([*cols, pa.array(s)], names=[*b.schema.names, "_score"])

    return run


def score(docs: DataFrame, model: Model) -> DataFrame:
    """All columns of ``docs`` and ``_score`` (which replaces a column of that name)."""
    docs = docs.drop("_score")
    sent = docs.sparkSession.sparkContext.broadcast((model.keys, model.weights, model.bias, model.length))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema) + ", _score double"
    return docs.mapInArrow(_scorer(sent), schema)
