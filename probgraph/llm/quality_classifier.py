"""Operator 7: quality classifier. Logistic regression on hashed word n-grams, trained with follow-the-regularised-leader updates.

Features: words and pairs of words, as written and as shapes (runs of upper case, lower case, digits; a word equal to the one before has a shape of its own),
hashed to ``2**bits`` weights; values are square roots of counts, scaled to unit length. The update is per coordinate with
L1 and L2 terms (proximal form), so most weights stay exactly zero. Training takes at most ``max_train`` labelled texts,
those with the least md5 of their id (the bound is this parameter, whatever the corpus's size), ``epochs`` times in one task; both classes weigh alike. The
model is a table of non-zero weights: at most ``2**bits``, so what is broadcast has a fixed bound. Scoring is a sparse dot product per text,
over all of them.

Null or empty text has only the intercept. A document without label isn't used to train; of several labels the largest counts;
null labels don't. Repeated rows are scored alike. Without labels of both classes the model is empty and every score is 0.5."""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BITS, MAX_TRAIN, EPOCHS = 18, 6000, 3
ALPHA, BETA, L1, L2 = 0.5, 1.0, 0.02, 0.1
THRESHOLD = 0.5
_RUNS = [(re.compile(r"[^\W\d_]+"), lambda m: "A" if m.group().isupper() else "a" if m.group().islower() else "Aa"), (re.compile(r"\d+"), lambda m: "0"), (re.compile(r"(.)\1+"), lambda m: m.group(1))]


def shape(word: str) -> str:
    for rx, to in _RUNS:
        word = rx.sub(to, word)
    return word


class _Coded(dict):
    def __init__(self, of):
        super().__init__()
        self.of = of

    def __missing__(self, w):
        if len(self) > 1_000_000:
            self.clear()
        v = self[w] = self.of(w)
        return v


class Features:
    """Text to (indices, values)."""

    def __init__(self, bits: int = BITS):
        self.shift = np.uint64(64 - bits)
        self.word = _Coded(lambda w: xxhash.xxh3_64_intdigest(w))
        self.shape = _Coded(lambda w: xxhash.xxh3_64_intdigest("\x00" + shape(w)))
        self.same = np.uint64(xxhash.xxh3_64_intdigest("\x00="))

    def __call__(self, text: str | None) -> tuple[np.ndarray, np.ndarray]:
        parts = (text or "").split()
        if not parts:
            return np.zeros(0, np.int64), np.zeros(0)
        w = np.fromiter(map(self.word.__getitem__, parts), np.uint64, len(parts))
        s = np.fromiter(map(self.shape.__getitem__, parts), np.uint64, len(parts))
        s[1:][w[1:] == w[:-1]] = self.same
        mul, add = np.uint64(0x9E3779B97F4A7C15), np.uint64(0x2545F4914F6CDD1D)
        every = np.concatenate([w, s, w[:-1] * mul + w[1:] * add, s[:-1] * mul + s[1:] * add])
        index = ((every ^ (every >> np.uint64(31))) * mul >> self.shift).astype(np.int64)
        index, n = np.unique(index, return_counts=True)
        v = np.sqrt(n)
        return index, v / np.sqrt(n.sum())


def _sigmoid(x: float) -> float:
    return 1 / (1 + np.exp(-np.clip(x, -35, 35)))


def train(texts: list[str], labels: list[int], bits: int = BITS, epochs: int = EPOCHS) -> tuple[np.ndarray, float]:
    """Weights and intercept."""
    z, n, w = (np.zeros(2**bits + 1) for _ in range(3))
    y = np.asarray(labels, float)
    if not 0 < y.sum() < len(y):
        return w[:-1], 0.0
    weight = np.where(y > 0, 0.5 * len(y) / y.sum(), 0.5 * len(y) / (len(y) - y.sum()))
    make = Features(bits)
    rows = []
    for t in texts:
        i, v = make(t)
        rows.append((np.append(i, 2**bits), np.append(v, 1.0)))
    for _ in range(epochs):
        for (i, v), target, c in zip(rows, y, weight):
            zi, ni = z[i], n[i]
            wi = np.where(np.abs(zi) <= L1, 0.0, -(zi - np.sign(zi) * L1) / ((BETA + np.sqrt(ni)) / ALPHA + L2))
            g = c * (_sigmoid(wi @ v) - target) * v
            more = ni + g * g
            z[i] = zi + g - (np.sqrt(more) - np.sqrt(ni)) / ALPHA * wi
            n[i] = more
    w = np.where(np.abs(z) <= L1, 0.0, -(z - np.sign(z) * L1) / ((BETA + np.sqrt(n)) / ALPHA + L2))
    return w[:-1], float(w[-1])


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", bits: int = BITS, max_train: int = MAX_TRAIN, epochs: int = EPOCHS) -> tuple[np.ndarray, float]:
    """Train in one executor task on the bounded sample."""
    known = labels.filter(F.col(label).isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max(label).cast("int").alias("y"))
    known = known.orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id").limit(max_train)
    texts = docs.select("doc_id", "text").join(F.broadcast(known), "doc_id").groupBy("doc_id", "y").agg(F.min("text").alias("text"))

    def run(_, part: pd.DataFrame) -> pd.DataFrame:
        part = part.assign(h=part.doc_id.map(lambda x: xxhash.xxh3_64_intdigest(str(x)))).sort_values("h")
        w, b = train(part.text.tolist(), part.y.tolist(), bits, epochs)
        at = np.flatnonzero(w)
        return pd.DataFrame({"i": np.append(at, 2**bits), "w": np.append(w[at], b)})

    got = texts.withColumn("one", F.lit(1)).groupBy("one").applyInPandas(run, "i long, w double").toPandas()
    w = np.zeros(2**bits + 1)
    w[got.i.to_numpy(np.int64)] = got.w.to_numpy(float)
    return w[:-1], float(w[-1])


def score(docs: DataFrame, model: tuple[np.ndarray, float], bits: int = BITS, threshold: float = THRESHOLD) -> DataFrame:
    """Columns of ``docs`` but the text, then ``score`` (probability of good quality) and ``keep``; columns of these names give way."""
    shared = docs.sparkSession.sparkContext.broadcast((model[0].astype(np.float32), model[1]))
    keep = [c for c in docs.columns if c not in ("text", "score", "keep")]

    @F.pandas_udf("double")
    def dot(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        w, b = shared.value
        make = Features(bits)
        for texts in parts:
            out = np.empty(len(texts))
            for k, t in enumerate(texts):
                i, v = make(t)
                out[k] = _sigmoid(w[i] @ v + b)
            yield pd.Series(out)

    return docs.select(*keep, F.round(dot(F.coalesce("text", F.lit(""))), 6).alias("score")).withColumn("keep", F.col("score") >= threshold)
