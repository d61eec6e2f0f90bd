"""Quality classifier: Naive Bayes features into a linear support vector machine.

Features are hashed byte n-grams of the text, each present or absent. Their class log-count ratios scale the indicators;
rows are brought to unit length; a hinge-loss model is fitted by dual coordinate descent; a logistic curve fitted on
training rows that were set aside turns its margin into a score in [0, 1]. Fitting takes place on the driver, on at most
max_rows labelled rows (picked by a hash of the id): that bound is a parameter. Scoring reads every whole text once,
without a shuffle.

Defined cases: a null text scores as an empty one, whose score is that of the bias alone; labels that are null are left
out, of several labels of one id the largest counts; rows with a null id are scored and never learnt from; without labels
of both classes every text scores the share of label 1 (1 if there is none); repeated rows are scored alike; an empty table gives no rows; other columns are not inputs.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from synthguard.llm.common import carried, handed_back, held_out, table, text_or_empty
from synthguard.llm.textkernel import BYTE_VALUE, U64, Words, mix

BITS, GRAMS = 17, (1, 2, 3, 4)


def features(text: bytes, bits: int = BITS, grams: tuple[int, ...] = GRAMS, step: int = 1 << 20) -> np.ndarray:
    """Sorted distinct buckets of the byte n-grams of a whole text, a stretch of it at a time."""
    seen = np.zeros(1 << bits, bool)
    raw = np.frombuffer(b"\n" + text + b"\n", np.uint8)
    shift = U64(64 - bits)
    for at in range(0, len(raw), step):
        v = BYTE_VALUE[raw[at : at + step + max(grams) - 1]]
        h = v
        for n in range(1, max(grams) + 1):
            if n > 1:
                h = h[:-1] * U64(0x9E3779B97F4A7C15) + v[n - 1 :]
            if n in grams and len(h):
                seen[(h ^ (h >> U64(29))) * U64(0xBF58476D1CE4E5B9) >> shift] = True
    seen[repeats(raw, bits)] = True
    return np.flatnonzero(seen).astype(np.uint32)


def repeats(raw: np.ndarray, bits: int) -> np.ndarray:
    """Buckets of n-grams over "is the word that stood so many words before": runs of 2 to 32 such words, at distances 1 to 4."""
    h = Words([raw[1:-1].tobytes()]).hashes()
    found = []
    for back in range(1, 5):
        if len(h) <= back:
            break
        same = np.concatenate(([False], h[back:] == h[:-back], [False]))
        edges = np.flatnonzero(same[1:] != same[:-1])
        longest = int((edges[1::2] - edges[0::2]).max(initial=0))
        found += [64 * back + n for n in (2, 3, 4, 6, 8, 12, 16, 24, 32) if longest >= n]
    return (mix(np.array(found, U64)) >> U64(64 - bits)).astype(np.int64)


@dataclass
class Model:
    weights: np.ndarray  # by bucket, on indicators
    squares: np.ndarray  # squared log-count ratio by bucket, for the length
    bias: float
    slope: float
    shift: float

    def margins(self, rows: list[np.ndarray]) -> np.ndarray:
        return np.array([(self.weights[f].sum() / np.sqrt(max(self.squares[f].sum(), 1e-12))) + self.bias for f in rows])

    def scores(self, rows: list[np.ndarray]) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * self.margins(rows) + self.shift, -50, 50)))


def dual_descent(rows: list[np.ndarray], scale: np.ndarray, y: np.ndarray, cost: float, epochs: int, seed: int = 1) -> tuple[np.ndarray, float]:
    """w and b of the L2-regularised hinge loss; row i is scale[rows[i]] at unit length with a constant 1; y in -1, 1."""
    w, b = np.zeros(len(scale)), 0.0
    # a row's values are looked up when it is its turn: holding them would take several times the memory of the rows
    short = np.array([1 / np.sqrt(max((scale[f] ** 2).sum(), 1e-12)) for f in rows])
    size = np.array([(scale[f] ** 2).sum() for f in rows]) * short**2 + 1
    alpha, order = np.zeros(len(rows)), np.random.default_rng(seed)
    for _ in range(epochs):
        most = 0.0
        for i in order.permutation(len(rows)):
            x = scale[rows[i]] * short[i]
            slack = y[i] * (w[rows[i]] @ x + b) - 1
            now = min(max(alpha[i] - slack / size[i], 0.0), cost)
            step = (now - alpha[i]) * y[i]
            if step:
                most = max(most, abs(step))
                w[rows[i]] += step * x
                b += step
                alpha[i] = now
        if most < 1e-3 * cost:
            break
    return w, b


def logistic_curve(m: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and shift of the likeliest logistic curve (targets drawn in a little), by Newton's method."""
    t = np.where(y > 0, ((y > 0).sum() + 1) / ((y > 0).sum() + 2), 1 / ((y < 0).sum() + 2))
    a, c = 1.0, 0.0
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a * m + c, -30, 30)))
        v = p * (1 - p) + 1e-9
        g = np.array([((p - t) * m).sum() + 1e-3 * a, (p - t).sum()])
        h = np.array([[(v * m * m).sum() + 1e-3, (v * m).sum()], [(v * m).sum(), v.sum()]])
        d = np.linalg.solve(h, g)
        a, c = a - d[0], c - d[1]
        if np.abs(d).max() < 1e-8:
            break
    return float(a), float(c)


def fit(rows: list[np.ndarray], labels: np.ndarray, bits: int = BITS, smooth: float = 1.0, cost: float = 4.0, epochs: int = 20) -> Model:
    size, n = 1 << bits, len(rows)
    share = float(labels.mean()) if n else 1.0
    if n < 4 or share in (0.0, 1.0):
        p = min(max(share, 1e-6), 1 - 1e-6)
        return Model(np.zeros(size), np.ones(size), 0.0, 0.0, float(np.log(p / (1 - p))))

    def ratios(pick):
        count = {c: np.full(size, smooth) for c in (0, 1)}
        for i in pick:
            count[int(labels[i])][rows[i]] += 1
        return np.log(count[1] / count[1].sum()) - np.log(count[0] / count[0].sum())

    def train(pick):
        r = ratios(pick)
        y = np.where(labels[pick] == 1, 1.0, -1.0)
        w, b = dual_descent([rows[i] for i in pick], r, y, cost, epochs)
        return Model(w * r, r * r, b, 1.0, 0.0)

    aside = np.arange(n) % 5 == 0
    if len(set(labels[aside])) == 2 and len(set(labels[~aside])) == 2:
        first = train(np.flatnonzero(~aside))
        m = first.margins([rows[i] for i in np.flatnonzero(aside)])
        slope, shift = logistic_curve(m, np.where(labels[aside] == 1, 1.0, -1.0))
    else:
        slope, shift = 2.0, 0.0
    model = train(np.arange(n))
    model.slope, model.shift = max(slope, 1e-3), shift
    return model


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", max_rows: int = 6000) -> Model:
    """A model of the labelled documents, max_rows of them at most."""
    marked = (
        labels.where(F.col(id_col).isNotNull() & F.col(label_col).isNotNull())
        .groupBy(F.col(id_col).alias("_sg_id")).agg(F.max(label_col).cast("int").alias("_sg_label"))
        .orderBy(F.xxhash64("_sg_id"), "_sg_id").limit(max_rows)
    )
    picked = docs.select(F.col(id_col).alias("_sg_id"), text_or_empty(text_col).alias("_sg_text")).join(F.broadcast(marked), "_sg_id")

    @F.pandas_udf("binary")
    def grams(text: pd.Series) -> pd.Series:
        return text.map(lambda t: features(t.encode()).tobytes())

    got = sorted(tuple(r) for r in picked.select(F.xxhash64("_sg_id"), "_sg_id", "_sg_label", grams("_sg_text")).collect())
    return fit([np.frombuffer(r[3], np.uint32) for r in got], np.array([r[2] for r in got]))


def score(docs: DataFrame, model: Model, text_col: str = "text", out: str = "score") -> DataFrame:
    """docs with a column of scores, in place of one so named; the model is of a fixed size (2 * 2**BITS floats)."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def scored(text: pd.Series) -> pd.Series:
        m = held.value
        return pd.Series(m.scores([features((t or "").encode()) for t in text]), dtype="float64")

    return handed_back(carried(docs, scored=scored(F.col(text_col))), docs, {out: "scored"})


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    labels = table(spark, sf_dir, "labels").select("doc_id", "quality").where(~held_out("doc_id", 5, 0))
    done = score(docs, train(docs, labels))
    return done.select("doc_id", held_out("doc_id", 5, 0).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))
