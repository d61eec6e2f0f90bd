"""Language identification by averaged hashed subword embeddings and a linear softmax.

A text is the mean of the embeddings of its byte 3- and 4-grams (ASCII upper case lowered, space between words); a linear
layer and a softmax give the language. Stochastic gradient descent in numpy trains both on the driver, on about
rows_each documents of each language (a parameter; picked by a hash of the id). A temperature fitted on documents set
aside makes the scores probabilities, and a rejection threshold is chosen there, so that what is accepted is right as
often as asked. As both layers are linear, scoring needs one table of a logit for each bucket and language; it reads every
whole text once, without a shuffle.

Defined cases: a null text, or one without a letter, is `und` with score 0; null languages and null ids are not learnt
from; without any language to learn every text is `und`; equal scores go to the first language in order; repeated rows are predicted alike; an empty table gives no rows.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from synthguard.llm.common import carried, handed_back, held_out, table, text_or_empty
from synthguard.llm.textkernel import BYTE_VALUE, LOWERED, SPACE, U64

BITS, WIDTH = 16, 16
UNKNOWN = "und"
_LETTER = regex.compile(r"\p{L}")


def buckets(text: bytes, bits: int = BITS) -> np.ndarray:
    return np.concatenate(list(stretches(text, bits)))


def stretches(text: bytes, bits: int = BITS, step: int = 1 << 20):
    """Buckets of the n-grams of a whole text between two spaces, each once, for a stretch of starts at a time."""
    raw = np.frombuffer(b" " + text + b" ", np.uint8)
    k = U64(0x9E3779B97F4A7C15)
    for at in range(0, max(len(raw) - 2, 1), step):
        some = LOWERED[raw[at : at + step + 3]]
        v = BYTE_VALUE[np.where(SPACE[some], np.uint8(32), some)]
        three = (v[:-2] * k + v[1:-1]) * k + v[2:]
        four = three[:-1] * k + v[3:]
        h = np.concatenate((three[:step], four))
        yield ((h ^ (h >> U64(29))) * U64(0xBF58476D1CE4E5B9) >> U64(64 - bits)).astype(np.int64)


def counted(text: bytes) -> tuple[np.ndarray, np.ndarray]:
    b, c = np.unique(buckets(text), return_counts=True)
    return b.astype(np.uint32), c.astype(np.float32)


@dataclass
class Model:
    languages: list[str]
    logits: np.ndarray  # bucket x language
    bias: np.ndarray
    temperature: float = 1.0
    threshold: float = 0.0

    def predict(self, text: bytes | None, step: int = 1 << 20) -> tuple[str, float]:
        if not self.languages or not text or not _LETTER.search(text.decode("utf-8", "replace")):
            return UNKNOWN, 0.0
        total, n = np.zeros(len(self.languages)), 0
        for b in stretches(text, step=step):  # a stretch at a time bounds the memory
            total += self.logits[b].sum(0, dtype=np.float64)
            n += len(b)
        return self.pick(total / max(n, 1) + self.bias)

    def pick(self, z: np.ndarray) -> tuple[str, float]:
        p = softmax(z / self.temperature)
        i = int(np.argmax(p))
        return self.languages[i], float(p[i])


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


def fit(rows: list[tuple[np.ndarray, np.ndarray]], names: list[str], epochs: int = 6, rate: float = 20.0, precision: float = 0.99, seed: int = 1) -> Model:
    """rows: (buckets, counts) of each document."""
    languages = sorted(set(names))
    if not languages:
        return Model([], np.zeros((1 << BITS, 0), np.float32), np.zeros(0))
    y = np.array([languages.index(x) for x in names])
    rng = np.random.default_rng(seed)
    embed = rng.normal(0, 0.1, (1 << BITS, WIDTH)).astype(np.float32)
    out, bias = np.zeros((WIDTH, len(languages)), np.float32), np.zeros(len(languages), np.float32)
    aside = np.arange(len(rows)) % 6 == 0 if len(rows) >= 30 else np.zeros(len(rows), bool)
    own = np.flatnonzero(~aside)
    for epoch in range(epochs):
        step = rate * (1 - epoch / epochs)
        for i in rng.permutation(own):
            b, c = rows[i]
            if not len(b):
                continue
            share = (c / c.sum())[:, None]
            hidden = (embed[b] * share).sum(0)
            p = softmax(hidden @ out + bias)
            p[y[i]] -= 1
            back = out @ p
            out -= 0.1 * step * np.outer(hidden, p)
            bias -= 0.002 * step * p
            embed[b] -= step * share * back
    model = Model(languages, (embed @ out).astype(np.float32), bias.astype(np.float64))
    test = np.flatnonzero(aside)
    if len(test):
        z = np.array([(model.logits[b] * (c / max(c.sum(), 1))[:, None]).sum(0) for b, c in (rows[i] for i in test)]) + model.bias
        grid = np.geomspace(0.05, 20, 60)
        loss = [-np.log(softmax(z / t)[np.arange(len(test)), y[test]] + 1e-12).mean() for t in grid]
        model.temperature = float(grid[int(np.argmin(loss))])
        p = softmax(z / model.temperature)
        sure, right = p.max(1), p.argmax(1) == y[test]
        order = np.argsort(-sure)
        good = np.cumsum(right[order]) / np.arange(1, len(order) + 1) >= precision
        model.threshold = float(sure[order][np.flatnonzero(good)[-1]]) if good.any() else 1.0
    return model


def train(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", rows_each: int = 1500) -> Model:
    """A model of all languages of docs, on about rows_each documents of each at most."""
    rows = docs.where(F.col(lang_col).isNotNull() & F.col(id_col).isNotNull() & F.col(text_col).isNotNull())
    # one row for each language
    shares = rows.groupBy(F.col(lang_col).alias("_sg_lang")).agg(F.least(F.lit(1.0), F.lit(float(rows_each)) / F.count("*")).alias("_sg_share"))
    luck = F.pmod(F.xxhash64(F.lit(11), F.col(id_col)), F.lit(1 << 30)) / float(1 << 30)
    picked = rows.join(F.broadcast(shares), F.col(lang_col) == F.col("_sg_lang")).where(luck < F.col("_sg_share"))

    @F.pandas_udf("struct<b binary, c binary>")
    def grams(text: pd.Series) -> pd.DataFrame:
        got = [counted(t.encode()) for t in text]
        return pd.DataFrame({"b": [x.tobytes() for x, _ in got], "c": [x.tobytes() for _, x in got]})

    got = picked.select(F.xxhash64(id_col).alias("h"), F.col(lang_col).alias("l"), grams(F.col(text_col)).alias("g")).select("h", "l", "g.b", "g.c").collect()
    got = sorted(tuple(r) for r in got)
    return fit([(np.frombuffer(r[2], np.uint32), np.frombuffer(r[3], np.float32)) for r in got], [r[1] for r in got])


def identify(docs: DataFrame, model: Model, text_col: str = "text") -> DataFrame:
    """docs with lang_pred, score and rejected (score under the calibrated threshold), in place of columns so named; the model is of a fixed size."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("struct<lang_pred string, score double, rejected boolean>")
    def told(text: pd.Series) -> pd.DataFrame:
        m = held.value
        got = [m.predict((t or "").encode()) for t in text]
        return pd.DataFrame({"lang_pred": [g[0] for g in got], "score": [g[1] for g in got], "rejected": [g[0] == UNKNOWN or g[1] < m.threshold for g in got]})

    done = carried(docs, told=told(F.col(text_col)))
    return handed_back(done, docs, {n: f"told.{n}" for n in ("lang_pred", "score", "rejected")})


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = train(docs.where(~held_out("doc_id", 5, 0)))
    done = identify(docs.select("doc_id", "text"), model)
    return done.select("doc_id", held_out("doc_id", 5, 0).alias("held_out"), "lang_pred", "score", "rejected")
