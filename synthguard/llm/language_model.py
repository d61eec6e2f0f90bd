"""Scoring by a deleted-interpolation n-gram model of the corpus itself.

The probability of a token mixes the maximum-likelihood estimates of bigram and unigram and a uniform share; the weights
depend on a bucket of how often the context was seen, and come from expectation-maximisation on counts of training
documents that are left out of the estimates (about one in ten). The final estimates use all training documents.

Blocks of documents send their distinct n-grams with counts, sorted and packed, to buckets of the key space; an n-gram
comes once at most from each block, so common words are no hot keys. The buckets add up and answer each message in its own
order, and each block's documents meet the answers once for the mixture statistics and once for the scores. Nothing that
grows with the corpus goes to the driver: only N, V and a histogram of rounded estimate ratios, of bounded size.

Words are told apart by 64-bit hashes, bigrams by 56 bits of theirs.

Defined cases: null and empty texts are the end token alone; rows with a null id are held out, and scored; repeated rows count as often
as they come; without any training document base and mixture are uniform; other columns are not read.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from synthguard.llm.blocks import U64, by_bucket, packed, packed_counts, unpacked, unpacked_counts
from synthguard.llm.common import held_out, staged, table, text_or_empty
from synthguard.llm.textkernel import Words, chunks, mix

END, START = U64(0x5851F42D4C957F2D), U64(0x14057B7EF767814F)
LEVELS, STEPS = 20, 8
_MESSAGE = "block long, kind int, bucket long, n long, keys binary, counts binary"
_ANSWER = "block long, kind int, bucket long, n long, counts binary, tokens long, words long, kept long"


class Tokens:
    """Token sequences of a block's documents, each closed by the end token, and their bigrams."""

    def __init__(self, texts: list[bytes]):
        words, before, sizes = [], [], []
        for _, run in chunks(texts):
            w = Words(run)
            n = len(w.start) + w.n
            seq = np.empty(n, U64)
            seq[np.arange(len(w.start)) + w.doc] = w.hashes()
            last = w.first[1:] + np.arange(w.n)
            seq[last] = END
            prev = np.empty(n, U64)
            prev[1:] = seq[:-1]
            prev[np.concatenate(([0], last[:-1] + 1))] = START
            words.append(seq)
            before.append(prev)
            sizes.append(w.count + 1)
        self.words, self.before = np.concatenate(words), np.concatenate(before)
        self.sizes = np.concatenate(sizes)
        self.doc = np.repeat(np.arange(len(texts)), self.sizes)

    def pairs(self) -> np.ndarray:
        return mix(self.before * U64(0xD1342543DE82EF95) + self.words * U64(0x2545F4914F6CDD1D)) >> U64(8) << U64(8)


def level(count: np.ndarray) -> np.ndarray:
    """Bucket of a context frequency: 0 for 0, then one for each power of two."""
    return np.minimum(np.ceil(np.log2(count + 1)), LEVELS - 1).astype(np.int64)


def _ask(pdf: pd.DataFrame, buckets: int) -> pd.DataFrame:
    t = Tokens(pdf["text"].tolist())
    learnt, aside = pdf["learnt"].to_numpy(bool)[t.doc], pdf["aside"].to_numpy(bool)[t.doc]
    rows = []
    for kind, seq in ((1, t.words), (2, t.pairs())):
        keys, which = np.unique(seq, return_inverse=True)
        total = np.bincount(which[learnt], minlength=len(keys))
        put_by = np.bincount(which[aside], minlength=len(keys))
        for bucket, lo, hi in by_bucket(keys, buckets):
            a, b = packed_counts(total[lo:hi]), packed_counts(put_by[lo:hi])
            rows.append((pdf["block"].iloc[0], kind, bucket, hi - lo, packed(keys[lo:hi]), len(a).to_bytes(4, "little") + a + b))
    return pd.DataFrame(rows, columns=["block", "kind", "bucket", "n", "keys", "counts"])


def _split(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    n = int.from_bytes(raw[:4], "little")
    return unpacked_counts(raw[4 : 4 + n]), unpacked_counts(raw[4 + n :])


def _add_up(pdf: pd.DataFrame) -> pd.DataFrame:
    """A bucket's sums, given back to each message in its order; the first row also tells tokens, distinct words and those left in."""
    keys = [unpacked(k) for k in pdf["keys"]]
    own = [_split(c) for c in pdf["counts"]]
    distinct, which = np.unique(np.concatenate(keys), return_inverse=True)
    total = np.bincount(which, np.concatenate([a for a, _ in own]), len(distinct)).astype(np.int64)
    aside = np.bincount(which, np.concatenate([b for _, b in own]), len(distinct)).astype(np.int64)
    out, at = [], 0
    for k in keys:
        w = which[at : at + len(k)]
        a, b = packed_counts(total[w]), packed_counts(aside[w])
        out.append(len(a).to_bytes(4, "little") + a + b)
        at += len(k)
    first = np.arange(len(pdf)) == 0
    one = pdf["kind"].to_numpy() == 1
    told = lambda x: np.where(first & one, x, 0)
    return pd.DataFrame({"block": pdf["block"], "kind": pdf["kind"], "bucket": pdf["bucket"], "n": pdf["n"], "counts": out, "tokens": told(total.sum()), "words": told((total > 0).sum()), "kept": told((total - aside).sum())})


def _told(answers: pd.DataFrame, kind: int, seq: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Total and left-out counts of every element of seq, from the answers to the block's messages."""
    mine = answers[answers["kind"] == kind].sort_values("bucket")
    pairs = [_split(c) for c in mine["counts"]]
    which = np.unique(seq, return_inverse=True)[1]
    return np.concatenate([a for a, _ in pairs])[which], np.concatenate([b for _, b in pairs])[which]


def _contexts(t: Tokens, words: np.ndarray, starts: int) -> np.ndarray:
    """Count of each token's context: that of the word before, or of documents at a document's start."""
    out = np.empty_like(words)
    out[1:] = words[:-1]
    out[t.before == START] = starts
    return out


def mixture(histogram: pd.DataFrame, rounds: int = 40) -> np.ndarray:
    """Weights (bigram, unigram, uniform) by context bucket, by expectation-maximisation; columns: level, pair, word (steps of log2 over uniform, None for 0), n."""
    weights = np.tile([0.5, 0.4, 0.1], (LEVELS, 1))
    for lv in range(LEVELS):
        own = histogram[histogram["level"] == lv]
        if not len(own):
            continue
        x = np.stack([np.exp2(own["pair"].to_numpy(float) / STEPS), np.exp2(own["word"].to_numpy(float) / STEPS), np.ones(len(own))], 1)
        x = np.nan_to_num(x, nan=0.0)
        n = own["n"].to_numpy(float)
        w = weights[lv]
        for _ in range(rounds):
            share = x * w
            share *= (n / share.sum(1))[:, None]
            w = (share.sum(0) + 1e-3) / (n.sum() + 3e-3)
        weights[lv] = w
    return weights


def score(spark: SparkSession, docs: DataFrame, learnt: Column, id_col: str = "doc_id", text_col: str = "text", block_bytes: int = 1 << 23) -> DataFrame:
    """doc_id, learnt, n_tokens, n_known, train_tokens, base_score, score for every row; learnt marks training documents."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(learnt, F.lit(False)).alias("learnt"), text_or_empty(text_col).cast("binary").alias("text"))
    size = rows.agg(F.sum(F.length("text") + 1)).first()[0] or 0
    n_blocks = max(1, -(-size // block_bytes))
    buckets = max(4, int(size // (1 << 22)))
    rows = rows.withColumn("aside", F.col("learnt") & (F.pmod(F.xxhash64(F.lit(5), "doc_id"), F.lit(10)) == 3)).withColumn("block", F.pmod(F.xxhash64("doc_id", "text"), F.lit(n_blocks)))
    asked = rows.groupBy("block").applyInPandas(lambda pdf: _ask(pdf, buckets), _MESSAGE)
    answers = staged(spark, asked.groupBy("kind", "bucket").applyInPandas(_add_up, _ANSWER), "answers")
    sums = answers.agg(F.sum("tokens"), F.sum("words"), F.sum("kept")).first()
    n, v, kept = (int(x or 0) for x in sums)
    starts = rows.agg(F.sum(F.col("learnt").cast("long")), F.sum(F.col("aside").cast("long"))).first()
    n_docs, n_aside = (int(x or 0) for x in starts)

    def observe(key, own: pd.DataFrame, told: pd.DataFrame) -> pd.DataFrame:
        columns = {"level": "int64", "pair": "float64", "word": "float64", "n": "int64"}
        if not len(own) or not kept:
            return pd.DataFrame({c: pd.Series([], dtype=d) for c, d in columns.items()})
        # the block's keys are those of all its documents; only the ones left out are looked at
        t = Tokens(own["text"].tolist())
        word, word_aside = _told(told, 1, t.words)
        pair, pair_aside = _told(told, 2, t.pairs())
        word, pair = word - word_aside, pair - pair_aside
        context = _contexts(t, word, n_docs - n_aside)
        m = own["aside"].to_numpy(bool)[t.doc]
        with np.errstate(divide="ignore", invalid="ignore"):
            p = np.round(STEPS * np.log2(np.where(pair > 0, pair / np.maximum(context, 1) * (v + 1), np.nan)))
            w = np.round(STEPS * np.log2(np.where(word > 0, word / kept * (v + 1), np.nan)))
        seen = pd.DataFrame({"level": level(context)[m], "pair": p[m], "word": w[m]})
        return seen.groupby(["level", "pair", "word"], dropna=False).size().reset_index(name="n").astype(columns)

    blocks_told = answers.select("block", "kind", "bucket", "n", "counts")
    some = rows.groupBy("block").cogroup(blocks_told.groupBy("block")).applyInPandas(observe, "level long, pair double, word double, n long")
    weights = mixture(some.groupBy("level", "pair", "word").agg(F.sum("n").alias("n")).toPandas())

    def judge(key, own: pd.DataFrame, told: pd.DataFrame) -> pd.DataFrame:
        names = ["doc_id", "learnt", "n_tokens", "n_known", "train_tokens", "base_score", "score"]
        if not len(own):
            return pd.DataFrame({c: [] for c in names})
        t = Tokens(own["text"].tolist())
        word, pair = _told(told, 1, t.words)[0], _told(told, 2, t.pairs())[0]
        context = _contexts(t, word, n_docs)
        w = weights[level(context)]
        p = w[:, 0] * pair / np.maximum(context, 1) + w[:, 1] * word / max(n, 1) + w[:, 2] / (v + 1)
        # without its bigram share, a context never seen leaves the rest scaled up to one
        p = np.where(context > 0, p, (w[:, 1] * word / max(n, 1) + w[:, 2] / (v + 1)) / np.maximum(1 - w[:, 0], 1e-12)) if n else np.full(len(p), 1 / (v + 1))
        add = lambda x: np.bincount(t.doc, x, len(own))
        base = np.log10((word + 1) / (n + v + 1))
        return pd.DataFrame(
            {"doc_id": own["doc_id"], "learnt": own["learnt"], "n_tokens": t.sizes, "n_known": add(word > 0).astype(np.int64), "train_tokens": n, "base_score": add(base), "score": add(np.log10(p))}
        )

    return rows.groupBy("block").cogroup(blocks_told.groupBy("block")).applyInPandas(judge, "doc_id long, learnt boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = score(spark, table(spark, sf_dir, "documents"), ~held_out("doc_id", 7, 2))
    return done.select("doc_id", (~F.col("learnt")).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The columns of the query that SQL can express."""
    return query(spark, sf_dir).select("doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score")


BASE_SQL = r"""
WITH words AS (
  SELECT doc_id, list_append(regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+'), ' ') AS w FROM documents),
tokens AS (SELECT doc_id, unnest(w) AS t FROM words),
crc AS (SELECT range AS i, list_reduce(list_prepend(range, range(8)), lambda c, k: CASE WHEN c % 2 = 1 THEN xor(c // 2, 3988292384) ELSE c // 2 END) AS v FROM range(256)),
look AS (SELECT list(v ORDER BY i) AS vs FROM crc),
folds AS (
  SELECT doc_id, xor(list_reduce(list_prepend(4294967295::BIGINT, list_transform(string_split(doc_id::VARCHAR, ''), lambda c: ascii(c)::BIGINT)), lambda c, b: xor(c // 256, vs[xor(c % 256, b) + 1])), 4294967295) % 7 = 2 AS held_out
  FROM documents, look),
counts AS (SELECT t, count(*) AS c FROM tokens JOIN folds USING (doc_id) WHERE NOT held_out GROUP BY t),
total AS (SELECT sum(c) AS n, count(*) AS v FROM counts)
SELECT doc_id, any_value(held_out) AS held_out, count(*)::BIGINT AS n_tokens, count(c)::BIGINT AS n_known, any_value(n)::BIGINT AS train_tokens,
  sum(log10((coalesce(c, 0) + 1) / (n + v + 1)::DOUBLE)) AS base_score
FROM tokens JOIN folds USING (doc_id) LEFT JOIN counts USING (t), total GROUP BY doc_id
"""
