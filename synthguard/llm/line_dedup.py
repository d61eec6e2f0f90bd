"""Line deduplication over a whole corpus.

The 128-bit hash of every line long enough is range-partitioned and sorted by (hash, document descending, position). Each
partition is streamed once: the first document met for a hash keeps its lines, the others lose them once min_docs
documents are known to hold it. Partition borders may cut through one hash (a very common line fills many partitions):
the first hash of a partition, and what is still open of its last, leave as edge rows plus at most min_docs document ids
for each, and a join with those few summaries settles them. What comes back is a compressed keep bitmap for each document
and no text.

Defined cases: a null or empty text is one empty line; rows with a null id are kept whole and count for nothing; rows
that share an id count as one document, and each is cut by its own text; ties cannot occur, as the largest id decides;
extra columns pass through untouched, whatever their names, but for those that have the names of the two counts.
"""

from __future__ import annotations

import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from synthguard.llm.common import LOWER, UPPER, WHITE_SPACE, carried, handed_back, staged, table, text_or_empty

DECIDED, EDGE, SUMMARY = 0, 1, 2
_SCHEMA = "kind int, doc long, print long, pos int, h1 long, h2 long"


def line_hashes(docs: DataFrame, id_col: str, text_col: str, min_chars: int) -> DataFrame:
    """One row for each line of min_chars or more: doc, print (hash of the whole text), pos, h1, h2."""
    lines = docs.where(F.col(id_col).isNotNull()).select(
        F.col(id_col).cast("long").alias("doc"), F.xxhash64(text_or_empty(text_col)).alias("print"), F.posexplode(F.split(text_or_empty(text_col), "\n", -1)).alias("pos", "line")
    )
    key = F.translate(F.btrim("line", F.lit(WHITE_SPACE)), UPPER, LOWER)
    return lines.select("doc", "print", "pos", key.alias("key")).where(F.length("key") >= min_chars).select("doc", "print", "pos", F.xxhash64("key").alias("h1"), F.xxhash64(F.lit(7), "key").alias("h2"))


def _stream(min_docs: int):
    """Streams a sorted partition; holds at most the rows of min_docs - 2 documents of one hash."""

    def run(batches):
        key, seen, last, first_key, waiting, tops = None, 0, None, True, [], []

        def rows(kind, a):
            n = len(a[0])
            return pa.RecordBatch.from_arrays([pa.array(np.full(n, kind, np.int32)), *(pa.array(x) for x in a)], names=["kind", "doc", "print", "pos", "h1", "h2"])

        def summary():
            n = len(tops)
            return rows(SUMMARY, [np.array(tops, np.int64), np.zeros(n, np.int64), np.zeros(n, np.int32), np.full(n, key[0], np.int64), np.full(n, key[1], np.int64)])

        for b in batches:
            if not b.num_rows:
                continue
            doc, mark, pos, h1, h2 = (b.column(k).to_numpy(zero_copy_only=False) for k in ("doc", "print", "pos", "h1", "h2"))
            pos = pos.astype(np.int32, copy=False)
            n = len(doc)
            new_key = np.empty(n, bool)
            new_key[0] = key is None or (h1[0], h2[0]) != key
            new_key[1:] = (h1[1:] != h1[:-1]) | (h2[1:] != h2[:-1])
            new_doc = new_key.copy()
            new_doc[0] |= doc[0] != last
            new_doc[1:] |= doc[1:] != doc[:-1]
            starts = np.flatnonzero(new_key)
            cum = np.cumsum(new_doc)
            run_of = np.cumsum(new_key)  # 0: goes on from the batch before
            base = np.concatenate(([-seen], cum[starts] - 1)) if len(starts) else np.array([-seen])
            rank = cum - base[run_of]
            ends = np.concatenate((starts, [n]))  # end of run r in this batch
            total = np.where(ends > 0, rank[np.maximum(ends - 1, 0)], seen)
            n_runs = len(ends)
            pick = lambda m: [x[m] for x in (doc, mark, pos, h1, h2)]
            # the partition's first hash may have begun before it: all its rows are open
            edge = (run_of == 0) if key is not None and first_key else (run_of == 1) if key is None else np.zeros(n, bool)
            if edge.any():
                yield rows(EDGE, pick(edge))
            # the run carried in
            if key is not None:
                tops += [int(x) for x in doc[(run_of == 0) & new_doc & (rank <= min_docs)]]
                if total[0] >= min_docs:
                    for w in waiting:
                        yield rows(DECIDED, w)
                    waiting = []
            if key is not None and n_runs > 1 and first_key:
                yield summary()
                first_key = False
            if n_runs > 1:
                waiting, tops = [], []
            if key is None and n_runs > 2:  # the first hash began and ended in this batch
                m = (run_of == 1) & new_doc & (rank <= min_docs)
                tops, key = [int(x) for x in doc[m]], (int(h1[0]), int(h2[0]))
                yield summary()
                tops, first_key = [], False
            full = total[run_of] >= min_docs
            drop = full & (rank >= 2) & ~edge
            if drop.any():
                yield rows(DECIDED, pick(drop))
            tail = run_of == n_runs - 1
            held = tail & ~full & (rank >= 2) & ~edge
            if held.any():
                waiting.append(pick(held))
            if n_runs > 1:
                tops = [int(x) for x in doc[tail & new_doc & (rank <= min_docs)]]
            key, seen, last = (int(h1[-1]), int(h2[-1])), int(rank[-1]), int(doc[-1])
        if key is not None:
            for w in waiting:
                yield rows(EDGE, w)
            yield summary()

    return run


def keep_bitmaps(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = 20, min_docs: int = 3) -> DataFrame:
    """doc, print, n_dropped, keep_bitmap (zlib of a bit for each line, 1 keeps; lines beyond it are kept) of every document that loses lines.

    min_docs of 2 or more documents must hold a line for it to go everywhere but in the largest id.
    """
    ordered = (
        line_hashes(docs, id_col, text_col, min_chars)
        .repartitionByRange("h1", "h2", F.desc("doc"))
        .sortWithinPartitions("h1", "h2", F.desc("doc"), "print", "pos")
    )
    found = staged(spark, ordered.mapInArrow(_stream(min_docs), _SCHEMA), "lines")
    # at most 2 * min_docs rows for each partition of the sort
    whole = found.where(F.col("kind") == SUMMARY).groupBy("h1", "h2").agg(F.max("doc").alias("top"), F.countDistinct("doc").alias("held_by")).where(F.col("held_by") >= min_docs)
    edges = found.where(F.col("kind") == EDGE).join(F.broadcast(whole), ["h1", "h2"]).where(F.col("doc") < F.col("top"))
    lost = found.where(F.col("kind") == DECIDED).select("doc", "print", "pos").unionByName(edges.select("doc", "print", "pos"))
    packed = lost.groupBy("doc", "print").agg(F.collect_set("pos").alias("lines"))

    @F.pandas_udf("binary")
    def bitmap(lines: pd.Series) -> pd.Series:
        def one(x):
            bits = np.ones((int(max(x)) + 8) // 8 * 8, np.uint8)  # whole bytes, filled up with ones
            bits[np.asarray(x, np.int64)] = 0
            return zlib.compress(np.packbits(bits).tobytes(), 6)

        return lines.map(one)

    return packed.select("doc", "print", F.size("lines").cast("long").alias("n_dropped"), bitmap("lines").alias("keep_bitmap"))


def apply_bitmaps(docs: DataFrame, bitmaps: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with the lines that the bitmaps drop cut from the text (null stays null), plus _n_lines and _n_dropped (in place of columns so named)."""
    left = carried(docs, doc=F.col(id_col).cast("long"), print=F.xxhash64(text_or_empty(text_col)), text=F.col(text_col))
    joined = left.join(bitmaps.select("doc", "print", "keep_bitmap"), ["doc", "print"], "left")

    @F.pandas_udf("struct<text string, n_lines long, n_dropped long>")
    def cut(text: pd.Series, bits: pd.Series) -> pd.DataFrame:
        out, n_lines, n_dropped = [], [], []
        for t, z in zip(text, bits, strict=True):
            if z is None:
                out.append(t)
                n_lines.append((t or "").count("\n") + 1)
                n_dropped.append(0)
                continue
            lines = t.split("\n")
            keep = np.unpackbits(np.frombuffer(zlib.decompress(z), np.uint8))[: len(lines)]
            stay = [x for i, x in enumerate(lines) if i >= len(keep) or keep[i]]
            out.append("\n".join(stay))
            n_lines.append(len(lines))
            n_dropped.append(len(lines) - len(stay))
        return pd.DataFrame({"text": out, "n_lines": n_lines, "n_dropped": n_dropped})

    done = joined.select("row", cut("text", "keep_bitmap").alias("cut"))
    return handed_back(done, docs, {text_col: "cut.text", "_n_lines": "cut.n_lines", "_n_dropped": "cut.n_dropped"})


def dedup_lines(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = 20, min_docs: int = 3) -> DataFrame:
    return apply_bitmaps(docs, keep_bitmaps(spark, docs, id_col, text_col, min_chars, min_docs), id_col, text_col)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    done = dedup_lines(spark, docs)
    return done.select("doc_id", F.col("_n_lines").alias("n_lines"), F.col("_n_dropped").alias("n_dropped"), F.sha2(text_or_empty(), 256).alias("kept_sha256"))


SQL = r"""
WITH lines AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, unnest(range(len(string_split(coalesce(text, ''), chr(10))))) AS pos
  FROM documents),
keyed AS (
  SELECT *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k FROM lines),
common AS (
  SELECT k, max(doc_id) AS top FROM keyed WHERE length(k) >= 20 GROUP BY k HAVING count(DISTINCT doc_id) >= 3),
judged AS (
  SELECT l.doc_id, l.pos, l.line, c.top IS NOT NULL AND l.doc_id < c.top AS gone FROM keyed l LEFT JOIN common c ON l.k = c.k)
SELECT doc_id, count(*)::BIGINT AS n_lines, count(*) FILTER (gone)::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone), '')) AS kept_sha256
FROM judged GROUP BY doc_id
"""
