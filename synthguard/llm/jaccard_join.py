"""Exact similarity join of documents by the Jaccard index of their word shingles, with its connected classes.

1. Counts: a table of bounded size (hashed counts over all documents, 2**24 at most) orders shingles from rare to frequent.
2. Sets: each document's distinct shingles are hashed to 64 bits; equal sets become one set. Of each set, the rarest
   n - ceil(t n) + 1 shingles are kept (two linked sets share one of these), and blocks of documents ask in packed messages which of theirs stand in
   other sets too; only those go on.
3. Groups: the least shingle of each eighth of the hash space is a mark. Sets that share marks are likely alike: each meets the
   set whose marks are the commonest, and some neighbours in the order of the next mark; those whose bitmaps are most like its own are compared,
   exactly, on whole texts, and linked sets are one group. A few pairs for each set, however many near copies a cluster has.
4. Token-group matrix: for each shingle and group, the group's entry holds the range of its set sizes and the longest
   rest behind the shingle. Shingles that the same groups hold are one row of the matrix, and a row's groups meet where sizes and rests allow.
   A set opens a group if it lacks few enough of the bits of the union of the group's shingles; of two groups that open each other, the
   sets that are likeliest alike are compared first, exactly, on whole texts, and all others that pass the bounds only if those are not.
   Within a group the classes are the same already, so copies are never expanded into pairs.

Defined cases: A-Z are lowered, words are separated by [\\x20\\x09-\\x0D]; a text with fewer words than a shingle has is one
shingle; null, empty and blank texts have none and link with nothing; rows with a null id get a null class and take no
part; rows that share an id are classed each by its own text; other columns are not read.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.taskcontext import TaskContext

from synthguard.llm.blocks import U64, by_bucket, packed, packed_counts, unpacked, unpacked_counts
from synthguard.llm.common import staged, table, text_or_empty, unstaged
from synthguard.llm.components import components
from synthguard.llm.textkernel import Words, as_bytes, chunks, mix, runs_unique

SLICE = 1 << 10
#: The table of counts has up to 2**MOST_BITS entries (64 MB).
MOST_BITS = 24
#: 64-bit words of a set's bitmap, one bit a shingle; bits of the filter of wanted texts.
BITMAP, WANTED = 16, 1 << 23
#: Parts of the hash space, each of which gives a set a mark.
MARKS = 8
#: Sets before a set that it is compared with by bitmaps, for each mark; pairs of a set that are compared exactly.
NEIGHBOURS, TRIES = 16, 3
_WEIGHTS = mix(np.arange(1, 65, dtype=U64)) | U64(1)


def shingles(texts: list[bytes], words: int) -> tuple[np.ndarray, np.ndarray]:
    """(text index, hash) of all shingles, repeats included, in order of the text; blank texts have none."""
    w = Words(texts)
    h = w.hashes()
    short = (w.count > 0) & (w.count < words)
    n = max(len(h) - words + 1, 0)
    s = np.zeros(n, U64)
    for k in range(words):
        s += h[k : k + n] * _WEIGHTS[k]
    whole = w.doc[:n] == w.doc[words - 1 :] if n else np.zeros(0, bool)
    doc, s = w.doc[:n][whole], mix(s[whole])
    if short.any():
        extra = np.flatnonzero(short)
        one = np.zeros(len(extra), U64)
        for j, i in enumerate(extra):
            own = h[w.first[i] : w.first[i + 1]]
            one[j] = (own * _WEIGHTS[: len(own)]).sum(dtype=U64) ^ _WEIGHTS[40 + len(own)]
        doc, s = np.concatenate((doc, extra)), np.concatenate((s, mix(one)))
        order = np.argsort(doc, kind="stable")
        doc, s = doc[order], s[order]
    return doc, s


def sets_of(texts: list[bytes], words: int) -> list[np.ndarray]:
    out = []
    for _, some in chunks(texts, 1 << 19):  # bounds the memory of the arrays
        doc, s = runs_unique(*shingles(some, words))
        cut = np.searchsorted(doc, np.arange(len(some) + 1))
        out += [s[a:b] for a, b in zip(cut[:-1], cut[1:], strict=True)]
    return out


def bitmap(s: np.ndarray) -> list[int]:
    bits = np.zeros(64 * BITMAP, np.uint8)
    bits[(s & U64(64 * BITMAP - 1)).astype(np.int64)] = 1
    return np.packbits(bits).view(np.int64).tolist()


def marks(s: np.ndarray) -> list[int | None]:
    """The least shingle of each part of the hash space; s is sorted."""
    cuts = np.searchsorted(s, np.arange(MARKS, dtype=U64) << U64(61))
    ends = np.append(cuts[1:], len(s))
    return [int(s[a].view(np.int64)) if a < b else None for a, b in zip(cuts.tolist(), ends.tolist(), strict=True)]


def alike(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= percent * (len(a) + len(b) - both)


def _counts(docs: DataFrame, words: int, bits: int) -> np.ndarray:
    """Hashed counts of all shingles: slices are summed in two steps, so that no task gets all partitions' tables."""

    def count(batches):
        total = np.zeros(1 << bits, np.int64)
        for b in batches:
            places = [(shingles(c, words)[1] >> U64(64 - bits)).astype(np.int32) for _, c in chunks(as_bytes(b.column(0)), 1 << 19)]
            if places:
                total += np.bincount(np.concatenate(places), minlength=len(total))
        n = len(total) // SLICE
        yield pa.RecordBatch.from_arrays(
            [pa.array(np.arange(n)), pa.array(np.full(n, TaskContext.get().partitionId() // 64)), pa.array([packed_counts(x) for x in total.reshape(n, SLICE)])], names=["slice", "lot", "sums"]
        )

    def add(pdf: pd.DataFrame) -> pd.DataFrame:
        total = sum(unpacked_counts(x) for x in pdf["sums"])
        return pd.DataFrame({"slice": [pdf["slice"].iloc[0]], "lot": [0], "sums": [packed_counts(total)]})

    schema = "slice long, lot long, sums binary"
    rows = docs.select(text_or_empty("text").alias("text")).mapInArrow(count, schema).groupBy("slice", "lot").applyInPandas(add, schema).groupBy("slice").applyInPandas(add, schema).collect()
    total = np.zeros(1 << bits, np.int64)
    for r in rows:
        total[r["slice"] * SLICE : (r["slice"] + 1) * SLICE] = unpacked_counts(r["sums"])
    return total.astype(np.int32) if total.max(initial=0) < 1 << 31 else total


_SETS = "kind int, doc_id long, print long, n long, sid long, block long, bucket long, payload binary, bitmap array<long>, marks array<long>"


def _sets(docs: DataFrame, counts: np.ndarray, words: int, percent: int, buckets: int) -> DataFrame:
    """kind 0: a document's set (payload: its rarest shingles in order); kind 1: a block's message to a bucket."""
    held = docs.sparkSession.sparkContext.broadcast(counts)

    def run(batches):
        number = TaskContext.get().partitionId() << 24
        rank = held.value
        shift = U64(64 - (len(rank).bit_length() - 1))
        for b in batches:
            ids, prints, texts = b.column(0).to_pylist(), b.column(1).to_pylist(), as_bytes(b.column(2))
            for at, run_of in chunks(texts, 1 << 22):
                rows, asked, seen = [], [], set()
                for i, s in enumerate(sets_of(run_of, words)):
                    n, sid = len(s), 0
                    rarest = s[:0]
                    if n:
                        both = mix(np.array([s.sum(dtype=U64) + U64(n), np.bitwise_xor.reduce(mix(s))], U64))
                        sid = int(mix(both[:1] * U64(3) + both[1:])[0].astype(np.int64))
                        keep = n - (percent * n + 99) // 100 + 1
                        if ids[at + i] is not None and sid not in seen:
                            seen.add(sid)
                            rarest = s[np.lexsort((s, rank[(s >> shift).astype(np.int64)]))[:keep]]
                            asked.append(rarest)
                    rows.append((0, ids[at + i], prints[at + i], n, sid, number, None, rarest.tobytes() if len(rarest) else None, bitmap(s) if len(rarest) else None, marks(s) if len(rarest) else None))
                if asked:
                    keys, times = np.unique(np.concatenate(asked), return_counts=True)
                    own = times > 1  # known in this block to stand in several sets
                    for bucket, lo, hi in by_bucket(keys, buckets):
                        rows.append((1, None, None, hi - lo, None, number, bucket, packed(keys[lo:hi]) + np.packbits(own[lo:hi]).tobytes(), None, None))
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int32(), *[pa.int64()] * 6, pa.binary(), pa.list_(pa.int64()), pa.list_(pa.int64())), strict=True)], names=["kind", "doc_id", "print", "n", "sid", "block", "bucket", "payload", "bitmap", "marks"])
                number += 1

    return docs.select(F.col("doc_id").cast("long"), F.xxhash64("text"), "text").mapInArrow(run, _SETS)


def _shared(sets: DataFrame) -> DataFrame:
    """token, sid, n, pos of the rare shingles that stand in two sets or more."""

    def judge(pdf: pd.DataFrame) -> pd.DataFrame:
        raw = [(unpacked(p[: 8 * n]), np.unpackbits(np.frombuffer(p[8 * n :], np.uint8), count=n).astype(bool)) for p, n in zip(pdf["payload"], pdf["n"], strict=True)]
        keys = np.concatenate([k for k, _ in raw])
        _, which, times = np.unique(keys, return_inverse=True, return_counts=True)
        several = times[which] > 1
        out, at = [], 0
        for k, own in raw:
            out.append(np.packbits(several[at : at + len(k)] | own).tobytes())
            at += len(k)
        return pd.DataFrame({"block": pdf["block"], "bucket": pdf["bucket"], "n": pdf["n"], "answer": out})

    asked = sets.where("kind = 1").select("block", "bucket", "n", "payload")
    answers = asked.groupBy("bucket").applyInPandas(judge, "block long, bucket long, n long, answer binary")

    def pick(key, own: pd.DataFrame, told: pd.DataFrame) -> pd.DataFrame:
        if not len(own) or not len(told):
            return pd.DataFrame({"token": [], "sid": [], "n": [], "pos": []}, dtype="int64")
        rare = [np.frombuffer(x, U64) for x in own["payload"]]
        tokens = np.concatenate(rare)
        told = told.sort_values("bucket")
        good = np.concatenate([np.unpackbits(np.frombuffer(a, np.uint8), count=n).astype(bool) for a, n in zip(told["answer"], told["n"], strict=True)])
        sizes = np.fromiter(map(len, rare), np.int64, len(rare))
        pos = np.arange(len(tokens)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        keep = good[np.unique(tokens, return_inverse=True)[1]]
        return pd.DataFrame({"token": tokens.view(np.int64)[keep], "sid": np.repeat(own["sid"].to_numpy(), sizes)[keep], "n": np.repeat(own["n"].to_numpy(), sizes)[keep], "pos": pos[keep]})

    own = sets.where("kind = 0 AND payload IS NOT NULL").select("block", "sid", "n", "payload")
    return own.groupBy("block").cogroup(answers.select("block", "bucket", "n", "answer").groupBy("block")).applyInPandas(pick, "token long, sid long, n long, pos long")


def _among(wanted: DataFrame, col: str):
    """A filter of fixed size (1 MB) that lets all rows pass whose col is wanted, and few others while those are few."""
    place = F.pmod(F.xxhash64(col), F.lit(WANTED))
    words = wanted.select(place.alias("p")).groupBy(F.shiftright("p", 6).alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, CAST(p & 63 AS INT))")).alias("b"))
    table_ = np.zeros(WANTED // 64, np.int64)
    for r in words.collect():  # at most WANTED / 64 rows
        table_[r["w"]] = r["b"]
    held = wanted.sparkSession.sparkContext.broadcast(table_.view(U64))

    @F.pandas_udf("boolean")
    def may_be(p: pd.Series) -> pd.Series:
        x = p.to_numpy(np.int64)
        return pd.Series((held.value[x >> 6] >> (x & 63).astype(U64) & U64(1)).astype(bool))

    return may_be(place)


def _texts(docs: DataFrame, known: DataFrame, ids: DataFrame) -> DataFrame:
    """sid, text of the sets in ids (sid, distinct)."""
    spark = docs.sparkSession
    needed = staged(spark, ids.join(known.select("sid", "rep", "print"), "sid"), "needed")
    held = docs.select(F.col("doc_id").cast("long").alias("rep"), F.xxhash64("text").alias("print"), F.col("text").cast("binary").alias("text")).where(_among(needed, "print"))
    found = staged(spark, needed.join(held, ["rep", "print"]).dropDuplicates(["sid"]).select("sid", "text"), "texts")
    unstaged(spark, needed)
    return found


def _linked(pairs: DataFrame, texts: DataFrame, words: int, percent: int) -> DataFrame:
    """Of candidate pairs (a, b) of sets those whose whole texts are alike. The text of a moves with its pairs, so a comes once or seldom."""
    both = pairs.join(texts.select(F.col("sid").alias("a"), F.col("text").alias("ta")), "a").join(texts.select(F.col("sid").alias("b"), F.col("text").alias("tb")), "b")

    def check(batches):
        for b in batches:
            x, y, ta, tb = (b.column(k).to_pylist() for k in ("a", "b", "ta", "tb"))
            texts = dict(zip(x + y, ta + tb, strict=True))
            held = {}
            for first, some in chunks(texts.values()):
                held |= zip(list(texts)[first : first + len(some)], sets_of(some, words), strict=True)
            ok = [alike(held[p], held[q], percent) for p, q in zip(x, y, strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array([v for v, o in zip(x, ok, strict=True) if o], pa.int64()), pa.array([v for v, o in zip(y, ok, strict=True) if o], pa.int64())], names=["a", "b"])

    return both.select("a", "b", "ta", "tb").mapInArrow(check, "a long, b long")


class _Bounds:
    """What sizes and bitmaps tell of two sets."""

    def __init__(self, percent: int):
        self.percent = percent

    def apart(self, n, m) -> Column:
        return 100 * F.least(n, m) < self.percent * F.greatest(n, m)

    def least(self, n, m) -> Column:
        """What linked sets of these sizes must share."""
        return F.ceil((F.lit(self.percent) * (n + m)) / F.lit(100 + self.percent) - 1e-9)

    def smallest_partner(self, n, lo) -> Column:
        """The smallest size from lo on that a set linked to one of size n can have."""
        return F.greatest(lo, F.ceil(F.lit(self.percent) * n / 100 - 1e-9))

    @staticmethod
    def lacking(own, other) -> Column:
        return F.aggregate(F.zip_with(own, other, lambda x, y: F.bit_count(x.bitwiseAND(F.bitwise_not(y)))), F.lit(0), lambda t, x: t + x)

    def shared(self, na, ma, nb, mb) -> Column:
        """The most that two sets can share by their bitmaps."""
        return F.least(F.col(na) - self.lacking(ma, mb), F.col(nb) - self.lacking(mb, ma))


def _neighbours(rows: DataFrame, percent: int) -> DataFrame:
    """a, b, near: of the NEIGHBOURS sets before a set, in the order of the next mark among the sets of one mark, the one whose bitmap is most
    like its own, if sizes and bitmaps allow a link. Neighbours beyond a partition's border are not seen."""

    def run(batches):
        key, sid, size, bits = (np.zeros(0, np.int64),) * 3 + (np.zeros((0, BITMAP), U64),)
        for batch in batches:
            old = min(NEIGHBOURS, len(key))
            new = [batch.column(k).to_numpy(zero_copy_only=False) for k in ("key", "sid", "n")]
            own = batch.column("bitmap").flatten().to_numpy(zero_copy_only=False).view(U64).reshape(-1, BITMAP)
            key, sid, size = (np.concatenate((x[len(x) - old :], y)) for x, y in zip((key, sid, size), new, strict=True))
            bits = np.concatenate((bits[len(bits) - old :], own))
            best, who = np.full(len(key), -1.0), np.zeros(len(key), np.int64)
            for back in range(1, min(NEIGHBOURS, len(key) - 1) + 1):
                at = np.arange(max(back, old), len(key))
                at = at[(key[at] == key[at - back]) & (100 * np.minimum(size[at], size[at - back]) >= percent * np.maximum(size[at], size[at - back]))]
                x, y, n, m = bits[at], bits[at - back], size[at], size[at - back]
                only = [np.bitwise_count(p).sum(1, dtype=np.int64) for p in (x & ~y, y & ~x, x & y)]
                can = np.minimum(n - only[0], m - only[1]) * (100 + percent) >= percent * (n + m)
                near = np.where(can, only[2] / np.maximum(sum(only), 1), -1.0)
                better = near > best[at]
                best[at[better]], who[at[better]] = near[better], sid[at[better] - back]
            good = best >= 0
            yield pa.RecordBatch.from_arrays([pa.array(sid[good]), pa.array(who[good]), pa.array(best[good])], names=["a", "b", "near"])

    return rows.repartitionByRange("key", "following", "sid").sortWithinPartitions("key", "following", "sid").select("key", "sid", "n", "bitmap").mapInArrow(run, "a long, b long, near double")


def _likely(spark: SparkSession, known: DataFrame, bounds: _Bounds) -> DataFrame:
    """a, b: for each set that shares a mark with others the TRIES whose bitmaps are most like its own, of its marks' most popular sets and of its neighbours."""
    following = F.element_at("marks", F.pmod(F.col("at") + 1, F.lit(MARKS)) + 1)
    marked = known.select("sid", "marks", F.posexplode("marks").alias("at", "key")).where("key IS NOT NULL").select("sid", "key", following.alias("following"))
    several = staged(spark, marked.groupBy("key").agg(F.count("*").alias("k")).where("k > 1"), "marks")
    rows = staged(spark, marked.join(several, "key"), "marked")
    popular = rows.groupBy("sid").agg(F.sum("k").alias("popular"))
    ranked = staged(spark, rows.drop("k").join(popular.join(known.select("sid", "n", "bitmap"), "sid"), "sid"), "ranked")
    leaders = staged(spark, ranked.groupBy("key").agg(F.max_by(F.struct(F.col("sid").alias("b"), F.col("n").alias("nb"), F.col("bitmap").alias("mb")), F.struct("popular", "sid")).alias("l")).select("key", "l.*"), "leaders")
    led = ranked.join(leaders, "key").where((F.col("sid") != F.col("b")) & ~bounds.apart(F.col("n"), F.col("nb")) & (bounds.shared("n", "bitmap", "nb", "mb") >= bounds.least(F.col("n"), F.col("nb"))))
    ones = lambda x: F.aggregate(x, F.lit(0), lambda t, v: t + F.bit_count(v))
    near = ones(F.zip_with("bitmap", "mb", lambda x, y: x.bitwiseAND(y))) / ones(F.zip_with("bitmap", "mb", lambda x, y: x.bitwiseOR(y)))
    met = led.select(F.col("sid").alias("a"), "b", near.alias("near")).unionByName(_neighbours(ranked, bounds.percent).where("a <> b")).groupBy("a", "b").agg(F.max("near").alias("near"))
    best = F.slice(F.sort_array(F.collect_list(F.struct("near", "b")), False), 1, TRIES)  # of 2 * MARKS at most
    found = staged(spark, met.groupBy("a").agg(best.alias("best")).select("a", F.explode("best.b").alias("b")), "likely")
    unstaged(spark, several, rows, ranked, leaders)
    return found


def _open_groups(spark: SparkSession, shared: DataFrame, known: DataFrame, labels: DataFrame | None, bounds: _Bounds) -> DataFrame:
    """g, h, a, na, ma, most: sets a of group g that open group h, g and h opening each other; most: what a can share with a set of h."""
    percent = bounds.percent
    rows = shared.withColumn("comp", F.col("sid")) if labels is None else _labelled(shared, labels)
    rows = staged(spark, rows, "labelled")
    several = staged(spark, rows.groupBy("token").agg(F.min("comp").alias("x"), F.max("comp").alias("y"), F.min("n").alias("lo"), F.max("n").alias("hi"), F.max(F.col("n") - F.col("pos")).alias("rest")).where("x < y").select("token", "lo", "hi", "rest"), "several")
    # rows whose rest is too short for any size and any rest that their shingle has cannot open a group or be opened
    partner = bounds.smallest_partner(F.col("n"), F.col("lo"))
    near = (percent * F.col("lo") <= 100 * F.col("n")) & (100 * F.col("hi") >= percent * F.col("n")) & (F.least(F.col("n") - F.col("pos"), F.col("rest")) >= bounds.least(F.col("n"), partner))
    mixed = staged(spark, rows.join(several, "token").where(near).select("token", "sid", "comp", "n", "pos"), "mixed")
    entry = mixed.groupBy("token", "comp").agg(F.min("n").alias("lo"), F.max("n").alias("hi"), F.max(F.col("n") - F.col("pos")).alias("rest"))
    entry = staged(spark, entry, "entries")
    # shingles that the same groups hold are one row
    alike_rows = entry.groupBy("token").agg(F.count("*").alias("held"), F.sum(F.pmod(F.xxhash64("comp"), F.lit(1 << 31))).alias("x"), F.bit_xor(F.xxhash64(F.lit(1), "comp")).alias("y"))
    alike_rows = staged(spark, alike_rows.where("held > 1").select("token", F.xxhash64("held", "x", "y").alias("row")), "rows")
    matrix = entry.join(alike_rows, "token").groupBy("row", "comp").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.max("rest").alias("rest"))
    matrix = staged(spark, matrix, "matrix")
    other = matrix.select("row", F.col("comp").alias("h"), F.col("lo").alias("lo_"), F.col("hi").alias("hi_"), F.col("rest").alias("rest_"))
    x, y = bounds.smallest_partner(F.col("lo_"), F.col("lo")), bounds.smallest_partner(F.col("lo"), F.col("lo_"))
    meets = (F.col("comp") < F.col("h")) & (100 * F.col("hi") >= percent * F.col("lo_")) & (100 * F.col("hi_") >= percent * F.col("lo")) & (F.least("rest", "rest_") >= bounds.least(x, y))
    met = staged(spark, matrix.join(other, "row").where(meets).select(F.col("comp").alias("g"), "h").distinct(), "met")
    sets = mixed.select("sid", "comp", "n").distinct().join(known.select("sid", F.col("bitmap").alias("m")), "sid")
    sets = staged(spark, sets.select(F.col("comp").alias("g"), F.col("sid").alias("a"), F.col("n").alias("na"), F.col("m").alias("ma")), "inside")
    union = staged(spark, sets.groupBy(F.col("g").alias("h")).agg(F.min("na").alias("lo"), F.max("na").alias("hi"), F.array(*[F.bit_or(F.col("ma")[k]) for k in range(BITMAP)]).alias("u")), "unions")
    both_ways = met.unionByName(met.select(F.col("h").alias("g"), F.col("g").alias("h")))
    asked = both_ways.join(union, "h").join(sets, "g").where((percent * F.col("lo") <= 100 * F.col("na")) & (100 * F.col("hi") >= percent * F.col("na")))
    asked = asked.withColumn("most", F.col("na") - bounds.lacking("ma", "u")).where(F.col("most") >= bounds.least(F.col("na"), bounds.smallest_partner(F.col("na"), F.col("lo"))))
    opened = staged(spark, asked.select("g", "h", "a", "na", "ma", "most"), "opened")
    unstaged(spark, rows, several, mixed, entry, alike_rows, matrix, met, sets, union)
    return opened


def similar_classes(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest id of the class) for every row; links need percent of the union in common."""
    bounds = _Bounds(percent)
    docs = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text"))
    sizes = docs.agg(F.sum(F.length("text")).alias("n")).first()["n"] or 0
    buckets = max(8, int(sizes // (1 << 24)))
    bits = int(np.clip(round(np.log2(max(sizes, 1) / 1536)), 14, MOST_BITS))  # some 256 shingles for each count
    rows = staged(spark, _sets(docs, _counts(docs, words, bits), words, percent, buckets), "sets")
    members = staged(spark, rows.where("kind = 0").select("doc_id", "n", "sid"), "members")
    found = docs.where("doc_id IS NOT NULL")
    known = rows.where("kind = 0 AND n > 0 AND doc_id IS NOT NULL").groupBy("sid").agg(F.min(F.struct("doc_id", "print", "n")).alias("x"), F.first("bitmap", True).alias("bitmap"), F.first("marks", True).alias("marks"))
    known = staged(spark, known.select("sid", F.col("x.doc_id").alias("rep"), "x.print", "x.n", "bitmap", "marks"), "known")
    shared = staged(spark, _shared(rows), "shared")
    unstaged(spark, rows)
    ids = lambda pairs: pairs.select(F.col("a").alias("sid")).unionByName(pairs.select(F.col("b").alias("sid"))).distinct()
    edges = labels = None  # links that are known, and groups by them

    def add(pairs: DataFrame, texts: DataFrame) -> None:
        nonlocal edges, labels
        new = staged(spark, _linked(pairs, texts, words, percent), "edges")
        edges = new if edges is None else edges.unionByName(new)
        if not new.isEmpty():
            before, labels = labels, staged(spark, components(spark, edges), "groups")
            if before is not None:
                unstaged(spark, before)

    # groups: some pairs for each set
    likely = _likely(spark, known, bounds)
    texts = _texts(found, known, ids(likely))
    add(likely, texts)
    unstaged(spark, likely, texts)
    # what groups have not settled
    opened = _open_groups(spark, shared, known, labels, bounds)
    ahead = opened.where("g < h")
    behind = opened.where("g > h").select(F.col("g").alias("h"), F.col("h").alias("g"), F.col("a").alias("b"), F.col("na").alias("nb"), F.col("ma").alias("mb"), F.col("most").alias("most_b"))
    texts = _texts(found, known, opened.select(F.col("a").alias("sid")).distinct())
    likeliest = ahead.groupBy("g", "h").agg(F.max(F.struct(F.col("most") / F.col("na"), "a")).alias("x")).join(behind.groupBy("g", "h").agg(F.max(F.struct(F.col("most_b") / F.col("nb"), "b")).alias("y")), ["g", "h"])
    first = staged(spark, likeliest.select(F.col("x.a").alias("a"), F.col("y.b").alias("b")).distinct(), "first")
    add(first, texts)
    of = lambda name: labels.select(F.col("node").alias(name), F.col("comp").alias(f"c{name}"))
    if labels is not None:  # group pairs that are one by now are left out
        alive = ahead.select("g", "h").distinct().join(of("g"), "g", "left").join(of("h"), "h", "left").where(F.coalesce("cg", "g") != F.coalesce("ch", "h")).select("g", "h")
        ahead = ahead.join(alive, ["g", "h"])
    pairs = ahead.join(behind, ["g", "h"]).where(~bounds.apart(F.col("na"), F.col("nb")) & (bounds.shared("na", "ma", "nb", "mb") >= bounds.least(F.col("na"), F.col("nb")))).select("a", "b")
    pairs = staged(spark, pairs.distinct().join(first, ["a", "b"], "left_anti"), "pairs")
    add(pairs, texts)
    unstaged(spark, opened, texts, first, pairs, shared)
    if labels is None:
        of = known.select("sid", "rep", F.col("sid").alias("comp"))
    else:
        of = known.join(labels.withColumnRenamed("node", "sid"), "sid", "left").select("sid", "rep", F.coalesce("comp", "sid").alias("comp"))
    smallest = of.groupBy("comp").agg(F.min("rep").alias("component_id"))
    named = of.join(smallest, "comp").select("sid", "component_id")
    done = members.join(named, "sid", "left")
    return done.select(
        "doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNull(), F.lit(None)).when(F.col("n") == 0, F.col("doc_id")).otherwise(F.col("component_id")).cast("long").alias("component_id")
    )


def _labelled(shared: DataFrame, labels: DataFrame) -> DataFrame:
    return shared.join(labels.withColumnRenamed("node", "sid"), "sid", "left").select("token", "sid", "n", "pos", F.coalesce("comp", "sid").alias("comp"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similar_classes(spark, table(spark, sf_dir, "documents"), words=4, percent=85)


SQL = r"""
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
held AS (
  SELECT DISTINCT doc_id, array_to_string(list_slice(w, i, i + 3), ' ') AS s
  FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, 1) + 1)) AS i FROM words WHERE len(w) > 0)),
sizes AS (SELECT doc_id, count(*) AS n FROM held GROUP BY doc_id),
common AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM held a JOIN held b ON a.s = b.s AND a.doc_id < b.doc_id GROUP BY 1, 2),
linked AS (
  SELECT x, y FROM common JOIN sizes p ON x = p.doc_id JOIN sizes q ON y = q.doc_id WHERE 100 * k >= 85 * (p.n + q.n - k)),
edges AS (SELECT x, y FROM linked UNION ALL SELECT y, x FROM linked),
reach(doc, stop) AS (SELECT x, x FROM edges UNION SELECT r.doc, e.y FROM reach r JOIN edges e ON r.stop = e.x),
tops AS (SELECT doc, min(stop) AS c FROM reach GROUP BY doc)
SELECT d.doc_id, coalesce(n, 0)::BIGINT AS n_shingles, coalesce(c, d.doc_id)::BIGINT AS component_id
FROM documents d LEFT JOIN sizes s ON d.doc_id = s.doc_id LEFT JOIN tops t ON d.doc_id = t.doc
"""
