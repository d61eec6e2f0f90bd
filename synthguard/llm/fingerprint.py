"""Document fingerprints from chains of content words behind common words.

Wherever a common word (an anchor) stands, the next `chain` content words that follow at `gap` content words' distance form a signature
together with it. A fingerprint is the set of a document's signatures, hashed to 32 bits and written as sorted hexadecimal
digits; the likeness of two fingerprints is their Jaccard index. matches() finds all pairs of alike fingerprints: they are
partitioned by set length, compared only where the lengths allow the threshold, and candidates come from the rarest part of each set.

Words are runs of ASCII letters and digits and of non-ASCII bytes, with A-Z lowered. A text without any signature is
fingerprinted by its words as a whole, or, without words, by its bytes, so equal texts have equal fingerprints.

Defined cases: null and empty texts are equal and alike (likeness 1); repeated rows have equal fingerprints; a null id sorts as the smallest; rows
that share an id follow each other in the order of their text hashes; an only document follows itself; other columns are not read.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from synthguard.llm.common import parts, table, text_or_empty
from synthguard.llm.textkernel import NOT_ALNUM, U64, Words, chunks, mix, runs_unique

#: Common words of English, French, German and Spanish: fixed values.
ANCHORS = (
    "the of and to in a is that for it on was as with be by this are from at an or have has had not but were which their "
    "de la le les des et un une que du en est dans qui pour par sur au ce il elle se ne pas plus avec "
    "der die und das den von zu mit sich dem ein eine ist nicht auf als auch es im er sie wird bei "
    "el los y del las al lo como con su para una por no se es si mas o esta pero"
).split()


def _hash_words(words: list[str]) -> np.ndarray:
    w = Words([x.encode() for x in words], parted_by=NOT_ALNUM)
    return np.unique(w.hashes())


class Spots:
    """Turns texts into sorted sets of 32-bit signatures."""

    def __init__(self, anchors=ANCHORS, chain: int = 2, gap: int = 1):
        self.anchors, self.chain, self.gap = _hash_words(list(anchors)), chain, gap

    def __call__(self, texts: list[bytes]) -> list[np.ndarray]:
        w = Words(texts, parted_by=NOT_ALNUM)
        h = w.hashes()
        at = np.minimum(np.searchsorted(self.anchors, h), len(self.anchors) - 1)
        anchor = self.anchors[at] == h
        content = np.flatnonzero(~anchor)
        spots = np.flatnonzero(anchor)
        reach = (self.chain - 1) * self.gap
        follow = np.searchsorted(content, spots)  # the first content word behind each anchor
        ok = follow + reach < len(content)
        spots, follow = spots[ok], follow[ok]
        ok = w.doc[content[follow + reach]] == w.doc[spots] if len(spots) else ok[:0]
        spots, follow = spots[ok], follow[ok]
        sig = h[spots]
        for k in range(self.chain):
            sig = mix(sig * U64(0xD1342543DE82EF95) + h[content[follow + k * self.gap]])
        doc, sig = runs_unique(w.doc[spots], (sig >> U64(32)).astype(np.uint32))
        cut = np.searchsorted(doc, np.arange(w.n + 1))
        out = [sig[a:b] for a, b in zip(cut[:-1], cut[1:], strict=True)]
        for i, x in enumerate(out):
            if not len(x):
                a, b = w.first[i], w.first[i + 1]
                whole = w.buf[w.start[a] : w.end[b - 1]].tobytes() if b > a else texts[i]
                out[i] = np.frombuffer(hashlib.sha256(b"whole:" + whole).digest()[:4], np.uint32)
        return out


def written(spots: np.ndarray) -> str:
    return spots.astype(">u4").tobytes().hex()


def likeness(a: np.ndarray, b: np.ndarray, threshold: float = 0.0) -> float:
    """Jaccard index of two sorted sets; 0 without a look at them where their lengths keep it under the threshold."""
    if min(len(a), len(b)) < threshold * max(len(a), len(b)):
        return 0.0
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / (len(a) + len(b) - both) if len(a) + len(b) else 1.0


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", chain: int = 2, gap: int = 1) -> DataFrame:
    """doc_id, spots (array of distinct signatures) of every document."""

    def run(batches):
        spots = Spots(chain=chain, gap=gap)
        for b in batches:
            ids, texts = b.column(0), [x or b"" for x in b.column(1).to_pylist()]
            sets = [s for _, c in chunks(texts) for s in spots(c)]
            yield pa.RecordBatch.from_arrays([ids, pa.array([s.astype(np.int64) for s in sets], pa.list_(pa.int64()))], names=["doc_id", "spots"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("binary").alias("t")).mapInArrow(run, "doc_id long, spots array<long>")


def matches(prints: DataFrame, threshold: float = 0.8) -> DataFrame:
    """a, b, likeness of all pairs of classes of equal fingerprints that are alike; a and b are the smallest ids of their classes.

    Sets are partitioned by length: a set of n meets those of its own partition and the next, whose bounds grow by
    1 / threshold. Candidates share one of the rarest n - ceil(threshold * n) + 1 signatures (of the corpus's own counts).
    """
    classes = prints.groupBy(F.array_sort("spots").alias("spots")).agg(F.min("doc_id").alias("id"))
    rows = classes.select("id", F.explode("spots").alias("s"), F.size("spots").alias("n"), F.floor(F.ln(F.size("spots")) / F.lit(float(-np.log(threshold))) + 1e-9).alias("part"))
    counts = rows.groupBy("s").count()
    by_rarity = Window.partitionBy("id").orderBy("count", "s")
    rarest = rows.join(counts, "s").withColumn("r", F.row_number().over(by_rarity)).where(F.col("r") <= F.col("n") - F.ceil(threshold * F.col("n") - 1e-9) + 1)
    left = rarest.select(F.col("id").alias("a"), F.col("n").alias("na"), "s", F.explode(F.array(F.col("part"), F.col("part") + 1)).alias("part"))
    right = rarest.select(F.col("id").alias("b"), F.col("n").alias("nb"), "s", "part")
    fits = (F.col("na") >= threshold * F.col("nb")) & (F.col("nb") >= threshold * F.col("na")) & ((F.col("na") < F.col("nb")) | ((F.col("na") == F.col("nb")) & (F.col("a") < F.col("b"))))
    pairs = left.join(right, ["s", "part"]).where(fits).select("a", "b").distinct()
    sets = classes.select("id", "spots")
    whole = pairs.join(sets.select(F.col("id").alias("a"), F.col("spots").alias("x")), "a").join(sets.select(F.col("id").alias("b"), F.col("spots").alias("y")), "b")
    both = F.size(F.array_intersect("x", "y"))
    return whole.select("a", "b", (both / (F.size("x") + F.size("y") - both)).alias("likeness")).where(F.col("likeness") >= threshold)


_EDITED = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def edited_by_next(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", chain: int = 2, gap: int = 1) -> DataFrame:
    """Each document's fingerprint, that of its text with the second half overwritten by the next document's beginning, and their likeness.

    Documents are dealt to ranges of ids and sorted within them; the first document of each range also goes to the end of
    the range before, so every text moves once, and one of each range twice.
    """
    n = parts(docs.sparkSession)
    rows = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(-(1 << 63))).alias("id"), F.col(id_col).isNull().alias("no_id"), text_or_empty(text_col).cast("binary").alias("t"))
    cuts = [int(c) for c in sorted(rows.approxQuantile("id", [i / n for i in range(1, n)], 0.25 / n))] if n > 1 else []
    # an id that fills several ranges is cut by its texts' hashes
    pairs = [(c, j * (1 << 64) // (cuts.count(c) + 1) - (1 << 63) if cuts.count(c) > 1 else -(1 << 63)) for c in sorted(set(cuts)) for j in range(1, cuts.count(c) + 1)]
    # ranges in descending order of ids: 0 holds the largest
    bound = F.array(*[F.struct(F.lit(c).cast("long").alias("id"), F.lit(t).cast("long").alias("tie")) for c, t in pairs])
    ranged = rows.withColumn("tie", F.xxhash64("t"))
    ranged = ranged.withColumn("range", F.size(F.filter(bound, lambda c: (c["id"] > F.col("id")) | ((c["id"] == F.col("id")) & (c["tie"] > F.col("tie"))))) if pairs else F.lit(0))
    # one row for each range
    heads = ranged.groupBy("range").agg(F.max(F.struct("id", "tie")).alias("head")).orderBy("range").collect()
    filled = [r["range"] for r in heads]
    before = {r: filled[i - 1] for i, r in enumerate(filled)}
    first = F.lit(None).cast("int")
    for r in heads:
        is_head = (F.col("range") == r["range"]) & (F.col("id") == r["head"]["id"]) & (F.col("tie") == r["head"]["tie"])
        first = F.when(is_head, F.lit(before[r["range"]])).otherwise(first)
    if len(heads) > 64:  # a lookup instead of a long chain of conditions
        known = docs.sparkSession.createDataFrame([(r["range"], r["head"]["id"], r["head"]["tie"], before[r["range"]]) for r in heads], "range int, id long, tie long, to int")
        marked = ranged.join(F.broadcast(known), ["range", "id", "tie"], "left").withColumnRenamed("to", "first_of")
    else:
        marked = ranged.withColumn("first_of", first)
    dealt = marked.select(
        "id", "no_id", "t", "tie", F.explode(F.when(F.col("first_of").isNull(), F.array(F.struct(F.col("range").alias("range"), F.lit(False).alias("ahead")))).otherwise(
            F.array(F.struct(F.col("range").alias("range"), F.lit(False).alias("ahead")), F.struct(F.col("first_of").alias("range"), F.lit(True).alias("ahead"))))).alias("to")
    ).select("to.range", "to.ahead", F.when(F.col("no_id"), None).otherwise(F.col("id")).alias("doc_id"), "id", "tie", "t")
    # a number for each range whose hash is that of a task of its own
    slots = {r["at"]: r["id"] for r in docs.sparkSession.range(64 * n).select("id", F.pmod(F.hash("id"), F.lit(n)).alias("at")).collect()}
    dealt = dealt.withColumn("slot", F.element_at(F.array(*[F.lit(slots.get(k % n, k)).cast("long") for k in range(len(pairs) + 1)]), F.col("range") + 1))
    ordered = dealt.repartition(n, "slot").sortWithinPartitions("range", "ahead", F.desc("id"), F.desc("tie"))

    def run(batches):
        spots = Spots(chain=chain, gap=gap)
        held = None  # (range, doc_id, text) that waits for the next

        def answer(pairs):
            texts = [t for _, t, _ in pairs]
            chars = [t.decode("utf-8", "replace") for t in texts]
            edited = []
            for c, (_, _, nxt) in zip(chars, pairs, strict=True):
                half = len(c) // 2
                # as many code points of the next text lie in four times as many bytes
                edited.append((c[: len(c) - half] + nxt[: 4 * half + 4].decode("utf-8", "ignore")[:half]).encode())
            own = [s for _, x in chunks(texts) for s in spots(x)]
            new = [s for _, x in chunks(edited) for s in spots(x)]
            after = [s for _, x in chunks([n for _, _, n in pairs]) for s in spots(x)]
            return pa.RecordBatch.from_arrays(
                [
                    pa.array([d for d, _, _ in pairs], pa.int64()), pa.array([len(c) for c in chars], pa.int64()), pa.array([hashlib.sha256(e).hexdigest() for e in edited]),
                    pa.array([written(s) for s in own]), pa.array([written(s) for s in new]),
                    pa.array([likeness(a, b) for a, b in zip(own, new, strict=True)], pa.float64()), pa.array([likeness(a, b) for a, b in zip(own, after, strict=True)], pa.float64()),
                ],
                names=["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"],
            )

        for b in batches:
            pairs, size = [], 0
            for rng, ahead, doc, text in zip(*(b.column(k).to_pylist() for k in ("range", "ahead", "doc_id", "t")), strict=True):
                if held is not None and held[0] == rng:
                    pairs.append((held[1], held[2], text))
                    size += len(held[2])
                held = None if ahead else (rng, doc, text)
                if size > 1 << 21:
                    yield answer(pairs)
                    pairs, size = [], 0
            if pairs:
                yield answer(pairs)

    return ordered.mapInArrow(run, _EDITED)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edited_by_next(table(spark, sf_dir, "documents"))


def edits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The columns of the query that SQL can express."""
    return query(spark, sf_dir).select("doc_id", "n_chars", "edited_sha256")


def alike(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of classes of equal fingerprints that are alike, 0.8 or more."""
    return matches(fingerprints(table(spark, sf_dir, "documents").where("doc_id IS NOT NULL")))


EDITS_SQL = """
SELECT doc_id, length(t)::BIGINT AS n_chars, sha256(left(t, length(t) - length(t) // 2) || left(nxt, length(t) // 2)) AS edited_sha256
FROM (SELECT doc_id, t, coalesce(lead(t) OVER w, first_value(t) OVER w) AS nxt FROM (SELECT doc_id, coalesce(text, '') AS t FROM documents) WINDOW w AS (ORDER BY doc_id DESC))
"""
