"""Five stages from raw documents to packed windows, each by one of the text operators.

Every stage takes (spark, docs, sf_dir) and works on all that the stage before kept; all but the last return the columns
of documents. Null texts count as empty, null ids are carried through, extra columns pass, and an empty table stays empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from synthguard.llm import jaccard_join, line_dedup, packing, quality, suffix_dedup
from synthguard.llm.common import staged, table, unstaged
from synthguard.shipping import ship


def _alone(docs: DataFrame) -> DataFrame:
    """The two columns that stages work on, and all columns in one struct, whose names cannot clash with theirs."""
    return docs.select("doc_id", "text", F.struct(*[docs[f"`{c}`"] for c in docs.columns]).alias("whole"))


def _whole(done: DataFrame, docs: DataFrame) -> DataFrame:
    """The columns of docs with the text as it is now; n_chars follows it."""
    now = {"text": F.col("text"), "n_chars": F.length("text").cast("long")}
    return done.select(*[now.get(c, F.col(f"whole.`{c}`")).alias(c) for c in docs.columns])


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier scores 0.3 or more; it learns from the labelled documents among them."""
    model = quality.train(docs, table(spark, sf_dir, "labels"))
    kept = quality.score(_alone(docs), model).where("score >= 0.3")
    return kept.select(*[F.col(f"whole.`{c}`").alias(c) for c in docs.columns])


def drop_common_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines of 20 characters or more that three documents hold stay only in the largest id."""
    ship(spark)
    return _whole(line_dedup.dedup_lines(spark, _alone(docs)), docs)


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents tied by a Jaccard index of 0.8 or more of their five-word shingles, the smallest id; rows without an id stay."""
    ship(spark)
    classes = jaccard_join.similar_classes(spark, docs)
    first = classes.where("component_id = doc_id").select("doc_id").distinct()
    # a semi join keeps the columns of docs alone, whatever their names
    named = docs.where("doc_id IS NOT NULL").join(first, "doc_id", "left_semi").select(*[f"`{c}`" for c in docs.columns])
    return named.unionByName(docs.where("doc_id IS NULL"))


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every byte in a string of 200 bytes that stands twice goes."""
    ship(spark)
    return _whole(suffix_dedup.remove_repeats(spark, _alone(docs)), docs)


def into_windows(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of documents in windows of 4096 tokens."""
    import public_tokenizers

    ship(spark)
    return packing.pack(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("quality_classifier", keep_quality),
    ("line_dedup", drop_common_lines),
    ("ngram_jaccard_join", one_of_each),
    ("suffix_array_dedup", cut_repeats),
    ("packing", into_windows),
]
#: SQL can express neither the classifier nor the packing.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        docs = staged(spark, stage(spark, docs, sf_dir), name)
        if before is not None:
            unstaged(spark, before)
        before = docs
    return docs
