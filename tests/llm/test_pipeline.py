"""The pipeline against brute force, stage by stage, and its odd cases."""

import pytest

import corpus_pipeline
from tests.llm.test_operators import ROWS, TEXTS, _jaccard_classes


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    base = str(tmp_path_factory.mktemp("tables"))
    rows = [(i, t, lang, "src", len(t or "")) for i, t, lang, *_ in ROWS]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{base}/documents.parquet")
    spark.createDataFrame([(i, 1, 0) for i in range(0, 60, 2)], "doc_id long, quality int, toxic int").write.parquet(f"{base}/labels.parquet")
    return base


def test_stages(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert len(names) == 5 and names[2] == "ngram_jaccard_join"
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, folder)
        assert out.columns == docs.columns
        if name == "ngram_jaccard_join":
            want = _jaccard_classes([(r["doc_id"], r["text"]) for r in docs.collect() if r["doc_id"] is not None], 5, 80)
            assert {r["doc_id"] for r in out.collect()} == {i for i, (_, c) in want.items() if c == i} | {None}
        path = f"{folder}/{name}"
        out.write.parquet(path)
        docs = spark.read.parquet(path)
    assert 0 < docs.count() <= len(TEXTS) + 1
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, folder)
    assert packed.groupBy("doc_id").count().count() == docs.select("doc_id").distinct().count()


def test_empty_table(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs, folder).count() == 0
