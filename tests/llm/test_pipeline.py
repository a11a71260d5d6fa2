import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")

DOC = "doc_id long, text string, lang string, source string, n_chars long"


def test_stages_chain(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    counts = [docs.count()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, sf)
        assert docs.columns == columns, name
        from ngramlake.llm.common import spool

        docs = spool(docs, "test")
        counts.append(docs.count())
    assert counts[1] >= 0.9 * counts[0] and counts[2] == counts[1] and counts[3] <= counts[2]
    pieces = corpus_pipeline.STAGES[-1][1](spark, docs, sf)
    assert pieces.count() > 0


def test_hard_rows(spark, sf):
    rows = [(1, None, None, None, None), (1, None, None, None, None), (None, "a text without an id", "en", "s", 1), (2, "", "en", None, 0), (3, "x " * 50_000, "en", "s", 1), (4, "plain words of a clean text", "en", "s", 1)]
    for data in (rows, []):
        docs = spark.createDataFrame([(*r, 0.5, 1, 2) for r in data], DOC + ", score double, n_lines int, stay int").repartition(2)
        for _, stage in corpus_pipeline.STAGES:
            out = stage(spark, docs, sf)
            out.collect()
