import pytest

import __spark_entry__
import corpus_pipeline


@pytest.fixture(scope="module")
def docs(spark, sf_dir):
    rows = spark.read.parquet(f"{sf_dir}/documents.parquet")
    more = spark.createDataFrame([(5000, None, None, "s", None), (5001, "", "en", None, 0), (5002, "write to me@site.org", "en", "s", 20)], rows.schema)
    return rows.unionByName(more)


def test_stages_keep_columns_and_clean_rows(spark, sf_dir, docs):
    now = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, now, sf_dir)
        assert out.columns == now.columns, name
        ids = {r["doc_id"] for r in out.select("doc_id").collect()}
        assert {5000, 5001} <= ids, name
        now = out
    assert "<email>" in now.where("doc_id = 5002").first()["text"]
    assert corpus_pipeline.STAGES[-1][1](spark, now, sf_dir).count() >= now.count()


def test_near_copies_leave_one(spark, sf_dir):
    text = " ".join(f"word{i}" for i in range(100))
    rows = [(3, text), (7, text + " more"), (9, "other words entirely " * 20), (9, "other words entirely " * 20), (None, text)]
    kept = corpus_pipeline.drop_near_copies(spark, spark.createDataFrame(rows, "doc_id long, text string"), sf_dir)
    assert sorted(r["doc_id"] or 0 for r in kept.collect()) == [0, 3, 9]


def test_registered():
    names = __spark_entry__.queries()
    assert "pipeline" in names and all(any(n.startswith(f"op{i}_") for n in names) for i in range(1, 11))
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "line_dedup", "ngram_jaccard", "pii", "packing"]


def test_empty_tables(spark, sf_dir, docs):
    now = docs.limit(0)
    for _, stage in corpus_pipeline.STAGES:
        now = stage(spark, now, sf_dir)
    assert now.count() == 0
