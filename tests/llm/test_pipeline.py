"""Stages of the pipeline against their operators on the smallest tables."""

import pytest

from pathtwin.plans.lineage import settled

corpus_pipeline = pytest.importorskip("corpus_pipeline")


def test_stages(spark):
    d = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert len(names) == 5
    before = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = settled(lambda: stage(spark, before, d))
        assert after.columns == docs.columns and dict(after.dtypes) == dict(docs.dtypes)
        assert after.count() <= before.count()
        if name != "suffix_array_dedup":
            assert after.join(before, ["doc_id", "text"], "left_anti").isEmpty()
        before = after
    left = {r.doc_id for r in before.collect()}
    assert {r.doc_id for r in corpus_pipeline.run(spark, d).collect()} == left


def test_clashing_columns_are_carried(spark):
    from pyspark.sql import functions as F

    d = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{d}/documents.parquet").withColumns({"score": F.lit("a"), "n_words": F.lit("b"), "kept": F.lit("c")})
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, d)
        assert out.columns == docs.columns
        assert {tuple(r) for r in out.select("score", "n_words", "kept").distinct().collect()} == {("a", "b", "c")}
