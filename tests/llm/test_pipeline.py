"""The pipeline's stages against their operators on a small table."""

from pyspark.sql import functions as F

import corpus_pipeline
from structcurve.llm import jaccard
from structcurve.llm.common import table

DATA = "/root/testdata/sf0.001"


def test_stages_keep_columns_and_shrink(spark):
    docs = table(spark, DATA, "documents")
    columns, before = docs.columns, docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, DATA)
        assert docs.columns == columns, name
        after = docs.count()
        assert after <= before, name
        before = after
    assert jaccard.similar_documents(docs).where("n_links > 0").count() == 0


def test_labelled_toxic_documents_go_and_clean_ones_stay(spark):
    labels = table(spark, "/root/testdata/sf0.01", "labels")
    docs = table(spark, "/root/testdata/sf0.01", "documents")
    kept = corpus_pipeline.drop_poor(spark, corpus_pipeline.drop_toxic(spark, docs, "/root/testdata/sf0.01"), "/root/testdata/sf0.01").select("doc_id", F.lit(1).alias("kept"))
    r = labels.join(kept, "doc_id", "left").agg(F.avg(F.when((F.col("toxic") == 0) & (F.col("quality") == 1), F.coalesce("kept", F.lit(0)))).alias("clean"), F.avg(F.when((F.col("toxic") == 1) | (F.col("quality") == 0), F.coalesce("kept", F.lit(0)))).alias("bad")).first()
    assert r.clean > 0.97 and r.bad < 0.25


def test_run(spark):
    out = corpus_pipeline.run(spark, DATA)
    assert {"doc_id", "size", "source_size", "target", "taken"} <= set(out.columns) and 0 < out.count() < 200
