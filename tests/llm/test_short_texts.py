"""Texts of one or two letters have no n-gram to measure; that is no reason to reject them."""

from pyspark.sql import functions as F

import corpus_pipeline


def test_short_texts_pass(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text", "lang")
    more = spark.createDataFrame([(-1, "A", "en"), (-2, "ab", "en"), (-3, "1.", "en"), (-4, "", "en"), (-5, None, "en")], docs.schema)
    got = corpus_pipeline.language_id(spark, docs.unionByName(more), "").where(F.col("doc_id") < 0)
    assert {r["doc_id"] for r in got.collect()} == {-1, -2}
