"""Workloads take all rows they are about."""

from pyspark.sql import functions as F

import __spark_entry__ as entry
from quotaknn.plans import workloads
from quotaknn.plans.lineage import cut
from quotaknn.sources.catalog import table


def test_every_passage_is_a_query(spark, sf):
    ids = {r["item_id"] for r in table(spark, sf, "benchmark").select("item_id").collect()}
    got = entry.queries()["exp_passages_as_queries"](spark, sf).collect()
    assert len(got) == len(ids) == 40 and {r["query_id"] for r in got} == ids
    assert all(r["status"] == "ok" and r["scanned"] > 0 for r in got)


def test_near_points_beyond_ten_thousand(spark, monkeypatch):
    """10,100 records in one place, and 300 at distance 1.2 that one table of buckets cannot all meet."""
    angle = F.col("id") * 0.7
    far = F.when(F.col("id") < 10_100, 0.0).otherwise(1.2)
    v = cut(spark.range(10_400).select(F.col("id").alias("rec_id"), F.array(far * F.cos(angle), far * F.sin(angle)).alias("vec"), F.lit("F").alias("status")), "v")
    monkeypatch.setattr(workloads, "vector_relation", lambda *_: v)
    got = workloads.near_recall(spark, "", tables=1).collect()
    assert len(got) == 6 and not any(r["covered"] for r in got)
