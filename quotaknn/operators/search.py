"""End-to-end search: retrieve by a policy, select, verify."""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from quotaknn.operators import baselines, retrieve
from quotaknn.operators.select import select, verify
from quotaknn.plans.index import Index
from quotaknn.plans.lineage import cut


@dataclass
class SearchResult:
    answer: DataFrame  # query_id, pos, rec_id, dist and the attributes
    status: DataFrame  # query_id, status, total_dist, pool_rows, scanned, short_groups, seconds
    pool: DataFrame
    seconds: dict


def pool_of(index: Index, found: DataFrame) -> DataFrame:
    """Candidates with their attributes, each record once for a query."""
    own = index.vectors.select("rec_id", *index.attrs)
    return found.groupBy("query_id", "rec_id").agg(F.min("dist").alias("dist")).join(own, "rec_id").select("query_id", "rec_id", "dist", *index.attrs)


def search(index: Index, queries: DataFrame, quotas: DataFrame, retriever: str = "lsh", policy: str = "cell", selector: str = "auto", scope: str = "coarse",
           finish: str = "select", exclude: DataFrame | None = None, options: dict | None = None, select_options: dict | None = None, graph=None) -> SearchResult:
    """Any retriever (exact, blocks, lsh, graph_filtered, graph_collection) with any policy (cell, per_attribute,
    independence) and any selector (auto, multi). finish = direct returns the policy's own nearest k and only checks the
    counts. Each query gets a status: ok, infeasible (for its pool), invalid, timeout or failed (counts not met)."""
    from quotaknn.operators import graph as graphs

    run = {"exact": retrieve.exhaustive, "blocks": retrieve.exhaustive_blocks, "lsh": retrieve.cell_lsh}
    began = time.monotonic()
    if policy == "cell":
        requests = retrieve.cell_requests(index, quotas, scope)
    elif policy == "per_attribute":
        requests = baselines.per_attribute_requests(index, quotas)
    elif policy == "independence":
        requests = baselines.independence_requests(index, quotas)
    else:
        raise ValueError(f"unknown policy {policy!r}")
    requests = cut(requests, "requests")
    args = dict(options or {})
    if retriever in run:
        found, scanned = run[retriever](index, queries, requests, exclude=exclude, **args)
    else:
        found, scanned = graphs.retrieve(graph, retriever, index, queries, requests, exclude=exclude, **args)
    found = cut(found, "found")
    if policy == "per_attribute":
        pool = baselines.intersected(found, requests, quotas)
    else:
        pool = found
    pool = cut(pool_of(index, pool), "pool")
    seconds = {"retrieve": time.monotonic() - began}
    began = time.monotonic()
    if finish == "direct":
        picked = baselines.direct(pool, quotas)
    else:
        picked = select(pool, quotas, index.attrs, selector, **(select_options or {}))
    picked = cut(picked, "picked")
    own = picked.where("rec_id is not null").select("query_id", "rec_id", "dist").join(pool.drop("dist"), ["query_id", "rec_id"])
    checked = verify(own, quotas, index.attrs)
    heads = queries.select("query_id")
    told = picked.groupBy("query_id").agg(F.max(F.when(F.col("status") != "ok", F.col("status"))).alias("told"), F.sum("dist").alias("total_dist"), F.max("seconds").alias("seconds"))
    rows = pool.groupBy("query_id").agg(F.count(F.lit(1)).alias("pool_rows"))
    asked = requests.groupBy("query_id", "group_id").agg(F.max("quota").alias("quota"))
    short = asked.join(found.groupBy("query_id", "group_id").agg(F.count(F.lit(1)).alias("h_")), ["query_id", "group_id"], "left").where(F.coalesce("h_", F.lit(0)) < F.col("quota"))
    short = short.groupBy("query_id").agg(F.count(F.lit(1)).cast("int").alias("short_groups"))
    status = heads.join(checked, "query_id", "left").join(told, "query_id", "left").join(rows, "query_id", "left").join(scanned, "query_id", "left").join(short, "query_id", "left")
    good = F.coalesce("verified", F.lit(False)) & F.col("told").isNull()
    status = status.select(
        "query_id", F.when(good, "ok").otherwise(F.coalesce("told", F.lit("infeasible" if finish == "select" else "failed"))).alias("status"),
        F.when(good, F.col("total_dist")).alias("total_dist"), F.coalesce("pool_rows", F.lit(0)).alias("pool_rows"),
        F.coalesce("scanned", F.lit(0)).alias("scanned"), F.coalesce("short_groups", F.lit(0)).alias("short_groups"), F.coalesce("seconds", F.lit(0.0)).alias("seconds"),
    )
    ok = status.where("status = 'ok'").select("query_id")
    from pyspark.sql import Window

    pos = F.row_number().over(Window.partitionBy("query_id").orderBy("dist", "rec_id"))
    # status and answer are plans over the small tables written above
    answer = own.join(ok, "query_id", "left_semi").withColumn("pos", pos).select("query_id", "pos", "rec_id", "dist", *index.attrs)
    seconds["select"] = time.monotonic() - began
    return SearchResult(answer, status, pool, seconds)


def quota_knn_1(index: Index, queries: DataFrame, quotas: DataFrame, **options) -> SearchResult:
    """Counts on one attribute."""
    return search(index, queries, quotas, **options)


def quota_knn_2(index: Index, queries: DataFrame, quotas: DataFrame, **options) -> SearchResult:
    """Counts on two attributes."""
    return search(index, queries, quotas, **options)


def quota_knn_m(index: Index, queries: DataFrame, quotas: DataFrame, **options) -> SearchResult:
    """Counts on three attributes or more."""
    return search(index, queries, quotas, selector="multi", **options)
