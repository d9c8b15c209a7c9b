"""The rival policies: an index for each attribute, a joint index with budgets from independence, and naive finishes."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from quotaknn.functions.cells import match_cells, query_cells
from quotaknn.plans.index import Index, postings_of


def per_attribute_requests(index: Index, quotas: DataFrame) -> DataFrame:
    """k records for each constrained (attribute, value), the values' own cells as a group."""
    total = quotas.groupBy("query_id", "attr").agg(F.sum("need").alias("t_")).groupBy("query_id").agg(F.max("t_").cast("int").alias("quota"))
    known = F.broadcast(index.dictionary.frame(index.spark))
    asked = quotas.where("need > 0").join(known, ["attr", "value"]).join(total, "query_id")
    asked = asked.select("query_id", (F.col("attr_no") * 1_000_000 + F.col("code")).cast("long").alias("group_id"), "mask", F.expr("shiftleft(code, shift)").alias("qcode"), "quota")
    masked = index.cells.join(F.broadcast(asked.select("mask").distinct())).withColumn("qcode", F.col("cell_code").bitwiseAND(F.col("mask")))
    return masked.join(asked, ["mask", "qcode"]).select("query_id", "group_id", "cell_code", "n_cell", "quota")


def intersected(found: DataFrame, requests: DataFrame, quotas: DataFrame) -> DataFrame:
    """Records retrieved under every constrained attribute."""
    m = quotas.where("need > 0").groupBy("query_id").agg(F.count_distinct("attr").alias("m_"))
    attr = F.floor(F.col("group_id") / 1_000_000)
    seen = found.groupBy("query_id", "rec_id").agg(F.min("dist").alias("dist"), F.count_distinct(attr).alias("n_"))
    return seen.join(m, "query_id").where("n_ = m_").select("query_id", "rec_id", "dist")


def marginals(index: Index) -> DataFrame:
    """attr, value, prop over the whole collection, from the cell sizes."""
    total = index.cells.agg(F.sum("n_cell").alias("n_"))
    values = F.array(*[F.struct(F.lit(a).alias("attr"), index.dictionary.decode(F.col("cell_code"))[a].alias("value")) for a in index.attrs])
    long = index.cells.select("n_cell", F.explode(values).alias("x_")).select("n_cell", "x_.*").where("value is not null")
    return long.groupBy("attr", "value").agg(F.sum("n_cell").alias("n")).join(F.broadcast(total)).select("attr", "value", "n", (F.col("n") / F.col("n_")).alias("prop"))


def independence_requests(index: Index, quotas: DataFrame) -> DataFrame:
    """ceil(k * product of the values' shares) of each relevant cell, as if attributes were independent."""
    asked = query_cells(quotas, index.dictionary)
    k = quotas.groupBy("query_id", "attr").agg(F.sum("need").alias("t_")).groupBy("query_id").agg(F.max("t_").alias("k_"))
    shares = marginals(index).join(F.broadcast(index.dictionary.frame(index.spark).select("attr", "value", "mask", F.expr("shiftleft(code, shift)").alias("at_"))), ["attr", "value"])
    shares = shares.select(F.col("mask").alias("m_"), "at_", "prop")
    codes = asked.select("mask", "qcode").distinct()
    per = codes.join(F.broadcast(shares), (F.col("mask").bitwiseAND(F.col("m_")) != 0) & (F.col("qcode").bitwiseAND(F.col("m_")) == F.col("at_")))
    per = per.groupBy("mask", "qcode").agg(F.product("prop").alias("prop"))
    budget = F.ceil(F.round(F.col("k_") * F.col("prop"), 9)).cast("int")
    return match_cells(index.cells, asked).join(per, ["mask", "qcode"]).join(k, "query_id").select(
        "query_id", F.col("cell_code").alias("group_id"), "cell_code", "n_cell", budget.alias("quota")
    )


def direct(pool: DataFrame, quotas: DataFrame) -> DataFrame:
    """The pool's k nearest as they are; counts are checked afterwards."""
    k = quotas.groupBy("query_id", "attr").agg(F.sum("need").alias("t_")).groupBy("query_id").agg(F.max("t_").alias("k_"))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy("dist", "rec_id"))
    rows = pool.withColumn("rank_", rank).join(k, "query_id").where("rank_ <= k_")
    return rows.select("query_id", "rec_id", "dist", F.lit("ok").alias("status"), F.lit(0.0).alias("seconds"), F.lit(None).cast("boolean").alias("certified"))


def post_filter(index: Index, queries: DataFrame, quotas: DataFrame, n: int, retriever=None, exclude: DataFrame | None = None) -> DataFrame:
    """The plain n nearest, as a pool to select from."""
    from quotaknn.operators import retrieve
    from quotaknn.operators.search import pool_of

    found = retrieve.knn(index, queries, n, retriever or retrieve.exhaustive, exclude=exclude)
    return pool_of(index, found)


def unconstrained_counts(index: Index, nearest: DataFrame, attr: str) -> DataFrame:
    """How the values of an attribute fall among plain neighbours."""
    return nearest.join(index.vectors.select("rec_id", F.col(attr).alias("value")), "rec_id").groupBy("query_id", "value").agg(F.count(F.lit(1)).alias("n"))


def per_attribute_postings(index: Index) -> DataFrame:
    """The postings that an index for each attribute holds: every record once for each attribute, as many times more."""
    copies = F.explode(F.array(*[F.struct(F.lit(i).alias("no"), F.shiftleft(F.lit(1).cast("long"), 40).alias("top")) for i, _ in enumerate(index.attrs)]))
    rows = index.vectors.select("rec_id", "vec", "cell_code", copies.alias("c_"))
    masks = F.array(*[F.lit(index.dictionary.mask(a)) for a in index.attrs])
    own = F.col("cell_code").bitwiseAND(F.get(masks, F.col("c_.no"))) + F.col("c_.no") * F.col("c_.top")
    return postings_of(rows.select("rec_id", "vec", own.alias("cell_code")), index.family)


def mllib_lsh_candidates(index: Index, queries: DataFrame, threshold: float, seed: int = 42) -> DataFrame:
    """query_id, rec_id, dist by Spark ML's bucketed projections, which OR tables but do not join hashes to longer keys."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    model = BucketedRandomProjectionLSH(inputCol="features", outputCol="hashes", bucketLength=index.family.width, numHashTables=index.family.tables, seed=seed)
    data = index.vectors.select("rec_id", array_to_vector("vec").alias("features"))
    asked = queries.select("query_id", array_to_vector("qvec").alias("features"))
    joined = model.fit(data).approxSimilarityJoin(data, asked, threshold, "dist")
    return joined.select("datasetB.query_id", "datasetA.rec_id", "dist")
