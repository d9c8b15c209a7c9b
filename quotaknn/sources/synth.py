"""The two-cluster collection: a tiny tight cluster at a centre and a large one far away, with attributes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

DOMAINS = {"g1": 3, "g2": 5, "g3": 4}


def _normal(i, j, seed: int):
    """A standard normal number from the record's and the component's number."""
    u = lambda k: (F.pmod(F.xxhash64(i, j, F.lit(seed + k)), F.lit(1 << 52)) + 0.5) / float(1 << 52)
    return F.sqrt(-2 * F.ln(u(0))) * F.cos(2 * 3.141592653589793 * u(1))


def two_clusters(spark: SparkSession, n: int = 10_000, dim: int = 128, near_every: int = 100, near: float = 0.05, away: float = 10.0, skewed: bool = False, seed: int = 5) -> DataFrame:
    """rec_id, vec, g1, g2, g3; every `near_every`-th record lies within about `near` of the origin. Rows are made where they
    are used, from their numbers, so the table needs no source and no shuffle."""
    i = F.col("rec_id")
    is_near = i % near_every == 0
    spread = F.when(is_near, F.lit(near / dim**0.5)).otherwise(F.lit(1.0))
    shift = F.when(is_near, F.lit(0.0)).otherwise(F.lit(away / dim**0.5))
    vec = F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda j: _normal(i, j, seed) * spread + shift)
    rows = spark.range(n).withColumnRenamed("id", "rec_id").withColumn("vec", vec)
    for k, (a, size) in enumerate(DOMAINS.items()):
        draw = F.pmod(F.xxhash64(i, F.lit(seed * 31 + k)), F.lit(size))
        other = F.pmod(F.xxhash64(i, F.lit(seed * 37 + k)), F.lit(size))
        rows = rows.withColumn(a, (F.least(draw, other) if skewed else draw).cast("string"))
    return rows


def centre_queries(spark: SparkSession, n: int = 20, dim: int = 128, noise: float = 0.02, seed: int = 9) -> DataFrame:
    """query_id, qvec: points close to the centre."""
    vec = F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda j: _normal(F.col("id"), j, seed) * (noise / dim**0.5))
    return spark.range(n).select(F.col("id").alias("query_id"), vec.alias("qvec"))
