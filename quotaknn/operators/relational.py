"""Relational work around the searches: joins of several kinds, rankings, set operations, features and samples."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def salted_top_k(rows: DataFrame, keys: list[str], order: list[str], k: int, salts: int = 16) -> DataFrame:
    """Top k of each group in two phases, so that a group of any size is first cut in `salts` places."""
    salt = F.pmod(F.xxhash64(*order), F.lit(salts))
    first = F.row_number().over(Window.partitionBy(*keys, "salt_").orderBy(*order))
    then = F.row_number().over(Window.partitionBy(*keys).orderBy(*order))
    cut = rows.withColumn("salt_", salt).withColumn("r_", first).where(F.col("r_") <= k).drop("r_", "salt_")
    return cut.withColumn("rank", then).where(F.col("rank") <= k)


def range_join(points: DataFrame, at: str, spans: DataFrame, low: str, high: str, width: float) -> DataFrame:
    """Rows with low <= at <= high: both sides are put in bins of `width`, joined by bin, then checked."""
    bins = F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width)))
    left = points.withColumn("bin_", F.floor(F.col(at) / width))
    return left.join(spans.withColumn("bin_", bins), "bin_").where((F.col(at) >= F.col(low)) & (F.col(at) <= F.col(high))).drop("bin_")


def stratified(rows: DataFrame, by: str, key: str, share: float, seed: int = 3) -> DataFrame:
    """The same share of each value of `by`, drawn by a hash of the key; the same rows on every run."""
    rank = F.percent_rank().over(Window.partitionBy(by).orderBy(F.pmod(F.col(key) * 2_654_435_761 + seed, F.lit(4_294_967_291)), key))
    return rows.withColumn("r_", rank).where(F.col("r_") < share).drop("r_")


def prefix_costs(pool: DataFrame, keys: list[str]) -> DataFrame:
    """take, cost: what the nearest 1, 2, ... records of each cell cost together (a convex curve)."""
    w = Window.partitionBy(*keys).orderBy("dist", "rec_id")
    rows = pool.withColumn("take", F.row_number().over(w)).withColumn("cost", F.sum("dist").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return rows.withColumn("step", F.col("dist") - F.lag("dist", 1, 0.0).over(w))


def choose_width(distances: DataFrame, column: str = "dist") -> DataFrame:
    """Quantiles of distance from a mergeable sketch, to choose the bucket width and the radius."""
    q = F.percentile_approx(column, [0.01, 0.1, 0.5, 0.9], 10_000)
    return distances.agg(q.alias("q")).select(*[F.get("q", F.lit(i)).alias(n) for i, n in enumerate(("q01", "q10", "q50", "q90"))])
