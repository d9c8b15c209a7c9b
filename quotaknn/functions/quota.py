"""Quota queries: a vector and, for each constrained attribute, how many results shall have each value."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

QUERIES = "query_id long, qvec array<double>, k int, m int"
QUOTAS = "query_id long, attr string, value string, need int"


@dataclass
class QuotaQuery:
    query_id: int
    vector: list
    needs: dict = field(default_factory=dict)

    @property
    def k(self) -> int:
        return max((sum(v.values()) for v in self.needs.values()), default=0)


def to_frames(spark: SparkSession, queries: list[QuotaQuery]) -> tuple[DataFrame, DataFrame]:
    heads = [(q.query_id, [float(x) for x in q.vector], q.k, len(q.needs)) for q in queries]
    rows = [(q.query_id, a, str(v), int(n)) for q in queries for a, own in q.needs.items() for v, n in own.items()]
    return spark.createDataFrame(heads, QUERIES), spark.createDataFrame(rows, QUOTAS)


def validate(quotas: DataFrame, dictionary) -> DataFrame:
    """query_id, k, m, reason (null: valid). A query is invalid with a negative need, an attribute or value that the
    dictionary lacks, sums that differ between attributes, or nothing asked for."""
    known = dictionary.frame(quotas.sparkSession).select("attr", "value", F.lit(True).alias("known"))
    rows = quotas.join(F.broadcast(known), ["attr", "value"], "left")
    per = rows.groupBy("query_id", "attr").agg(
        F.sum("need").alias("total"), F.min("need").alias("least"), F.count(F.when(F.col("known").isNull() & (F.col("need") > 0), 1)).alias("strange")
    )
    return per.groupBy("query_id").agg(
        F.max("total").cast("int").alias("k"), F.count(F.lit(1)).cast("int").alias("m"),
        F.when(F.min("least") < 0, "negative").when(F.sum("strange") > 0, "unknown value")
        .when(F.min("total") != F.max("total"), "sums differ").when(F.max("total") <= 0, "nothing asked for").alias("reason"),
    )


def route(quotas: DataFrame) -> DataFrame:
    """query_id, m, variant: which selector a query takes."""
    m = quotas.groupBy("query_id").agg(F.count_distinct("attr").cast("int").alias("m"))
    return m.withColumn("variant", F.when(F.col("m") == 1, "single").when(F.col("m") == 2, "pair").otherwise("multi"))


def from_shares(shares: dict, k: int) -> dict:
    """Counts that add up to k and follow the shares, by largest remainder; ties go to the smaller value."""
    total = sum(shares.values())
    exact = {v: k * s / total for v, s in shares.items()}
    counts = {v: int(x) for v, x in exact.items()}
    for v in sorted(exact, key=lambda v: (counts[v] - exact[v], str(v)))[: k - sum(counts.values())]:
        counts[v] += 1
    return counts


def from_population(vectors: DataFrame, attrs: list[str], k: int) -> DataFrame:
    """attr, value, n, need: counts in proportion to the population, by largest remainder."""
    long = vectors.select(F.explode(F.array(*[F.struct(F.lit(a).alias("attr"), F.col(a).cast("string").alias("value")) for a in attrs])).alias("x"))
    sizes = long.select("x.*").where("value is not null").groupBy("attr", "value").agg(F.count(F.lit(1)).alias("n"))
    whole = Window.partitionBy("attr")
    # whole numbers throughout: floor(k n / N) and the remainder (k n) mod N
    shares = sizes.withColumn("all", F.sum("n").over(whole)).withColumn("low", F.floor(F.col("n") * k / F.col("all"))).withColumn("rest", F.pmod(F.col("n") * k, F.col("all")))
    rank = F.row_number().over(whole.orderBy(F.desc("rest"), "value"))
    return shares.withColumn("more", (rank <= F.lit(k) - F.sum("low").over(whole)).cast("int")).select(
        "attr", "value", "n", (F.col("low") + F.col("more")).cast("int").alias("need")
    )


def quick_infeasible(pool: DataFrame, quotas: DataFrame) -> DataFrame:
    """query_id, short_values: values asked for more often than the pool has them (enough to refuse, not to accept)."""
    attrs = [c for c in pool.columns if c not in ("query_id", "rec_id", "dist", "group_id", "cell_code")]
    long = pool.select("query_id", F.explode(F.array(*[F.struct(F.lit(a).alias("attr"), F.col(a).cast("string").alias("value")) for a in attrs])).alias("x"))
    have = long.select("query_id", "x.*").groupBy("query_id", "attr", "value").agg(F.count(F.lit(1)).alias("have"))
    asked = quotas.where("need > 0").join(have, ["query_id", "attr", "value"], "left")
    return asked.groupBy("query_id").agg(F.count(F.when(F.coalesce("have", F.lit(0)) < F.col("need"), 1)).cast("int").alias("short_values"))


def gadget_from_triples(spark: SparkSession, triples: list[tuple], query_id: int = 0) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The three-dimensional matching gadget: a record for each triple and a need of one for each element."""
    rows = [(i, [float(i)], *map(str, t)) for i, t in enumerate(triples)]
    vectors = spark.createDataFrame(rows, "rec_id long, vec array<double>, x string, y string, z string")
    needs = {a: {str(t[i]): 1 for t in triples} for i, a in enumerate("xyz")}
    return (vectors, *to_frames(spark, [QuotaQuery(query_id, [0.0], needs)]))
