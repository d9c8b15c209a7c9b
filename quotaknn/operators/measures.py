"""Quality and cost measures over answers and statuses."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from quotaknn.functions.distance import distance_block
from quotaknn.functions.lsh import Family, p_collide
from quotaknn.operators.select import _long


def success_pct(status: DataFrame) -> DataFrame:
    """One row: answered share in percent over all queries of the workload."""
    return status.agg(F.count(F.lit(1)).alias("queries"), F.round(100 * F.avg((F.col("status") == "ok").cast("double")), 6).alias("success_pct"))


def daf(status: DataFrame, truth_status: DataFrame) -> DataFrame:
    """query_id, daf (total distance over the truth's; null where either has no answer; 0 over 0 is 1), daf_zeroed (0 where
    the query failed)."""
    t = truth_status.select("query_id", F.col("total_dist").alias("best_"))
    both = status.select("query_id", "total_dist").join(t, "query_id", "left")
    ratio = F.when((F.col("best_") == 0) & (F.col("total_dist") == 0), 1.0).otherwise(F.col("total_dist") / F.nullif(F.col("best_"), F.lit(0.0)))
    return both.select("query_id", ratio.alias("daf"), F.coalesce(ratio, F.lit(0.0)).alias("daf_zeroed"))


def daf_report(status: DataFrame, truth_status: DataFrame) -> DataFrame:
    return daf(status, truth_status).agg(F.round(F.avg("daf"), 6).alias("daf_answered"), F.round(F.avg("daf_zeroed"), 6).alias("daf_zeroed"))


def recall_at_k(answer: DataFrame, truth: DataFrame, tie_aware: bool = False) -> DataFrame:
    """query_id, recall: share of the truth's records found; 0 where the query has no answer. tie_aware also counts a record
    at the same rank and distance (to 1e-9) as a hit."""
    t = truth.select("query_id", "rec_id", "pos", F.col("dist").alias("d_"))
    a = answer.select("query_id", F.col("rec_id").alias("r_"), F.col("pos").alias("p_"), F.col("dist").alias("e_"))
    same = (t.query_id == a.query_id) & (F.col("rec_id") == F.col("r_"))
    hits = t.join(a, same, "left").select(t.query_id, "rec_id", "pos", "d_", F.col("r_").isNotNull().alias("hit"))
    if tie_aware:
        b = answer.select("query_id", F.col("pos").alias("p_"), F.col("dist").alias("e_"))
        hits = hits.join(b, (hits.query_id == b.query_id) & (F.col("pos") == F.col("p_")), "left").select(hits.query_id, (F.col("hit") | F.coalesce(F.abs(F.col("d_") - F.col("e_")) <= 1e-9, F.lit(False))).alias("hit"))
    return hits.groupBy("query_id").agg(F.avg(F.col("hit").cast("double")).alias("recall"))


def scanned_share(status: DataFrame, n: int) -> DataFrame:
    return status.select("query_id", (F.col("scanned") / F.lit(float(max(n, 1)))).alias("scanned_share"))


def quota_gap(answer: DataFrame, quotas: DataFrame, attrs: list[str]) -> DataFrame:
    """query_id, gap: sum over all values of |asked for - returned|."""
    have = _long(answer, attrs).groupBy("query_id", "attr", "value").agg(F.count(F.lit(1)).alias("have"))
    have = have.join(quotas.select("query_id", "attr").distinct(), ["query_id", "attr"], "left_semi")
    both = quotas.join(have, ["query_id", "attr", "value"], "full")
    return both.groupBy("query_id").agg(F.sum(F.abs(F.coalesce("need", F.lit(0)) - F.coalesce("have", F.lit(0)))).cast("long").alias("gap"))


def false_positives(probed: DataFrame, far: float) -> DataFrame:
    """query_id, inspected, false_positives: inspected records farther than `far` (= c R)."""
    return probed.groupBy("query_id").agg(F.count(F.lit(1)).alias("inspected"), F.count(F.when(F.col("dist") > far, 1)).alias("false_positives"))


def coverage(found: DataFrame, near: DataFrame) -> DataFrame:
    """query_id, covered: whether all near records (query_id, rec_id) were retrieved."""
    hit = near.join(found.select("query_id", "rec_id").distinct().withColumn("hit_", F.lit(True)), ["query_id", "rec_id"], "left")
    return hit.groupBy("query_id").agg(F.bool_and(F.coalesce("hit_", F.lit(False))).alias("covered"))


def collision_curve(vectors: DataFrame, family, step: float = 0.1, pairs_of: int = 64) -> DataFrame:
    """band, pairs, agree: how often one base hash agrees by band of l2 distance (angle for sign hashing), over the pairs of
    every record with the first `pairs_of` records; planned is the family's formula at the middle of the band."""
    probe = [(r["rec_id"], r["vec"]) for r in vectors.orderBy("rec_id").limit(pairs_of).collect()]
    q_ids, q = np.array([r for r, _ in probe]), np.array([v for _, v in probe], float)
    shared = vectors.sparkSession.sparkContext.broadcast((q_ids, q, (family.kind, family.dim, family.tables, family.hashes, family.width, family.seed)))

    def run(batches):
        import pyarrow as pa

        q_ids, q, parts = shared.value
        own = Family(*parts)
        hq = own.hash(q).reshape(len(q), -1)
        for b in batches:
            x = b.column(1).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1)
            h = own.hash(x).reshape(len(x), -1)
            d = np.arccos(np.clip(1 - distance_block("cosine", q, x), -1, 1)) if own.kind == "sign" else distance_block("l2", q, x)
            agree = np.stack([(h == row).mean(1) for row in hq])
            other = q_ids[:, None] != b.column(0).to_numpy()[None, :]
            band = np.floor(d / step).astype(np.int64)[other]
            k, inv = np.unique(band, return_inverse=True)
            yield pa.RecordBatch.from_arrays([pa.array(k), pa.array(np.bincount(inv)), pa.array(np.bincount(inv, weights=agree[other]))], names=["band", "pairs", "agree"])

    bands = vectors.select("rec_id", "vec").mapInArrow(run, "band long, pairs long, agree double").groupBy("band").agg(F.sum("pairs").alias("pairs"), (F.sum("agree") / F.sum("pairs")).alias("agree"))
    rows = bands.collect()  # at most the number of bands
    out = [(int(r["band"]), float(r["band"] * step), int(r["pairs"]), float(r["agree"]), p_collide(family.kind, (r["band"] + 0.5) * step, family.width)) for r in rows]
    return vectors.sparkSession.createDataFrame(out, "band long, at_least double, pairs long, agree double, planned double")


def speedup(seconds: dict[str, float], slow: str, fast: str) -> float:
    """How many times as long one method takes as another."""
    return seconds[slow] / max(seconds[fast], 1e-9)
