"""Candidate retrieval for batches of requests.

A request (query_id, group_id, cell_code, quota) asks for the `quota` records nearest to the query within a group of cells.
Retrievers differ in how they look; each returns query_id, group_id, rec_id, dist and, in `scanned`, how many records had
their distance computed for the query.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from quotaknn.functions.cells import match_cells, query_cells
from quotaknn.functions.distance import distance, distance_block
from quotaknn.functions.lsh import lsh_keys
from quotaknn.plans.index import Index
from quotaknn.plans.lineage import cut


def cell_requests(index: Index, quotas: DataFrame, scope: str = "coarse") -> DataFrame:
    """The paper's policy: k_cell of each relevant cell. Fine groups are cells; coarse groups unite the cells that are equal
    in the constrained attributes, which keeps an optimum in a smaller pool."""
    matched = match_cells(index.cells, query_cells(quotas, index.dictionary))
    group = F.col("qcode") if scope == "coarse" else F.col("cell_code")
    return matched.select("query_id", group.alias("group_id"), "cell_code", "n_cell", F.col("k_cell").alias("quota"))


def nearest(found: DataFrame, most: int) -> DataFrame:
    """The `quota` nearest of each (query, group), ties by record. The literal bound lets Spark keep only `most` rows of a
    group in each task before the shuffle."""
    order = Window.partitionBy("query_id", "group_id").orderBy("dist", "rec_id")
    return found.withColumn("rank_", F.row_number().over(order)).where((F.col("rank_") <= most) & (F.col("rank_") <= F.col("quota"))).drop("rank_", "quota")


def most_asked(requests: DataFrame) -> int:
    return requests.agg(F.max("quota")).head()[0] or 0


def scan_counts(found: DataFrame) -> DataFrame:
    return found.groupBy("query_id").agg(F.count_distinct("rec_id").alias("scanned"))


def cells_scanned(requests: DataFrame) -> DataFrame:
    """What a scan of all cells asked for compares, from the cell sizes: no row is counted again."""
    return requests.select("query_id", "cell_code", "n_cell").distinct().groupBy("query_id").agg(F.sum("n_cell").alias("scanned"))


def with_distance(pairs: DataFrame, index: Index, queries: DataFrame) -> DataFrame:
    q = queries.select("query_id", "qvec")
    return pairs.join(q, "query_id").withColumn("dist", distance(index.metric, "vec", "qvec")).drop("vec", "qvec")


def exhaustive(index: Index, queries: DataFrame, requests: DataFrame, exclude: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """Exact distances to every record of the cells asked for; (candidates, scanned)."""
    rows = index.vectors.select("rec_id", "vec", "cell_code").join(requests.select("query_id", "group_id", "cell_code", "quota"), "cell_code")
    found = with_distance(_without(rows, exclude), index, queries).select("query_id", "group_id", "rec_id", "dist", "quota")
    return nearest(found, most_asked(requests)), cells_scanned(requests)


def within(index: Index, queries: DataFrame, requests: DataFrame, radius: float, exclude: DataFrame | None = None) -> DataFrame:
    """query_id, rec_id, dist of all records of the cells asked for that are no farther than `radius`, however many."""
    rows = index.vectors.select("rec_id", "vec", "cell_code").join(requests.select("query_id", "cell_code").distinct(), "cell_code")
    found = with_distance(_without(rows, exclude), index, queries)
    return found.where(F.col("dist") <= radius).select("query_id", "rec_id", "dist")


def _without(rows: DataFrame, exclude: DataFrame | None) -> DataFrame:
    return rows if exclude is None else rows.join(exclude.select("query_id", "rec_id"), ["query_id", "rec_id"], "left_anti")


def probe(index: Index, queries: DataFrame, requests: DataFrame, delta: float = 0.1, cap: bool = True, keep: str = "first", probes: int = 1,
          exclude: DataFrame | None = None) -> DataFrame:
    """query_id, group_id, rec_id, quota of the records met in the tables: those that share a bucket with the query in one of
    its cells, once each, at most k* = quota + ceil(2 tables / delta) of a group. keep = first: by table, then record, as
    they are met; most_collisions: those met in most tables. probes > 1 also looks into that many neighbouring buckets on
    each side of the last hash."""
    family = index.family
    planned = "hashes" in index.cells.columns
    lengths = range(1, family.hashes + 1) if planned else [family.hashes]
    own = [queries.select("query_id", F.lit(n).alias("hashes"), F.posexplode(lsh_keys(family.prefix(n))(F.col("qvec"))).alias("table_no", "bucket")) for n in lengths]
    keys = reduce(DataFrame.unionByName, own)
    if probes > 1:
        around = F.explode(F.sequence(F.lit(1 - probes), F.lit(probes - 1)))
        keys = keys.withColumn("off_", around).select("query_id", "hashes", "table_no", (F.col("bucket") + F.col("off_")).alias("bucket"))
    wanted = requests.select("query_id", "group_id", "cell_code", "quota")
    if planned:  # each cell is asked by keys as long as its own
        wanted = wanted.join(index.cells.select("cell_code", "hashes"), "cell_code").join(keys, ["query_id", "hashes"])
    else:
        wanted = wanted.join(keys, "query_id")
    # the same posting twice, as after an append that was tried again, is one
    met = index.postings.join(wanted.drop("hashes"), ["cell_code", "table_no", "bucket"])
    met = met.groupBy("query_id", "group_id", "rec_id").agg(F.min("table_no").alias("first_"), F.count_distinct("table_no", "bucket").alias("times_"), F.first("quota").alias("quota"))
    met = _without(met, exclude)
    if not cap:
        return met.select("query_id", "group_id", "rec_id", "quota")
    extra = -int(-2 * family.tables // delta)
    order = [F.asc("first_"), F.asc("rec_id")] if keep == "first" else [F.desc("times_"), F.asc("first_"), F.asc("rec_id")]
    rank = F.row_number().over(Window.partitionBy("query_id", "group_id").orderBy(*order))
    bound = most_asked(requests) + extra
    kept = met.withColumn("rank_", rank).where((F.col("rank_") <= bound) & (F.col("rank_") <= F.col("quota") + extra))
    return kept.select("query_id", "group_id", "rec_id", "quota")


def cell_lsh(index: Index, queries: DataFrame, requests: DataFrame, delta: float = 0.1, cap: bool = True, keep: str = "first", probes: int = 1,
             on_short: str = "keep", scan_below: int = 0, exclude: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """Hash retrieval for all (query, cell) pairs at once; (candidates, scanned).

    Short groups keep what was met (on_short = keep) or are scanned (scan). Cells of at most `scan_below` records are scanned
    from the start, as probing them costs more."""
    small = requests.where(F.col("n_cell") <= scan_below) if scan_below else None
    large = requests.where(F.col("n_cell") > scan_below) if scan_below else requests
    met = probe(index, queries, large, delta, cap, keep, probes, exclude)
    if small is not None:
        rows = index.vectors.select("rec_id", "cell_code").join(small.select("query_id", "group_id", "cell_code", "quota"), "cell_code").drop("cell_code")
        met = met.unionByName(_without(rows, exclude)).dropDuplicates(["query_id", "group_id", "rec_id"])
    if on_short == "scan":
        sizes = requests.groupBy("query_id", "group_id").agg(F.sum("n_cell").alias("n_"), F.max("quota").alias("q_"))
        have = met.groupBy("query_id", "group_id").agg(F.count(F.lit(1)).alias("h_"))
        short = sizes.join(have, ["query_id", "group_id"], "left").where(F.coalesce("h_", F.lit(0)) < F.least("n_", "q_")).select("query_id", "group_id")
        again = requests.join(short, ["query_id", "group_id"], "left_semi").select("query_id", "group_id", "cell_code", "quota")
        rows = index.vectors.select("rec_id", "cell_code").join(again, "cell_code").drop("cell_code")
        met = met.unionByName(_without(rows, exclude)).dropDuplicates(["query_id", "group_id", "rec_id"])
    found = with_distance(met.join(index.vectors.select("rec_id", "vec"), "rec_id"), index, queries).select("query_id", "group_id", "rec_id", "dist", "quota")
    found = cut(found, "met")  # read by both results
    return nearest(found, most_asked(requests)), scan_counts(found)


def exhaustive_blocks(index: Index, queries: DataFrame, requests: DataFrame, most_queries: int = 5_000, most_requests: int = 2_000_000, exclude: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """The same as exhaustive, with distances by matrix products: each batch of vectors meets the whole batch of queries
    (checked to be at most `most_queries`, their requests at most `most_requests`) and keeps its own nearest of each group, and
    as many more as the query excludes, so little is shuffled."""
    asked = queries.select("query_id", "qvec").limit(most_queries + 1).collect()
    wanted = requests.select("query_id", "group_id", "cell_code", "quota").limit(most_requests + 1).collect()
    if len(asked) > most_queries or len(wanted) > most_requests:
        raise ValueError(f"more than {most_queries} queries or {most_requests} requests in a batch; use exhaustive or smaller batches")
    ids = [r["query_id"] for r in asked]
    number = {k: i for i, k in enumerate(ids)}
    q = np.array([r["qvec"] for r in asked], float)
    more = {} if exclude is None else {r["query_id"]: r["n"] for r in exclude.join(queries.select("query_id"), "query_id").groupBy("query_id").agg(F.count(F.lit(1)).alias("n")).collect()}
    wants: dict = {}
    for r in wanted:
        wants.setdefault(r["cell_code"], []).append((number[r["query_id"]], r["group_id"], r["quota"], r["quota"] + more.get(r["query_id"], 0)))
    shared = index.spark.sparkContext.broadcast((ids, q, wants))
    metric = index.metric

    def run(batches):
        import pyarrow as pa

        ids, q, wants = shared.value
        for b in batches:
            rec, cell = b.column(0).to_numpy(), b.column(2).to_numpy()
            x = b.column(1).flatten().to_numpy(zero_copy_only=False).reshape(len(rec), -1)
            out: list[list] = [[], [], [], [], []]
            for c in np.unique(cell).tolist():
                if c not in wants:
                    continue
                at = np.flatnonzero(cell == c)
                rows = sorted({w[0] for w in wants[c]})
                place = {i: n for n, i in enumerate(rows)}
                d = distance_block(metric, q[rows], x[at])
                for i, group, quota, keep in wants[c]:
                    own = d[place[i]]
                    near = np.lexsort((rec[at], own))[:keep]
                    for o, v in zip(out, ([ids[i]] * len(near), [group] * len(near), rec[at][near], own[near], [quota] * len(near))):
                        o.extend(v)
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.int32()]
            yield pa.RecordBatch.from_arrays([pa.array(o, t) for o, t in zip(out, kinds)], names=["query_id", "group_id", "rec_id", "dist", "quota"])

    found = index.vectors.select("rec_id", "vec", "cell_code").mapInArrow(run, "query_id long, group_id long, rec_id long, dist double, quota int")
    return nearest(_without(found, exclude), most_asked(requests)), cells_scanned(requests)


def knn(index: Index, queries: DataFrame, k: int, retriever=exhaustive, predicate=None, **options) -> DataFrame:
    """Plain k nearest without counts, over all cells or those whose values pass the predicate (a Column over attributes)."""
    cells = index.cells.select("cell_code", "n_cell")
    if predicate is not None:
        named = cells.select("*", index.dictionary.decode(F.col("cell_code")).alias("v_")).select("cell_code", "n_cell", "v_.*")
        cells = named.where(predicate).select("cell_code", "n_cell")
    requests = queries.select("query_id").crossJoin(cells).select("query_id", F.lit(0).cast("long").alias("group_id"), "cell_code", "n_cell", F.lit(k).alias("quota"))
    found, _ = retriever(index, queries, requests, **options)
    return found.select("query_id", "rec_id", "dist")
