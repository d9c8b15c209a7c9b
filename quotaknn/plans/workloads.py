"""Query workloads and the experiments, as functions that return one row for each setting."""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from quotaknn.functions.lsh import p_collide
from quotaknn.operators import graph as graphs
from quotaknn.operators import measures, retrieve
from quotaknn.operators.baselines import per_attribute_postings
from quotaknn.operators.search import search
from quotaknn.operators.select import select
from quotaknn.plans.index import build_index, index_bytes
from quotaknn.plans.lineage import bytes_under, cut
from quotaknn.sources.catalog import ATTRS, METRIC, vector_relation
from quotaknn.sources.synth import centre_queries, two_clusters


TURN = 4_294_967_291


def draw_order(query_id: Column, rec_id: Column, seed: int) -> Column:
    """A pseudo-random order of records for each query, in whole numbers that other engines can follow."""
    return F.pmod(F.pmod(rec_id, F.lit(1_000_003)) * 2_654_435_761 + query_id * 40_503_017 + F.lit(seed), F.lit(TURN))


def feasible_queries(vectors: DataFrame, attrs: list[str], n: int, k: int, seed: int = 1, minority: bool = False) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(queries, quotas, exclude): n queries that k records drawn at random satisfy, for sure, together. The counts are those
    records' own; the vector is that of one more record, which the query must not return.

    A query's order of the records is one fixed order of all, turned by a number of its own: so it only meets the few records
    of the ranges from there on, not every record. minority prefers records of small cells, in an order for each query."""
    rows = vectors.where(" and ".join(f"{a} is not null" for a in attrs) or "true").select("rec_id", *attrs)
    asked = vectors.sparkSession.range(n).withColumnRenamed("id", "query_id")
    order = draw_order(F.col("query_id"), F.col("rec_id"), seed)
    total = rows.count()
    parts = total // (16 * (k + 1))
    if parts < 4 or minority:
        drawn = rows.join(F.broadcast(asked))
    else:
        part = lambda at: F.floor(at * parts / float(TURN)).cast("long")
        dealt = rows.withColumn("part_", part(draw_order(F.lit(0), F.col("rec_id"), 0)))
        turn = F.pmod(F.lit(TURN) - F.pmod(F.col("query_id") * 40_503_017 + F.lit(seed), F.lit(TURN)), F.lit(TURN))
        near = asked.withColumn("part_", F.explode(F.array(*[F.pmod(part(turn) + i, F.lit(parts)) for i in range(3)])))
        # the three ranges hold 48 (k + 1) records on average, of which those of the first may lie behind the turn
        drawn = dealt.join(F.broadcast(near), "part_").where(order < 2 * TURN // parts).drop("part_")
        full = drawn.groupBy("query_id").agg(F.count(F.lit(1)).alias("n_")).where(F.col("n_") > k).select("query_id")
        short = asked.join(full, "query_id", "left_anti")
        drawn = drawn.join(full, "query_id", "left_semi").select("rec_id", *attrs, "query_id").unionByName(rows.join(F.broadcast(short)))
    if minority:
        sizes = rows.groupBy(*attrs).agg(F.count(F.lit(1)).alias("n_"))
        drawn = drawn.join(sizes, attrs)
        order = (order % 1024) * F.col("n_") * 4096 + order / 1024 / 4096
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(order, "rec_id"))
    drawn = cut(drawn.withColumn("rank_", rank).where(F.col("rank_") <= k + 1).drop("n_"), "draws")
    values = F.explode(F.array(*[F.struct(F.lit(a).alias("attr"), F.col(a).cast("string").alias("value")) for a in attrs]))
    quotas = drawn.where(F.col("rank_") <= k).select("query_id", values.alias("x_")).select("query_id", "x_.*").groupBy("query_id", "attr", "value").agg(F.count(F.lit(1)).cast("int").alias("need"))
    source = drawn.where(F.col("rank_") == k + 1).select("query_id", "rec_id")
    queries = F.broadcast(source).join(vectors.select("rec_id", F.col("vec").alias("qvec")), "rec_id").select("query_id", "qvec", F.lit(k).alias("k"), F.lit(len(attrs)).alias("m"))
    return cut(queries, "queries"), cut(quotas, "quotas"), source.select("query_id", "rec_id")


def infeasible(quotas: DataFrame, supply: DataFrame) -> DataFrame:
    """The quotas with one need of each query raised above what there is (attr, value, n), the sums kept equal by raising
    one value of each attribute alike."""
    more = supply.groupBy().agg((F.max("n") + 1).cast("int").alias("more_"))
    first = F.row_number().over(Window.partitionBy("query_id", "attr").orderBy("value")) == 1
    return quotas.join(F.broadcast(more)).withColumn("need", F.when(first, F.col("need") + F.col("more_")).otherwise(F.col("need"))).drop("more_")


def together(*steps) -> list:
    """Results of independent steps that nobody times, run at the same time: small jobs mostly wait for one another."""
    with ThreadPoolExecutor(4) as pool:
        return list(pool.map(lambda step: step(), steps))


def compare(index, queries, quotas, exclude, settings: dict[str, dict], n: int, graph=None, truth=None) -> list[tuple]:
    """(setting, success %, recall, DAF of answered, DAF with failures as 0, share scanned, seconds) against the truth. Searches
    run one by one, as they are timed; what they found is judged afterwards."""
    truth = truth or search(index, queries, quotas, retriever="exact", exclude=exclude)
    found = []
    for name, kw in settings.items():
        began = time.monotonic()
        got = search(index, queries, quotas, exclude=exclude, graph=(graph or {}).get(kw.get("retriever")), **kw)
        found.append((name, got, time.monotonic() - began))
    true = cut(truth.answer, "truth"), cut(truth.status, "truth")

    def judged(name, got, seconds):
        answer, status = cut(got.answer, "answer"), cut(got.status, "status")
        success = measures.success_pct(status).head()["success_pct"]
        recall = measures.recall_at_k(answer, true[0]).agg(F.avg("recall")).head()[0]
        d = measures.daf_report(status, true[1]).head()
        share = measures.scanned_share(status, n).agg(F.avg("scanned_share")).head()[0]
        return name, float(success), float(recall or 0), float(d["daf_answered"] or 0), float(d["daf_zeroed"] or 0), float(share or 0), seconds

    return together(*[lambda f=f: judged(*f) for f in found])


COMPARED = "setting string, success_pct double, recall double, daf_answered double, daf_zeroed double, scanned_share double, seconds double"


def _rows(spark: SparkSession, found: list[tuple], extra: str) -> DataFrame:
    return spark.createDataFrame(found, f"{extra}, {COMPARED}")


POLICIES = {
    "cell_lsh": {"retriever": "lsh"}, "per_attribute_lsh": {"retriever": "lsh", "policy": "per_attribute"},
    "independence_lsh": {"retriever": "lsh", "policy": "independence"},
}
GRAPHS = {"graph_filtered_quota": {"retriever": "graph_filtered"}, "graph_collection_fair": {"retriever": "graph_collection"}}


def rivals(index, candidates: str = "exact") -> dict:
    return dict(zip(("graph_filtered", "graph_collection"), together(*[lambda c=c: graphs.build(index, 8, per_cell=c, candidates=candidates) for c in (False, True)])))


def by_k(spark: SparkSession, sf_dir: str, relation: str, ks=(5, 10, 20), n: int = 8, tables: int = 128, m: int = 3, policies: dict | None = None, width: float = 1.0, candidates: str = "exact", sample: int | None = None) -> DataFrame:
    """Quality by k: distance ratio, recall, answered share, share scanned. `sample` makes the collection about that many of
    the relation's records (a stated size of the experiment, as graphs over all of them take long)."""
    attrs = ATTRS[relation][:m]
    vectors = vector_relation(spark, sf_dir, relation)
    if sample:
        vectors = vectors.where(F.pmod(F.xxhash64("rec_id"), F.lit(1 << 20)) < int(min(1.0, sample / max(vectors.count(), 1)) * (1 << 20)))
    vectors = cut(vectors, "vectors")
    index = build_index(vectors, attrs, METRIC.get(relation, "l2"), tables=tables, width=width)
    total, settings = vectors.count(), policies or POLICIES
    graph = rivals(index, candidates) if any(s["retriever"].startswith("graph") for s in settings.values()) else None
    out = []
    for k in ks:
        q, u, x = feasible_queries(vectors, attrs, n, k)
        out += [(k, *row) for row in compare(index, q, u, x, settings, total, graph)]
    return _rows(spark, out, "k int")


def by_m(spark: SparkSession, sf_dir: str, relation: str = "V_EMB5", ms=(1, 2, 3, 4, 5), n: int = 6, k: int = 6, tables: int = 128, with_graphs: bool = True, policies: dict | None = None) -> DataFrame:
    """Quality by the number of attributes."""
    vectors = cut(vector_relation(spark, sf_dir, relation), "vectors")
    total = vectors.count()

    def ready(m: int) -> tuple:
        attrs = ATTRS[relation][:m]
        index = build_index(vectors, attrs, METRIC.get(relation, "l2"), tables=tables)
        q, u, x = feasible_queries(vectors, attrs, n, k)
        graph, truth = together(lambda: rivals(index) if with_graphs else None, lambda: search(index, q, u, retriever="exact", exclude=x))
        return index, q, u, x, graph, truth

    out = []
    for m, (*made, graph, truth) in zip(ms, together(*[lambda m=m: ready(m) for m in ms])):
        out += [(m, *row) for row in compare(*made, (policies or POLICIES) | (GRAPHS if with_graphs else {}), total, graph, truth)]
    return _rows(spark, out, "m int")


def by_parameter(spark: SparkSession, sf_dir: str, relation: str, tables=(4, 16, 64), widths=(1.0,), hashes=(2,), n: int = 8, k: int = 6, policies: dict | None = None) -> DataFrame:
    """Quality of the hash-based policies by tables, width and hashes in a key."""
    attrs = ATTRS[relation][:3]
    vectors = cut(vector_relation(spark, sf_dir, relation), "vectors")
    total = vectors.count()
    q, u, x = feasible_queries(vectors, attrs, n, k)
    out = []
    for t in tables:
        for w in widths:
            for h in hashes:
                index = build_index(vectors, attrs, METRIC.get(relation, "l2"), tables=t, width=w, hashes=h)
                out += [(t, float(w), h, *row) for row in compare(index, q, u, x, policies or POLICIES, total)]
    return _rows(spark, out, "tables int, width double, hashes int")


def plain_retrieval(spark: SparkSession, n_rows: int = 10_000, n: int = 10, k: int = 10, ef: int = 8, degree: int = 8, tables: int = 16, hashes: int = 2, width: float = 0.1) -> DataFrame:
    """Graphs, hashing and exact search without counts on the two-cluster collection, queries near the centre. The graph's
    candidate pairs come from shared buckets, as all pairs would be too many."""
    vectors = cut(two_clusters(spark, n_rows), "vectors")
    queries = cut(centre_queries(spark, n), "queries")
    index = build_index(vectors, ["g1"], tables=tables, hashes=hashes, width=width)
    wide = build_index(vectors, ["g1"], tables=4, hashes=4, width=4.0)
    graph = graphs.build(wide, degree, candidates="lsh")
    truth = cut(retrieve.knn(index, queries, k), "truth")
    out = []
    requests = queries.select("query_id").join(F.broadcast(index.cells)).select("query_id", F.lit(0).cast("long").alias("group_id"), "cell_code", "n_cell", F.lit(k).alias("quota"))
    for name in ("exhaustive", "hash", "graph"):
        began = time.monotonic()
        if name == "exhaustive":
            found, scanned = retrieve.exhaustive(index, queries, requests)
        elif name == "hash":
            found, scanned = retrieve.cell_lsh(index, queries, requests, cap=False)
        else:
            found, scanned = graphs.retrieve(graph, "graph_filtered", wide, queries, requests, ef=max(ef, k))
        found = cut(found, "found")
        seconds = time.monotonic() - began
        hit = truth.join(found.select("query_id", "rec_id"), ["query_id", "rec_id"], "left_semi").count()
        # place by place, so that a retriever that finds few does not look near: what is missing tells in `found_share`
        place = F.row_number().over(Window.partitionBy("query_id").orderBy("dist", "rec_id")).alias("place")
        both = found.select("query_id", place, F.col("dist").alias("d")).join(truth.select("query_id", place, F.col("dist").alias("t")), ["query_id", "place"])
        far, best, n_found = both.agg(F.sum("d"), F.sum("t"), F.count(F.lit(1))).head()
        share = (scanned.agg(F.sum("scanned")).head()[0] or 0) / n_rows / n
        out.append((name, hit / (n * k), n_found / (n * k), float(far / best) if best else None, float(share), seconds))
    return spark.createDataFrame(out, "retriever string, recall double, found_share double, distance_ratio double, scanned_share double, seconds double")


def plain_swept(spark: SparkSession, n_rows: int = 10_000, n: int = 10, k: int = 10, efs=(8, 32), degrees=(8, 16), tables=(4, 16)) -> DataFrame:
    """plain_retrieval over beam widths, out-degrees and numbers of tables."""
    out = None
    for ef, degree, t in [(e, d, tables[-1]) for e in efs for d in degrees] + [(efs[0], degrees[0], t) for t in tables[:-1]]:
        own = plain_retrieval(spark, n_rows, n, k, ef, degree, t).select(F.lit(ef).alias("ef"), F.lit(degree).alias("degree"), F.lit(t).alias("tables"), "*")
        out = own if out is None else out.unionByName(own)
    return out


def selection_times(spark: SparkSession, sf_dir: str, ms=(1, 2, 3), k: int = 20, n: int = 8) -> DataFrame:
    """Solver seconds by number of attributes, over the same kind of pools."""
    vectors = cut(vector_relation(spark, sf_dir, "V_EMB5"), "vectors")
    out = []
    for m in ms:
        attrs = ATTRS["V_EMB5"][:m]
        index = build_index(vectors, attrs, tables=4)
        q, u, x = feasible_queries(vectors, attrs, n, k)
        got = search(index, q, u, retriever="exact", exclude=x, selector="multi" if m > 2 else "auto", select_options={"method": "bnb"} if m > 2 else None)
        r = got.status.agg(F.avg("seconds"), F.avg((F.col("status") == "ok").cast("double"))).head()
        out.append((m, float(r[0]), float(r[1])))
    return spark.createDataFrame(out, "m int, seconds double, answered double")


def flow_or_integer(spark: SparkSession, sf_dir: str, ks=(5, 10, 20, 40), n: int = 8, relation: str = "V_EMB") -> DataFrame:
    """Solver seconds and equal optima of flow and integer search on two attributes."""
    vectors = cut(vector_relation(spark, sf_dir, relation), "vectors")
    attrs = ATTRS[relation][:2]
    index = build_index(vectors, attrs, tables=4)
    out = []
    for k in ks:
        q, u, x = feasible_queries(vectors, attrs, n, k)
        pool = search(index, q, u, retriever="exact", exclude=x).pool
        total = {}
        for name, kw in {"flow": {}, "integer": {"selector": "multi", "method": "bnb"}}.items():
            picked = cut(select(pool, u, attrs, **kw), "picked")
            per = picked.groupBy("query_id").agg(F.sum("dist").alias("d"), F.max("seconds").alias("s"))
            total[name] = per.agg(F.sum("d"), F.avg("s")).head()
        out.append((k, float(total["flow"][1]), float(total["integer"][1]), abs(total["flow"][0] - total["integer"][0]) < 1e-6))
    return spark.createDataFrame(out, "k int, flow_seconds double, integer_seconds double, same_optimum boolean")


def scanned_by(spark: SparkSession, n_rows: int = 10_000, ms=(1, 2, 3), ks=(5, 20), n: int = 5) -> DataFrame:
    """Share of records whose distance is computed, hashing against exact search, on the two-cluster collection."""
    vectors = cut(two_clusters(spark, n_rows), "vectors")
    near = centre_queries(spark, n)
    out = []
    for m in ms:
        attrs = ["g1", "g2", "g3"][:m]
        index = build_index(vectors, attrs, tables=16, width=0.5)
        for k in ks:
            # needs come from the small cluster, so that hashing can meet them
            _, u, _ = feasible_queries(vectors.where("rec_id % 100 = 0"), attrs, n, k)
            for name, kw in {"cell_lsh": {"retriever": "lsh"}, "exhaustive": {"retriever": "exact"}}.items():
                got = search(index, near, u, **kw)
                r = got.status.agg(F.avg("scanned"), F.avg((F.col("status") == "ok").cast("double"))).head()
                out.append((m, k, name, float(r[0]) / n_rows, float(r[1])))
    return spark.createDataFrame(out, "m int, k int, method string, scanned_share double, answered double")


def index_costs(spark: SparkSession, sf_dir: str, relations=("V_EMB", "V_DOC"), settings=((4, 2), (16, 2), (16, 4))) -> DataFrame:
    """Build seconds, bytes and posting rows of the joint index and of an index for each attribute."""
    out = []
    for relation in relations:
        vectors = cut(vector_relation(spark, sf_dir, relation), "vectors")
        for t, h in settings:
            began = time.monotonic()
            index = build_index(vectors, ATTRS[relation][:3], METRIC.get(relation, "l2"), tables=t, hashes=h)
            seconds = time.monotonic() - began
            size = index_bytes(index)
            out.append((relation, "joint", t, h, index.postings.count(), size["postings"] + size["hash_functions"], seconds))
            began = time.monotonic()
            each = cut(per_attribute_postings(index), "postings")
            seconds_each = time.monotonic() - began + index.seconds["dictionary"]
            out.append((relation, "per_attribute", t, h, each.count(), bytes_under(spark, each.stored_at) + size["hash_functions"], seconds_each))
    return spark.createDataFrame(out, "relation string, policy string, tables int, hashes int, posting_rows long, bytes long, seconds double")


def query_times(spark: SparkSession, sf_dir: str, relation: str = "V_LINE", m: int = 2, ks=(5, 20), n: int = 20, tables: int = 16, width: float = 1.0, hashes: int = 2) -> DataFrame:
    """Seconds of a batch by k, hashing against exact search."""
    attrs = ATTRS[relation][:m]
    vectors = cut(vector_relation(spark, sf_dir, relation), "vectors")
    index = build_index(vectors, attrs, METRIC.get(relation, "l2"), tables=tables, width=width, hashes=hashes)
    out = []
    for k in ks:
        q, u, x = feasible_queries(vectors, attrs, n, k)
        for name, kw in {"cell_lsh": {"retriever": "lsh"}, "exhaustive": {"retriever": "exact"}}.items():
            began = time.monotonic()
            got = search(index, q, u, exclude=x, **kw)
            out.append((k, name, time.monotonic() - began, float(got.status.agg(F.avg((F.col("status") == "ok").cast("double"))).head()[0])))
    return spark.createDataFrame(out, "k int, method string, seconds double, answered double")


def planned_coverage(near_angle: float = 0.3, dim: int = 32, n: int = 400, delta: float = 0.2, seeds: int = 20, near: int = 5) -> dict:
    """Monte Carlo over sign families: how often all near points share a bucket with the query under the planned numbers."""
    import numpy as np

    from quotaknn.functions.lsh import Family, plan_cell

    p1, p2 = p_collide("sign", near_angle), p_collide("sign", 1.3)
    plan = plan_cell(n, p1, p2, near, delta)
    hit = 0
    for s in range(seeds):
        rng = np.random.default_rng(s)
        q = rng.standard_normal(dim)
        q /= np.linalg.norm(q)
        side = rng.standard_normal((near, dim))
        side -= np.outer(side @ q, q)
        side /= np.linalg.norm(side, axis=1, keepdims=True)
        x = np.cos(near_angle) * q + np.sin(near_angle) * side
        family = Family("sign", dim, plan["tables"], plan["hashes"], seed=s)
        hit += bool((family.keys(x) == family.keys(q[None])).any(1).all())
    return plan | {"covered": hit / seeds, "promised": 1 - delta / 2}


def times_by_relation(spark: SparkSession, sf_dir: str, relations=("V_EMB", "V_LINE", "V_DOC"), k: int = 20, m: int = 3, n: int = 5) -> DataFrame:
    """Seconds of a batch on several relations, hashing against exact search; distance by relation."""
    out = []
    for relation in relations:
        rows = query_times(spark, sf_dir, relation, min(m, len(ATTRS[relation])), (k,), n).collect()
        out += [(relation, METRIC.get(relation, "l2"), r["method"], r["seconds"], r["answered"]) for r in rows]
    return spark.createDataFrame(out, "relation string, metric string, method string, seconds double, answered double")


def by_metric(spark: SparkSession, sf_dir: str, n: int = 5, k: int = 6, tables: int = 32) -> DataFrame:
    """The same vectors under l2, l1 and cosine distance, each with its own family."""
    vectors = cut(vector_relation(spark, sf_dir, "V_EMB"), "vectors")
    attrs, total, out = ATTRS["V_EMB"], vectors.count(), []
    q, u, x = feasible_queries(vectors, attrs, n, k)
    for metric, hashes, width in (("l2", 2, 1.0), ("l1", 1, 8.0), ("cosine", 4, 1.0)):
        index = build_index(vectors, attrs, metric, tables=tables, hashes=hashes, width=width)
        out += [(metric, *row) for row in compare(index, q, u, x, {"cell_lsh": {"retriever": "lsh"}}, total)]
    return _rows(spark, out, "metric string")


def passages_as_queries(spark: SparkSession, sf_dir: str, k: int = 6) -> DataFrame:
    """All benchmark passages as query vectors over documents, with counts in proportion to the languages."""
    from quotaknn.functions.quota import from_population

    vectors = cut(vector_relation(spark, sf_dir, "V_DOC"), "vectors")
    index = build_index(vectors, ["lang"], "cosine", tables=16, hashes=6)
    queries = cut(vector_relation(spark, sf_dir, "V_BENCH").select(F.col("rec_id").alias("query_id"), F.col("vec").alias("qvec")), "queries")
    needs = from_population(vectors, ["lang"], k).select("attr", "value", "need")
    quotas = cut(queries.select("query_id").join(F.broadcast(needs)), "quotas")
    return search(index, queries, quotas, options={"on_short": "scan"}).status.select("query_id", "status", F.round("total_dist", 6).alias("total_dist"), "scanned")


def near_recall(spark: SparkSession, sf_dir: str, radius: float = 1.25, tables: int = 64) -> DataFrame:
    """query_id, covered, inspected, false_positives against the bound: near points found and far points met in probing."""
    vectors = cut(vector_relation(spark, sf_dir, "V_EMB"), "vectors")
    index = build_index(vectors, ["status"], tables=tables)
    q, u, x = feasible_queries(vectors, ["status"], 6, 6)
    requests = cut(retrieve.cell_requests(index, u), "requests")
    met = retrieve.probe(index, q, requests, cap=False, exclude=x)
    found = cut(retrieve.with_distance(met.join(index.vectors.select("rec_id", "vec"), "rec_id"), index, q).select("query_id", "rec_id", "dist"), "met")
    near = retrieve.within(index, q, requests, radius, x).select("query_id", "rec_id")
    return measures.coverage(found, near).join(measures.false_positives(found, 1.4), "query_id", "full")
