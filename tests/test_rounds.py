"""Exclusions in block scans, draws by ranges, records cut off by a crash, streams without rows, planned keys."""

from pyspark.sql import functions as F

from quotaknn.operators import retrieve
from quotaknn.operators.solvers import branch, cell_dp, flow
from quotaknn.plans import workloads as W
from quotaknn.plans.index import append_index, build_index, postings_of
from quotaknn.plans.lineage import cut, shared_path
from quotaknn.streaming import events as E


def _line(spark, n=20):
    return spark.range(n).select(F.col("id").alias("rec_id"), F.array(F.col("id").cast("double"), F.lit(0.0)).alias("vec"), F.lit("x").alias("g"))


def test_blocks_make_up_for_what_is_excluded(spark):
    index = build_index(_line(spark), ["g"], tables=1)
    q = spark.createDataFrame([(0, [0.0, 0.0]), (1, [19.0, 0.0])], "query_id long, qvec array<double>")
    u = spark.createDataFrame([(0, "g", "x", 3), (1, "g", "x", 2)], "query_id long, attr string, value string, need int")
    x = spark.createDataFrame([(0, 0), (0, 1), (0, 2), (1, 19)], "query_id long, rec_id long")
    requests = retrieve.cell_requests(index, u)
    got = [sorted((r["query_id"], r["rec_id"]) for r in f(index, q, requests, exclude=x)[0].collect()) for f in (retrieve.exhaustive, retrieve.exhaustive_blocks)]
    assert got[0] == got[1] == [(0, 3), (0, 4), (0, 5), (1, 17), (1, 18)]


def test_draws_by_ranges_equal_draws_from_all(spark):
    rows = cut(spark.range(3000).selectExpr("id * 7 as rec_id", "concat('v', id % 5) as g", "array(cast(id as double)) as vec"), "v")
    _, quotas, source = W.feasible_queries(rows, ["g"], 9, 6, seed=3)
    got = {r["query_id"]: r["rec_id"] for r in source.collect()}
    for q in range(9):
        order = sorted((((i * 7) % 1_000_003 * 2_654_435_761 + q * 40_503_017 + 3) % W.TURN, i * 7) for i in range(3000))
        assert got[q] == order[6][1]
    assert quotas.groupBy("query_id").agg(F.sum("need").alias("n")).select("n").distinct().collect()[0][0] == 6


def test_an_append_that_was_cut_off_is_done_again(spark):
    """Postings were written, vectors were not: the records are not held yet, and the next try makes them findable once."""
    v = _line(spark)
    index = build_index(v.where("rec_id < 10"), ["g"], tables=2)
    coded = v.where("rec_id >= 10").withColumn("cell_code", index.dictionary.cell_code())
    postings_of(coded, index.family).write.mode("append").parquet(f"{index.path}/postings")
    path = shared_path(spark, "arrivals")
    v.where("rec_id >= 5").write.parquet(path)
    after = E.ingest(E.read_stream(spark, path, v.schema), index)
    assert sorted(r[0] for r in after.vectors.select("rec_id").collect()) == list(range(20))
    q = spark.createDataFrame([(0, [15.0, 0.0])], "query_id long, qvec array<double>")
    u = spark.createDataFrame([(0, "g", "x", 4)], "query_id long, attr string, value string, need int")
    met = retrieve.probe(after, q, retrieve.cell_requests(after, u), cap=False).groupBy("rec_id").count()
    assert met.where("count > 1").isEmpty() and not met.where("rec_id = 15").isEmpty()


def test_streams_without_rows(spark):
    path = shared_path(spark, "none")
    spark.createDataFrame([], E.EVENTS).write.parquet(path)
    e = E.read_stream(spark, path, spark.createDataFrame([], E.EVENTS).schema)
    assert E.run_to_end(E.tumbling(e), "t", "complete").count() == 0
    assert E.late_rows(e, ["event_id"]).where("late_rows > 0").count() == 0


def test_appended_records_keep_their_cells_plan(spark):
    index = build_index(_line(spark, 16), ["g"], tables=6, hashes=3, per_cell={"p1": 0.9, "p2": 0.3, "near": 2, "delta": 0.5})
    plan = index.cells.head()
    more = append_index(index, _line(spark).where("rec_id >= 16"))
    per = {r["rec_id"]: r["n"] for r in more.postings.groupBy("rec_id").agg(F.count(F.lit(1)).alias("n")).collect()}
    assert plan["hashes"] == 3 and 1 <= plan["tables"] <= 6 and set(per.values()) == {plan["tables"]} and len(per) == 20


def test_flow_equals_the_program_over_cells():
    import random

    rng = random.Random(2)
    for _ in range(150):
        a, b = [f"a{i}" for i in range(rng.randint(1, 4))], [f"b{i}" for i in range(rng.randint(1, 4))]
        costs = {(x, y): sorted(rng.random() for _ in range(rng.randint(0, 4))) for x in a for y in b if rng.random() < 0.8}
        k = rng.randint(1, 6)
        needs = []
        for side in (a, b):
            own = dict.fromkeys(side, 0)
            for _ in range(k):
                own[rng.choice(side)] += 1
            needs.append({v: n for v, n in own.items() if n})
        took, cells = flow(costs, *needs), sorted(costs.items())
        best = cell_dp(cells, needs)
        assert (took is None) == (best is None) == (branch(cells, needs)[0] == "infeasible")
        if took is not None:
            assert abs(sum(sum(costs[e][:n]) for e, n in took.items()) - best[0]) < 1e-9
