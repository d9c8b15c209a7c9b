from pyspark.sql import functions as F

from quotaknn.functions import cells as C
from quotaknn.operators import retrieve
from quotaknn.plans.index import build_index, load_index
from quotaknn.plans.workloads import feasible_queries
from quotaknn.sources.catalog import table, vector_relation
from quotaknn.streaming import events as E


def plan(df) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def test_matching_is_a_hash_join(spark, sf):
    v = vector_relation(spark, sf, "V_EMB")
    index = build_index(v, ["status", "priority"], tables=1)
    _, u, _ = feasible_queries(v, ["status", "priority"], 3, 4)
    asked = C.query_cells(u, index.dictionary)
    assert "HashJoin" in plan(C.match_cells(index.cells, asked)) or "SortMergeJoin" in plan(C.match_cells(index.cells, asked))
    assert "NestedLoopJoin" in plan(C.match_cells_xor(index.cells, asked))


def test_top_k_is_cut_before_the_shuffle(spark, sf):
    v = vector_relation(spark, sf, "V_EMB")
    index = build_index(v, ["status"], tables=1)
    q, u, x = feasible_queries(v, ["status"], 3, 4)
    found, _ = retrieve.exhaustive(index, q, retrieve.cell_requests(index, u))
    assert "WindowGroupLimit" in plan(found)


def test_filters_and_columns_reach_the_scan(spark, sf):
    v = vector_relation(spark, sf, "V_EMB")
    index = build_index(v, ["status"], tables=4)
    text = plan(index.postings.where("table_no = 1 and cell_code = 2").select("rec_id"))
    assert "PushedFilters" in text and "EqualTo(table_no,1)" in text and "EqualTo(cell_code,2)" in text
    assert "vec" not in plan(index.vectors.select("rec_id", "cell_code")).split("ReadSchema")[1].split("\n")[0]


def test_stored_index_is_the_same(spark, sf):
    v = vector_relation(spark, sf, "V_EMB")
    index = build_index(v, ["status", "priority"], tables=3)
    again = load_index(spark, index.path)
    assert again.family == index.family and again.dictionary == index.dictionary
    assert again.postings.exceptAll(index.postings).isEmpty() and again.postings.count() == 3 * v.count()


def test_cells_keep_the_tables_they_need(spark, sf):
    v = vector_relation(spark, sf, "V_EMB")
    index = build_index(v, ["status", "priority"], tables=64, per_cell={"p1": 0.9, "p2": 0.3, "near": 2, "delta": 0.5})
    per = index.postings.groupBy("cell_code").agg(F.count_distinct("table_no").alias("t")).join(index.cells, "cell_code").collect()
    assert all(1 <= r["t"] < 64 for r in per)


def test_stream_equals_batch(spark, sf):
    e = table(spark, sf, "events")
    stream = E.read_stream(spark, f"{sf}/events.parquet*", e.schema).withColumn("ts", F.col("ts").cast("timestamp"))
    got = E.run_to_end(E.tumbling(stream), "t", "complete")
    want = e.groupBy(F.date_trunc("hour", "ts").cast("timestamp").alias("start"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    assert got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty()
