"""Edges of the graph rivals: the exact pairs come from blocks, and pruning looks at the kept edges only."""

import numpy as np
import pytest

from quotaknn.functions.distance import distance_pairs
from quotaknn.operators import graph
from quotaknn.plans.index import build_index


@pytest.mark.parametrize("per_cell", [False, True])
def test_edges_equal_brute_force_without_a_row_for_each_pair(spark, monkeypatch, per_cell):
    monkeypatch.setattr(graph, "GROUP", 100)
    rng = np.random.default_rng(3)
    x = rng.integers(0, 3, (400, 4)).astype(float)  # many equal vectors and equal distances
    cell = rng.integers(0, 3, 400)
    rows = [(i, v.tolist(), str(c)) for i, (v, c) in enumerate(zip(x, cell))]
    index = build_index(spark.createDataFrame(rows, "rec_id long, vec array<double>, g string"), ["g"], tables=1)
    edges = graph.knn_edges(index, 5, per_cell)
    plan = edges._jdf.queryExecution().optimizedPlan().toString()
    assert "rec_id" in plan and "Join Inner, NOT" not in plan and "CoGroup" in plan
    want = []
    for i in range(400):
        d = distance_pairs("l2", x[i], x)
        d[i] = np.inf
        if per_cell:
            d[cell != cell[i]] = np.inf
        want += [(i, int(j), float(d[j])) for j in np.lexsort((np.arange(400), d))[:5]]
    assert sorted(map(tuple, edges.collect())) == sorted(want)


def test_pruning_across_batches(spark, monkeypatch):
    """A node's edges go on over Arrow batches; those that stay are as the pairwise rule has them."""
    rng = np.random.default_rng(5)
    x = rng.standard_normal((60, 3))
    index = build_index(spark.createDataFrame([(i, v.tolist(), "a") for i, v in enumerate(x)], "rec_id long, vec array<double>, g string"), ["g"], tables=1)
    near = graph.knn_edges(index, 12)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        got = sorted((r["src"], r["dst"]) for r in graph.pruned(index, near, 6, 1.0).collect())
        plan = graph.pruned(index, near, 6, 1.0)._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert "FlatMapGroups" not in plan.split("MapInArrow")[0]
    pairs = {(r["src"], r["dst"]): r["dist"] for r in near.collect()}
    pairs |= {(b, a): d for (a, b), d in pairs.items()}
    want = []
    for i in range(60):
        kept = []
        for d, j in sorted((d, b) for (a, b), d in pairs.items() if a == i):
            if len(kept) < 6 and not any(np.linalg.norm(x[c] - x[j]) < d for c in kept):
                kept.append(j)
        want += [(i, j) for j in kept]
    assert got == sorted(want)


def test_walks_in_cells_equal_walks_by_joins(spark, monkeypatch):
    rng = np.random.default_rng(8)
    x = rng.integers(0, 4, (300, 3)).astype(float)  # many equal distances
    rows = [(i, v.tolist(), str(i % 3)) for i, v in enumerate(x)]
    index = build_index(spark.createDataFrame(rows, "rec_id long, vec array<double>, g string"), ["g"], tables=1)
    made = graph.build(index, 4, per_cell=True)
    queries = spark.createDataFrame([(i, rng.standard_normal(3).tolist()) for i in range(4)], "query_id long, qvec array<double>")
    starts = queries.select("query_id").crossJoin(made.entries).select("query_id", "scope", "rec_id")
    keys = ["query_id", "scope", "rec_id", "dist"]
    got = sorted(map(tuple, graph.walk_cells(made, index, queries, starts, 6).select(keys).collect()))
    assert got == sorted(map(tuple, graph.walk(made, index, queries, starts, None, 6).select(keys).collect())) and len(got) > 60
    need = index.cells.select("cell_code", "n_cell").crossJoin(queries.select("query_id")).selectExpr("query_id", "0L as group_id", "cell_code", "n_cell", "3 as quota")
    found = []
    for local in (graph.LOCAL, 0):  # cells too large for one task are walked by joins
        monkeypatch.setattr(graph, "LOCAL", local)
        found.append([sorted(map(tuple, d.collect())) for d in graph.retrieve(made, "graph_collection", index, queries, need)])
    assert found[0] == found[1] and found[0][0]
