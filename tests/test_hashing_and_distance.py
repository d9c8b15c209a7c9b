import math

import numpy as np
import pytest
from hypothesis import given
from hypothesis import settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from quotaknn.functions import lsh
from quotaknn.functions.distance import distance, distance_block
from quotaknn.plans.workloads import planned_coverage


def test_distances(spark):
    df = spark.createDataFrame([([1.0, 2.0], [4.0, 6.0])], "a array<double>, b array<double>")
    got = df.select(*[distance(m, "a", "b", 3).alias(m) for m in ("l2", "l1", "cosine", "lp")]).head()
    assert got["l2"] == pytest.approx(5) and got["l1"] == pytest.approx(7) and got["lp"] == pytest.approx(91 ** (1 / 3))
    assert got["cosine"] == pytest.approx(0.007722, abs=1e-6)
    zero = spark.createDataFrame([([0.0, 0.0], [1.0, 1.0])], "a array<double>, b array<double>")
    assert zero.select(distance("cosine", "a", "b")).head()[0] == 1.0


@settings(max_examples=30, deadline=None)
@given(st.integers(0, 10_000), st.sampled_from(["l2", "l1", "cosine", "lp"]))
def test_blocks_agree_with_definitions(seed, metric):
    rng = np.random.default_rng(seed)
    q, x = rng.standard_normal((2, 5)), rng.standard_normal((3, 5))
    d = distance_block(metric, q, x, 2.5)
    for i in range(2):
        for j in range(3):
            g = np.abs(q[i] - x[j])
            want = {"l2": math.sqrt((g**2).sum()), "l1": g.sum(), "lp": (g**2.5).sum() ** 0.4, "cosine": 1 - q[i] @ x[j] / np.linalg.norm(q[i]) / np.linalg.norm(x[j])}[metric]
            assert d[i, j] == pytest.approx(want, abs=1e-9)


def test_families_begin_alike():
    x = np.random.default_rng(0).standard_normal((20, 6))
    big, small = lsh.Family("pstable", 6, 8, 4), lsh.Family("pstable", 6, 3, 2)
    assert (big.hash(x)[:, :3, :2] == small.hash(x)).all()
    assert (lsh.Family("pstable", 6, 5, 2).keys(x)[:, :3] == small.keys(x)).all()


def test_keys_do_not_depend_on_partitions(spark):
    rng = np.random.default_rng(1)
    rows = [(i, rng.standard_normal(4).tolist()) for i in range(60)]
    df = spark.createDataFrame(rows, "rec_id long, vec array<double>")
    key = lsh.lsh_keys(lsh.Family("sign", 4, 3, 2))
    one, many = ({r["rec_id"]: r["k"] for r in df.repartition(n).select("rec_id", key(F.col("vec")).alias("k")).collect()} for n in (1, 17))
    assert one == many


def test_planning_numbers():
    assert lsh.inspect_budget(10, 16, 0.1) == 330
    p = lsh.plan_cell(1000, 0.8, 0.4, 10, 0.1)
    assert p["rho"] == pytest.approx(0.2435, abs=1e-4) and p["hashes"] == 8 and p["tables"] == 29
    assert lsh.plan_cell(1, 0.8, 0.4, 10, 0.1)["tables"] == 1
    assert lsh.overall_success(4, 0.1) == pytest.approx(0.8) and lsh.overall_success(1000, 0.1) == 0
    with pytest.raises(ValueError):
        lsh.rho(0.3, 0.5)


def test_collision_chances():
    assert lsh.p_collide("sign", math.pi / 2) == pytest.approx(0.5) and lsh.p_collide("sign", 0) == 1 and lsh.p_collide("sign", math.pi) == pytest.approx(0)
    rng = np.random.default_rng(2)
    x, step = rng.standard_normal(16), rng.standard_normal(16)
    y = x + step / np.linalg.norm(step) * 1.3
    h = lsh.Family("pstable", 16, 1500, 1, 2.0).hash(np.stack([x, y]))
    assert (h[0] == h[1]).mean() == pytest.approx(lsh.p_collide("pstable", 1.3, 2.0), abs=0.04)
    c = lsh.Family("cauchy", 16, 1500, 1, 4.0).hash(np.stack([x, y]))
    assert (c[0] == c[1]).mean() == pytest.approx(lsh.p_collide("cauchy", np.abs(x - y).sum(), 4.0), abs=0.04)


def test_planned_tables_cover_near_points():
    got = planned_coverage(seeds=12)
    assert got["covered"] >= got["promised"] - 0.1
