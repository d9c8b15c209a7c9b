"""Selection solvers against each other and against plain enumeration."""

import random

import pytest

from quotaknn.operators.select import select_multi
from quotaknn.operators.solvers import TooManyStates, branch, cell_dp, certified, enumerate_sets, flow, greedy


def instance(seed, m, records=14, k=4):
    rng = random.Random(seed)
    rows = [(tuple(rng.choice("abc"[: 2 + j % 2]) for j in range(m)), round(rng.uniform(1, 9), 3)) for _ in range(records)]
    picked = rng.sample(rows, k)
    needs = [{} for _ in range(m)]
    for values, _ in picked:
        for j, v in enumerate(values):
            needs[j][v] = needs[j].get(v, 0) + 1
    if seed % 5 == 4:  # sometimes out of reach
        needs[0] = {"a": k}
        needs[-1] = {"b": k} if m > 1 else {"a": k}
    groups = {}
    for values, d in rows:
        groups.setdefault(values, []).append(d)
    cells = [(c, sorted(groups[c])) for c in sorted(groups)]
    return rows, cells, needs


@pytest.mark.parametrize("m", [1, 2, 3, 4])
@pytest.mark.parametrize("seed", range(12))
def test_solvers_agree(seed, m):
    rows, cells, needs = instance(seed, m)
    want = enumerate_sets(rows, needs)
    dp = cell_dp(cells, needs)
    status, cost, took = branch(cells, needs)
    if want is None:
        assert dp is None and status == "infeasible"
        return
    assert dp[0] == pytest.approx(want[0]) and status == "ok" and cost == pytest.approx(want[0])
    for j, own in enumerate(needs):
        for v, n in own.items():
            assert sum(t for (values, _), t in zip(cells, took) if values[j] == v) == n
    if m == 2:
        got = flow(dict(cells), *needs)
        assert sum(sum(dict(cells)[e][:n]) for e, n in got.items()) == pytest.approx(want[0])
        assert certified(dict(cells), got)


def test_pool_of_the_nearest_holds_an_optimum():
    for seed in range(10):
        rows, cells, needs = instance(seed, 3, records=16)
        small = [(c, d[: min(needs[j].get(v, 0) for j, v in enumerate(c))]) for c, d in cells]
        a, b = cell_dp(cells, needs), cell_dp(small, needs)
        assert (a is None) == (b is None) and (a is None or a[0] == pytest.approx(b[0]))


def test_attribute_order_does_not_matter():
    _, cells, needs = instance(3, 3)
    turned = [(tuple(reversed(c)), d) for c, d in cells]
    assert cell_dp(cells, needs)[0] == pytest.approx(branch(turned, needs[::-1])[1])


def test_three_dimensional_matching():
    yes = [((1, 1, 1), [0.0]), ((2, 2, 2), [0.0])]
    no = [((1, 1, 1), [0.0]), ((2, 1, 2), [0.0]), ((1, 2, 2), [0.0])]
    needs = [{1: 1, 2: 1}] * 3
    assert branch(yes, needs)[0] == "ok" and branch(no, needs)[0] == "infeasible"
    assert cell_dp(no, needs) is None


def test_out_of_time_is_not_infeasible():
    _, cells, needs = instance(1, 3)
    assert branch(cells, needs, node_limit=0)[0] == "timeout"


def test_greedy_meets_the_needs():
    for seed in range(8):
        rows, _, needs = instance(seed, 2)
        got = greedy(rows, needs)
        if got is not None:
            assert sorted(rows[i][0][0] for i in got) == sorted(v for v, n in needs[0].items() for _ in range(n))


def test_program_stops_at_its_states_and_the_search_takes_over(spark):
    rng = random.Random(5)
    rows = [(0, i, rng.random(), f"x{rng.randrange(3)}", f"y{rng.randrange(3)}", f"z{rng.randrange(3)}") for i in range(60)]
    needs = [(0, a, f"{a}{v}", 2) for a in "xyz" for v in range(3)]
    pool = spark.createDataFrame(rows, "query_id long, rec_id long, dist double, x string, y string, z string")
    quotas = spark.createDataFrame(needs, "query_id long, attr string, value string, need int")
    totals = {round(sum(r["dist"] for r in select_multi(pool, quotas, ["x", "y", "z"], **kw).collect()), 9) for kw in ({}, {"dp_states": 5}, {"method": "bnb"}, {"method": "dp"})}
    assert len(totals) == 1
    cells = [((f"x{a}", f"y{b}", f"z{c}"), [0.1 * a + 0.01 * b + c, 3.0]) for a in range(3) for b in range(3) for c in range(3)]
    with pytest.raises(TooManyStates):
        cell_dp(cells, [{f"{n}{v}": 2 for v in range(3)} for n in "xyz"], 5)


def test_search_ends_where_few_records_meet_the_counts():
    """Five attributes, one record of each cell: the greedy solution and the program agree with the search."""
    rng = random.Random(8)
    for _ in range(20):
        cells = sorted({tuple(f"{j}{rng.randrange(2)}" for j in range(5)) for _ in range(14)})
        cells = [(c, [rng.random()]) for c in cells]
        chosen = rng.sample(range(len(cells)), 4)
        needs = [{} for _ in range(5)]
        for i in chosen:
            for j, v in enumerate(cells[i][0]):
                needs[j][v] = needs[j].get(v, 0) + 1
        want = cell_dp(cells, needs)
        status, cost, _ = branch(cells, needs)
        assert status == "ok" and abs(cost - want[0]) < 1e-9
        got = greedy([(c, d) for c, own in cells for d in own], needs)
        assert got is None or sum(cells[i][1][0] for i in got) >= want[0] - 1e-9
