"""Selection of the answer from a pool: exactly the counts asked for, least total distance.

One attribute is a window; two and more are solved per query in Python workers, each holding one query's pool, which is
bounded by the needs and not by the data.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from quotaknn.operators.solvers import TooManyStates, branch, cell_dp, certified, flow, greedy

ANSWER = "query_id long, rec_id long, dist double"
PICKED = "query_id long, rec_id long, dist double, status string, seconds double, certified boolean"


def _long(pool: DataFrame, attrs: list[str]) -> DataFrame:
    values = F.array(*[F.struct(F.lit(a).alias("attr"), F.col(a).cast("string").alias("value")) for a in attrs])
    return pool.select("query_id", "rec_id", "dist", F.explode(values).alias("x_")).select("query_id", "rec_id", "dist", "x_.*")


def select_single(pool: DataFrame, quotas: DataFrame, attrs: list[str]) -> DataFrame:
    """One attribute: the nearest `need` records of each value. Records of a value not asked for are left."""
    asked = quotas.where("need > 0")
    rank = F.row_number().over(Window.partitionBy("query_id", "attr", "value").orderBy("dist", "rec_id"))
    return _long(pool, attrs).join(asked, ["query_id", "attr", "value"]).withColumn("rank_", rank).where(F.col("rank_") <= F.col("need")).select("query_id", "rec_id", "dist")


def _grouped(pool: DataFrame, quotas: DataFrame, attrs: list[str], solve) -> DataFrame:
    needs = quotas.where("need > 0").groupBy("query_id").agg(F.to_json(F.map_from_entries(F.collect_list(F.struct(F.concat_ws("\x1f", "attr", "value"), "need")))).alias("needs_"))
    rows = pool.join(needs, "query_id").select("query_id", "rec_id", "dist", "needs_", *[F.col(a).cast("string").alias(a) for a in attrs])

    def run(pdf):
        import json
        import time

        import pandas as pd

        needs_by: dict = {}
        for key, n in json.loads(pdf["needs_"].iloc[0]).items():
            a, v = key.split("\x1f", 1)
            needs_by.setdefault(a, {})[v] = n
        own = [a for a in attrs if a in needs_by]
        needs = [needs_by[a] for a in own]
        pdf = pdf.sort_values(["dist", "rec_id"])
        began = time.perf_counter()
        if len(own) < len(needs_by):
            got = ("invalid", None, None)
        else:
            groups: dict = {}
            for values, rec, dist in zip(zip(*[pdf[a] for a in own]), pdf["rec_id"], pdf["dist"]):
                if all(v in n for v, n in zip(values, needs)):
                    groups.setdefault(values, []).append((dist, rec))
            cells = sorted(groups)
            k = sum(needs[0].values())
            costs = [(c, [d for d, _ in groups[c]][:k]) for c in cells]
            began = time.perf_counter()
            got = solve(costs, needs)
        spent = time.perf_counter() - began  # of the solver alone
        status, took, sure = got
        picked = [(rec, d) for c, n in zip(cells, took) for d, rec in groups[c][:n]] if took is not None else []
        out = pd.DataFrame(picked or [(None, None)], columns=["rec_id", "dist"])
        out.insert(0, "query_id", pdf["query_id"].iloc[0])
        out["status"], out["seconds"], out["certified"] = status, spent, sure
        return out.astype({"rec_id": "Int64", "dist": "float64"})

    # pools are few bytes but much work: a number of partitions that is named is not merged into fewer tasks at run time
    spark = pool.sparkSession
    parts = min(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    return rows.repartition(parts, "query_id").groupBy("query_id").applyInPandas(run, PICKED)


def select_pair(pool: DataFrame, quotas: DataFrame, attrs: list[str], certify: bool = False) -> DataFrame:
    """Two attributes: min-cost flow. One row for each record chosen, or one with status infeasible; with `certify` the
    solver's own proof of optimality is in `certified`."""

    def solve(cells, needs):
        costs = dict(cells)
        if len(needs) != 2:
            return "invalid", None, None
        if sum(needs[0].values()) != sum(needs[1].values()):
            return "invalid", None, None
        took = flow(costs, *needs)
        if took is None:
            return "infeasible", None, None
        return "ok", [took[c] for c, _ in cells], certified(costs, took) if certify else None

    return _grouped(pool, quotas, attrs, solve)


def select_multi(pool: DataFrame, quotas: DataFrame, attrs: list[str], method: str = "auto", node_limit: int = 200_000, time_limit_s: float = 60.0, dp_states: int = 20_000) -> DataFrame:
    """Any number of attributes: integer search (bnb), the program over cells (dp), or both in turn (auto). Where few records
    meet the counts the program ends at once and the search would try everything; where many do, it is the other way round. So
    auto gives the program `dp_states` states, then the search a tenth of its time, then the program fifty times as many
    states, and then the search all its time."""

    def search(cells, needs, seconds):
        status, _, took = branch(cells, needs, node_limit, seconds)
        return status, took, None

    def program(cells, needs, most):
        try:
            got = cell_dp(cells, needs, most)
        except TooManyStates:
            return None
        return ("infeasible", None, None) if got is None else ("ok", got[1], None)

    def solve(cells, needs):
        if len({sum(n.values()) for n in needs}) != 1:
            return "invalid", None, None
        if method == "dp":
            return program(cells, needs, None)
        if method == "auto":
            got = program(cells, needs, dp_states)
            if got is None:
                got = search(cells, needs, time_limit_s / 10)
                if got[0] == "timeout":
                    got = program(cells, needs, 50 * dp_states)
            if got is not None:
                return got
        return search(cells, needs, time_limit_s)

    return _grouped(pool, quotas, attrs, solve)


def select_cell_dp(pool: DataFrame, quotas: DataFrame, attrs: list[str]) -> DataFrame:
    return select_multi(pool, quotas, attrs, method="dp")


def select_greedy(pool: DataFrame, quotas: DataFrame, attrs: list[str]) -> DataFrame:
    """Nearest first with exchanges; what it returns meets the counts but need not be the least."""

    def solve(cells, needs):
        records = [(c, d) for c, own in cells for d in own]
        took = greedy(records, needs)
        if took is None:
            return "infeasible", None, None
        count: dict = {}
        for i in took:
            count[records[i][0]] = count.get(records[i][0], 0) + 1
        return "ok", [count.get(c, 0) for c, _ in cells], None

    return _grouped(pool, quotas, attrs, solve)


def feasible_pair(pool: DataFrame, quotas: DataFrame, attrs: list[str]) -> DataFrame:
    """query_id, feasible: whether a full flow exists, costs aside."""
    free = pool.withColumn("dist", F.lit(0.0))
    return select_pair(free, quotas, attrs).groupBy("query_id").agg((F.min("status") == "ok").alias("feasible"))


def select(pool: DataFrame, quotas: DataFrame, attrs: list[str], selector: str = "auto", **options) -> DataFrame:
    """Answers query_id, rec_id, dist, status, seconds by the number of attributes that each query constrains; a batch may
    mix them."""
    if selector == "multi":
        return select_multi(pool, quotas, attrs, **options)
    m = quotas.groupBy("query_id").agg(F.count_distinct("attr").alias("m_"))
    part = lambda df, cond: df.join(m.where(cond).select("query_id"), "query_id", "left_semi")
    one = select_single(part(pool, "m_ = 1"), part(quotas, "m_ = 1"), attrs).select("*", F.lit("ok").alias("status"), F.lit(0.0).alias("seconds"), F.lit(None).cast("boolean").alias("certified"))
    two = select_pair(part(pool, "m_ = 2"), part(quotas, "m_ = 2"), attrs)
    more = select_multi(part(pool, "m_ > 2"), part(quotas, "m_ > 2"), attrs, **options)
    return one.unionByName(two).unionByName(more)


def verify(answer: DataFrame, quotas: DataFrame, attrs: list[str]) -> DataFrame:
    """query_id, verified: a recount of every attribute and value of the answer (with attribute columns) against the needs.
    Values asked for but absent, values not asked for, and missing answers all fail."""
    counted = _long(answer.where("rec_id is not null"), attrs).groupBy("query_id", "attr", "value").agg(F.count(F.lit(1)).alias("have"))
    constrained = quotas.select("query_id", "attr").distinct()
    counted = counted.join(constrained, ["query_id", "attr"], "left_semi")
    needs = quotas.groupBy("query_id", "attr", "value").agg(F.sum("need").alias("need"))
    both = needs.withColumnRenamed("value", "v_").join(
        counted.withColumnRenamed("value", "w_"), (needs.query_id == counted.query_id) & (needs.attr == counted.attr) & F.col("v_").eqNullSafe(F.col("w_")), "full"
    )
    wrong = both.select(F.coalesce(needs.query_id, counted.query_id).alias("query_id"), (F.coalesce("have", F.lit(0)) == F.coalesce("need", F.lit(0))).alias("same"))
    return wrong.groupBy("query_id").agg(F.bool_and("same").alias("verified"))
