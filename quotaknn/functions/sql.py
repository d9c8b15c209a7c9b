"""SQL surface: registered functions, a table function that expands quotas, and grouped aggregates."""

from __future__ import annotations

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from quotaknn.functions.cells import CellDictionary
from quotaknn.functions.distance import distance_block
from quotaknn.functions.lsh import Family, lsh_keys


def vec_distance(metric: str = "l2", p: float = 2.0):
    """Arrow function of two vector columns, row by row in blocks."""

    @F.arrow_udf(T.DoubleType())
    def run(a, b):
        import pyarrow as pa

        x = a.flatten().to_numpy(zero_copy_only=False).reshape(len(a), -1)
        y = b.flatten().to_numpy(zero_copy_only=False).reshape(len(b), -1)
        if metric == "l2":
            return pa.array(np.sqrt(((x - y) ** 2).sum(1)))
        if metric == "l1":
            return pa.array(np.abs(x - y).sum(1))
        return pa.array(np.array([distance_block(metric, q[None], r[None], p)[0, 0] for q, r in zip(x, y)]))

    return run


def expand_quota(dictionary: CellDictionary):
    """Table function: (needs as JSON) -> rows (mask, qcode, k_cell)."""
    fields = {a: (dictionary.mask(a), dictionary.shift(a), {v: i + 1 for i, v in enumerate(own)}) for a, own in dictionary.values.items()}

    class ExpandQuota:
        def eval(self, needs: str):
            import json

            rows = [(0, 0, None)]
            for attr, own in (json.loads(needs) if needs else {}).items():
                mask, shift, code = fields[attr]
                rows = [(m | mask, q | (code[v] << shift), n if k is None else min(k, n)) for m, q, k in rows for v, n in own.items() if n > 0 and v in code]
            for row in rows:
                if row[2] is not None:
                    yield row

    return F.udtf(ExpandQuota, returnType="mask long, qcode long, k_cell int")


def centroid():
    """Grouped aggregate of vectors: the mean of each component."""

    def run(v):
        return np.stack(v.to_numpy()).mean(0).tolist()

    return F.pandas_udf(run, T.ArrayType(T.DoubleType()), F.PandasUDFType.GROUPED_AGG)


def register_sql(spark: SparkSession, family: Family, dictionary: CellDictionary) -> None:
    """lsh_keys(vec), vec_l2(a, b), expand_quota(json), and the planners cell_quota, cell_match, inspect_budget, plan_hashes
    and plan_tables as SQL functions."""
    spark.udf.register("lsh_keys", lsh_keys(family))
    spark.udf.register("vec_l2", vec_distance("l2"))
    spark.udtf.register("expand_quota", expand_quota(dictionary))
    for text in (
        "cell_match(code bigint, mask bigint, qcode bigint) returns boolean return ((code & mask) ^ qcode) = 0",
        "cell_quota(needs array<int>) returns int return array_min(filter(needs, x -> x is not null))",
        "inspect_budget(k int, tables int, delta double) returns int return k + cast(ceil(2 * tables / delta) as int)",
        "plan_hashes(n bigint, p2 double) returns int return greatest(1, cast(ceil(ln(n) / ln(1 / p2)) as int))",
        "plan_tables(n bigint, p1 double, p2 double, near int, delta double) returns int return case when n <= 1 then 1 else greatest(1, cast(ceil(pow(n, ln(1 / p1) / ln(1 / p2)) * ln(2 * near / delta)) as int)) end",
    ):
        spark.sql(f"create or replace temporary function {text}")
