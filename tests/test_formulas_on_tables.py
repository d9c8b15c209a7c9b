"""The planning formulas run over given tables, and agree with their plain versions."""

import pytest

from quotaknn.functions import lsh
from quotaknn.plans import registry


@pytest.mark.parametrize("name, source", [("inspect_budget", "lineitem"), ("success_bound", "orders")])
def test_formulas_read_a_table(spark, sf, name, source):
    import duckdb

    made = registry.QUERIES[name](spark, sf)
    assert any(f"{source}.parquet" in f for f in made.inputFiles())
    con = duckdb.connect()
    con.sql(f"create view {source} as select * from '{sf}/{source}.parquet'")
    assert sorted(map(tuple, made.collect())) == sorted(con.sql(registry.SQL[name]).fetchall())
    for r in made.collect():
        if name == "inspect_budget":
            assert r["budget"] == lsh.inspect_budget(r["k"], r["l"], 0.1)
        else:
            assert r["success"] == lsh.overall_success(r["n"], 0.01)
