"""Rows keep their numbers though files are dealt otherwise in each reading, as they are once executors come or go."""

import random

import pytest

from quotaknn.llm import common, minhash, substring, suffix

DEAL = "spark.sql.files.minPartitionNum"


@pytest.fixture(scope="module")
def table(spark):
    """Ten files of different sizes: near copies, shared lines and shared passages between texts of their own."""
    rng = random.Random(5)
    word = lambda: "".join(rng.choices("abcdefghij", k=6))
    passage = " ".join(word() for _ in range(90))
    path = common.scratch(spark, "places")
    doc = 0
    for size in (30, 3, 17, 8, 25, 1, 12, 5, 20, 9):
        rows = []
        for _ in range(size):
            own = " ".join(word() for _ in range(rng.choice((20, 60, 150))))
            kind = doc % 4
            rows.append((doc, own if kind == 0 else own + "\nshared line here\n" + word() if kind == 1 else own + " " + passage + " " + word() if kind == 2 else passage + f" x{doc}"))
            doc += 1
        spark.createDataFrame(rows, "doc_id long, text string").coalesce(1).write.mode("append").parquet(path)
    return spark.read.schema("doc_id long, text string").parquet(path)


@pytest.fixture
def dealt(spark):
    before = spark.conf.get(DEAL, None)
    yield lambda n: spark.conf.set(DEAL, n)
    spark.conf.unset(DEAL) if before is None else spark.conf.set(DEAL, before)


def test_numbers_stay(table, dealt):
    found = []
    for n in (1, 32):
        dealt(n)
        found.append({r["doc_id"]: r["row_key"] for r in common.placed(table).collect()})
        position = common.keyed(table)
        found.append({r["doc_id"]: r["row_key"] for r in position.collect()})
    assert found[0] == found[2] and len(set(found[0].values())) == 130
    assert found[1] != found[3]  # positions in one reading do not


def test_many_files_and_clashing_names(spark, table, monkeypatch):
    want = {r["doc_id"]: r["row_key"] for r in common.placed(table).collect()}
    monkeypatch.setattr(common, "MOST_FILES", 2)  # numbers join without a broadcast
    clash = common.materialise(table.selectExpr("doc_id", "text", "1 as file", "2 as `row`", "3 as number", "4 as row_key", "5 as `a.b`"), "clash")
    got = common.with_place(clash, common.fresh(clash, "row_key"))
    assert got.columns == [*clash.columns, "_row_key"] and got.select("_row_key").distinct().count() == 130
    assert {r["doc_id"]: r["row_key"] for r in common.placed(table).collect()} == want
    assert common.placed(table.limit(0)).count() == 0


@pytest.mark.parametrize("module", [substring, suffix, minhash])
def test_operators_read_alike(table, dealt, monkeypatch, module):
    run = {
        substring: lambda: substring.remove_units(table), suffix: lambda: suffix.remove_repeats(table),
        minhash: lambda: minhash.drop_near_copies(table, words=4),
    }[module]
    dealt(1)
    columns = [c for c in run().columns if c != "row_key"]
    want = sorted(map(str, run().select(*columns).collect()))
    first, count = module.materialise, [0]

    def between(df, name):
        made = first(df, name)
        count[0] += 1
        dealt(32 if count[0] % 2 else 1)
        return made

    monkeypatch.setattr(module, "materialise", between)
    last = run()
    dealt(32)
    assert sorted(map(str, last.select(*columns).collect())) == want and count[0]
