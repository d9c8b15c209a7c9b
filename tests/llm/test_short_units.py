"""Lines of any length and sentences inside lines: repeated ones go, with their offsets, as the SQL has it."""

import duckdb
import pytest

import __spark_entry__ as entry
from quotaknn.llm import common, substring


def test_short_lines(spark, tmp_path):
    texts = [(1, "Released under the MIT license.\n空白のない一行\nend"), (2, "own\nreleased  under the mit license.\n\n空白のない一行\n \nend"), (3, None), (4, "\n\nEnd")]
    spark.createDataFrame(texts, "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    got = {r["doc_id"]: r for r in entry.queries()["op5_line_dedup"](spark, str(tmp_path)).collect()}
    assert {k: (r["n_removed"], r["removed_spans"]) for k, r in got.items()} == {1: (0, ""), 2: (3, "4-36,38-45,48-51"), 3: (0, ""), 4: (1, "2-5")}
    docs = spark.read.parquet(str(tmp_path / "documents.parquet"))
    assert {r["doc_id"]: r["kept"] for r in substring.remove_units(docs, with_text=True).collect()}[2] == "own\n\n "


def test_a_passage_inside_a_line(spark):
    """Pasted between other words, a passage goes by its inner sentences; spans point into the original."""
    passage = "Ends here. One two three four five six seven eight nine. Ten eleven twelve thirteen fourteen fifteen sixteen seventeen! So."
    docs = {1: f"before it {passage} after it", 2: f"quite other words {passage} and then more", 3: "nothing. of. the. kind. at. all."}
    df = common.materialise(spark.createDataFrame(list(docs.items()), "doc_id long, text string"), "d")
    got = {r["doc_id"]: r for r in substring.remove_units(df, with_text=True).collect()}
    assert got[1]["n_removed"] == got[3]["n_removed"] == 0 and got[1]["kept"] == docs[1]
    assert [docs[2][s["start"] : s["stop"]].strip() for s in got[2]["spans"]] == passage.split(". ", 1)[1].replace("! So.", "!").replace(". Ten", ".| Ten").split("| ")
    assert got[2]["kept"] == "quite other words Ends here. So. and then more"
    assert {r["doc_id"]: r["n_removed"] for r in substring.remove_units(df, sentence_words=0).collect()} == {1: 0, 2: 0, 3: 0}


def test_first_occurrences_stay(spark):
    """Whatever the order of lines and sentences, every normalised sentence is still somewhere."""
    s = [f"sentence number {w} has exactly nine words in it." for w in ("a", "b", "c")]
    docs = {1: f"{s[0]} {s[1]}\n{s[0]}", 2: f"{s[1]}\n{s[0]} {s[1]}\n{s[2]} {s[0]}", 3: f"{s[2]} {s[0]}\n{s[2]}"}
    df = common.materialise(spark.createDataFrame(list(docs.items()), "doc_id long, text string"), "d")
    kept = "\n".join(r["kept"] for r in substring.remove_units(df, with_text=True).collect())
    assert all(kept.count(x) == 1 for x in s)


@pytest.mark.parametrize("sf", ["0.001", "0.01"])
def test_query_equals_its_sql(spark, sf):
    path = f"/root/testdata/sf{sf}"
    con = duckdb.connect()
    con.execute(f"create view documents as select * from '{path}/documents.parquet'")
    want = {tuple(r) for r in con.execute(entry.oracle_sql()["op5_line_dedup"]).fetchall()}
    got = entry.queries()["op5_line_dedup"](spark, path)
    assert {tuple(r) for r in got.collect()} == want and sum(r[1] for r in want) > 0
