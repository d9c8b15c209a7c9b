"""Every operator on nulls, empty and very long texts, ties, repeated rows, empty tables and clashing columns."""

import hashlib
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from quotaknn.llm import ann, common, exact_dedup, langid, minhash, mixing, packing, sharding, substring, suffix, tokens_out

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, row_key string, digest string, shard string, n string, mixed string, language string, TEXT_ string"
LONG = "".join(f"w{i} " for i in range(40_000))
COMMON = " ".join(f"passage{i}" for i in range(70))


def rows():
    base = [
        (1, "alpha beta gamma delta epsilon zeta eta theta", "en", "s1"), (2, None, "en", "s1"), (3, "", None, "s2"), (None, "no id here at all, my friend", "de", None),
        (4, LONG, "en", "s1"), (9, LONG, "en", "s1"), (5, "alpha beta gamma delta epsilon zeta eta theta", "de", "s1"), (5, "alpha beta gamma delta epsilon zeta eta theta", "de", "s1"),
        (6, "   \t\n ", "en", "s2"), (7, "first\n" + COMMON + "\nlast", "en", "s3"), (8, "other\n" + COMMON + "\nend", "fr", "s3"), (10, "12345 !!! ###", "en", "s1"), (11, "ü", "de", "s2"),
    ]
    return [(*r, len(r[1] or ""), "x", "y", "z", "q", "m", "l", "t") for r in base]


@pytest.fixture(scope="module")
def docs(spark):
    return common.materialise(spark.createDataFrame(rows(), SCHEMA).coalesce(2), "docs")


@pytest.fixture(scope="module")
def empty(spark):
    return common.materialise(spark.createDataFrame([], SCHEMA), "docs")


def test_exact_dedup(docs, empty):
    got = exact_dedup.exact_dedup(docs).collect()
    assert len(got) == 13
    kept = [r for r in got if r["kept"]]
    assert len(kept) == len({t or "" for _, t, *_ in rows()})
    assert {r["keep_id"] for r in got if r["doc_id"] in (1, 5)} == {5} and {r["group_size"] for r in got if r["doc_id"] in (1, 5)} == {3}
    assert {r["keep_id"] for r in got if r["doc_id"] in (2, 3)} == {3}
    assert [r["keep_id"] for r in got if r["doc_id"] is None] == [None]
    assert exact_dedup.exact_dedup(empty).count() == 0
    left = exact_dedup.drop_copies(docs)
    assert left.columns == docs.columns and left.count() == len(kept)


def test_exact_dedup_looks_at_the_bytes(spark, monkeypatch):
    """Digests that collide, made so by hand, are told apart by the texts that their locators lead to."""
    docs = common.materialise(spark.createDataFrame([(i, "b" if i == 77 else "a") for i in range(300)] + [(300, "c")], "doc_id long, text string"), "docs")
    arrivals = exact_dedup.arrivals
    monkeypatch.setattr(exact_dedup, "arrivals", lambda *a: arrivals(*a).withColumn("digest", F.when(F.col("doc_id") < 300, F.lit(bytearray(b"\x01"))).otherwise(F.col("digest"))))
    got = {r["doc_id"]: r for r in exact_dedup.exact_dedup(docs).collect()}
    assert (got[77]["keep_id"], got[77]["group_size"], got[77]["kept"]) == (77, 1, True) and got[300]["kept"]
    assert {(r["keep_id"], r["group_size"]) for i, r in got.items() if i not in (77, 300)} == {(299, 299)}
    assert exact_dedup.drop_copies(docs).count() == 3


def test_locators_lead_to_rows(spark):
    """The same rows have the same locators in each run, whatever is selected; a table that is no scan is written first."""
    docs = common.materialise(spark.range(50).selectExpr("id as doc_id", "concat('t', id % 7) as text", "id as row").repartition(3), "docs")
    one = {(r["file"], r["row"]): (r["doc_id"], r["text"]) for r in exact_dedup.texts_of(docs).collect()}
    two = {(r["file"], r["row"]): (r["doc_id"], r["text"]) for r in exact_dedup.texts_of(docs.where("doc_id >= 0").select("text", "doc_id")).collect()}
    assert len(one) == 50 and one == two
    twice = docs.unionByName(docs)
    assert not common.is_scan(twice) and common.is_scan(docs.select("doc_id"))
    got = exact_dedup.exact_dedup(twice).collect()
    assert len(got) == 100 and sum(r["kept"] for r in got) == 7


def test_exact_dedup_goes_on(spark):
    """The state lives on disk: a second run sees what the first has seen."""
    log, state = common.scratch(spark, "log"), common.scratch(spark, "state")
    one = spark.createDataFrame([(1, "x"), (2, "y")], "doc_id long, text string")
    exact_dedup.arrivals(one).write.parquet(log)
    first = {r["n"] for r in exact_dedup.run_state(spark, log, state).collect()}
    exact_dedup.arrivals(spark.createDataFrame([(3, "x")], "doc_id long, text string")).write.mode("append").parquet(log)
    second = sorted((r["n"], r["keeper"]["doc_id"]) for r in exact_dedup.run_state(spark, log, state).collect())
    assert first == {1} and second == [(1, 2), (2, 3)]


def test_sharding(docs, empty):
    tree = sharding.Tree.balanced(16)
    got = sharding.shard_documents(docs, tree).collect()
    assert len(got) == 13
    for s in range(16):
        slots = sorted(r["slot"] for r in got if r["shard"] == s)
        assert slots == list(range(len(slots)))
    assert all(r["grown_shard"] in (r["shard"], 16) for r in got)
    assert {(r["size"], r["text_crc32"]) for r in got if r["doc_id"] in (2, 3)} == {(1, 0)}
    assert sharding.shard_documents(empty, tree).count() == 0


def test_sharding_moves_only_within_changed_subtrees(spark):
    ids = spark.range(4000).select(F.col("id").cast("string").alias("k"))
    tree = sharding.Tree.balanced(16)
    heavier = tree.with_weight(5, 3.0)
    got = ids.select(sharding.place(F.col("k"), tree).alias("a"), sharding.place(F.col("k"), heavier).alias("b"), sharding.place(F.col("k"), tree.with_weight(5, 0.0)).alias("c")).collect()
    moved = [r for r in got if r["a"] != r["b"]]
    assert moved and all(r["b"] // 8 == 0 for r in moved)  # into region 0, where shard 5 lies
    assert all(r["c"] != 5 for r in got)
    share = np.bincount([r["a"] for r in got], minlength=16) / len(got)
    assert abs(share - 1 / 16).max() < 0.02


def test_near_duplicates(docs, empty):
    got = {(r["doc_id"], r["row_key"]): r for r in minhash.near_duplicates(docs, 4).collect()}
    assert len(got) == 13
    by = {k[0]: r for k, r in got.items()}
    assert by[9]["component_id"] == 4 and by[4]["n_shingles"] == 40_000 - 3
    assert by[5]["component_id"] == 1 and by[11]["n_shingles"] == 1 and by[2]["n_shingles"] == 0 and by[3]["component_id"] == 3 and by[6]["n_shingles"] == 0
    assert by[None]["component_id"] is None
    assert by[8]["component_id"] == 7 and sum(r["stays"] for r in got.values()) == 9
    assert minhash.near_duplicates(empty, 4).count() == 0
    left = minhash.drop_near_copies(docs)
    assert left.columns == docs.columns and left.count() == 9


def test_lines(docs, empty):
    got = {r["doc_id"]: r for r in substring.remove_units(docs, with_text=True).collect()}
    assert got[7]["n_removed"] == 0 and got[8]["n_removed"] == 1 and got[8]["kept"] == "other\nend"
    span = got[8]["spans"][0]
    assert ("other\n" + COMMON + "\nend")[span["start"] : span["stop"]] == COMMON
    assert got[1]["n_removed"] == 0 and got[9]["n_removed"] == 1
    assert substring.remove_units(empty).count() == 0
    assert substring.remove_units(docs, "paragraph").count() == 13


def test_suffixes(docs, empty):
    got = {r["doc_id"]: r for r in suffix.remove_repeats(docs, with_text=True).collect()}
    raw = ("first\n" + COMMON + "\nlast").encode()
    assert len(COMMON) > 400 and got[7]["n_spans"] == 1
    cut = bytes(got[7]["kept"])
    span = got[7]["spans"][0]
    assert cut == raw[: span["start"]] + raw[span["stop"] :] and hashlib.sha256(cut).hexdigest() == got[7]["kept_sha256"]
    assert got[4]["n_removed"] == got[4]["n_bytes"] == len(LONG) and got[1]["n_removed"] == 0
    assert got[2]["n_bytes"] == 0 and got[2]["kept_sha256"] == hashlib.sha256(b"").hexdigest()
    assert suffix.remove_repeats(empty).count() == 0


def test_language(docs, empty):
    out = langid.identify(docs)
    assert out.columns[-1] == "_language" and out.count() == 13
    got = {r["doc_id"]: r["_language"] for r in out.collect()}
    assert got[2]["lang_pred"] == got[3]["lang_pred"] == got[6]["lang_pred"] == got[10]["lang_pred"] == "und"
    assert all(0 <= r["score"] <= 1 for r in got.values())
    assert langid.identify(empty).count() == 0
    unlabelled = docs.withColumn("lang", F.lit(None).cast("string"))
    assert {r["_language"]["lang_pred"] for r in langid.identify(unlabelled).collect()} == {"und"}
    assert langid.accepted(docs).columns == docs.columns


def test_mixing(docs, empty):
    out = mixing.mix(docs)
    c = out.columns[-1]
    assert c == "_mixed" and out.count() == 13
    got = [r[c] for r in out.collect()]
    assert all(0 <= r["probability"] <= 1 for r in got) and all(r["probability"] == 0 for r in got if r["n_tokens"] == 0)
    assert mixing.mix(empty).count() == 0 and mixing.sampled(docs).columns == docs.columns
    assert mixing.mix(docs.withColumn("text", F.lit(None).cast("string"))).where(f"{c}.kept").count() == 0


def test_tokens(spark, docs, empty):
    path, name = common.scratch(spark, "t"), common.tokenizer_path("byte_bpe_50k.json")
    tokens_out.write(docs, path, name, block_tokens=1000)
    got = tokens_out.documents(spark, path, with_ids=True).orderBy("start").collect()
    assert len(got) == 13 and got[0]["doc_id"] is None
    at = 0
    for r in got:
        assert r["start"] == at and r["n_tokens"] == len(r["ids"]) and r["ids"][-1] == 0
        assert zlib.crc32(np.array(r["ids"], "<u4").tobytes()) == r["ids_crc32"]
        at += r["n_tokens"]
    flat = [i for r in got for i in r["ids"]]
    for p in (0, 5, 17, len(flat) // 2, len(flat) - 1):
        assert tokens_out.token_at(spark, path, p) == flat[p]
    with pytest.raises(IndexError):
        tokens_out.token_at(spark, path, len(flat))
    other = common.scratch(spark, "t")
    tokens_out.write(empty, other, name)
    assert tokens_out.documents(spark, other).count() == 0


def test_packing(docs, empty):
    name = common.tokenizer_path("word_bpe_49k.json")
    got = packing.pack(docs, name).collect()
    check_packed(got, 4096)
    assert {r["length"] for r in got if r["doc_id"] in (2, 3)} == {1}
    assert packing.pack(empty, name).count() == 0


def check_packed(got, capacity):
    by = {}
    for r in got:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for own in by.values():
        at = 0
        for offset, length in sorted(own):
            assert offset == at
            at += length
        assert at <= capacity
    return len(by)


def test_vectors(spark):
    nan = float("nan")
    data = [(0, [1.0, 0.0]), (1, [1.0, 0.0]), (2, [0.9, 0.1]), (3, None), (4, [0.0, 0.0]), (5, [nan, 1.0]), (6, [1.0, None]), (20, [0.0, 1.0]), (20, [0.0, 1.0]), (None, [0.5, 0.5]), (7, [1.0]), (40, [2.0, 0.0])]
    v = common.materialise(spark.createDataFrame([(*r, "c") for r in data], "vec_id long, embedding array<double>, row string"), "v")
    got = ann.search(v).collect()
    zero = [(r["rank"], r["vec_id"], r["score"]) for r in got if r["query_id"] == 0]
    assert [x[1] for x in sorted(zero)] == [40, 1, 2, None, 20, 20] and sorted(zero)[0][2] == 2.0
    assert len([r for r in got if r["query_id"] == 20]) == 12
    assert ann.search(v.where("false")).count() == 0 and ann.search(v.where("vec_id = 3")).count() == 0


def test_pipeline_on_messy_documents(spark, docs):
    now = docs
    for name, stage in corpus_pipeline.STAGES:
        last, now = now, common.materialise(stage(spark, now, ""), name)
        assert name == "packing" or now.columns == docs.columns
    assert now.count() > 0
    check_packed(now.collect(), 4096)
