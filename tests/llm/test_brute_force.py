"""Operators against plain versions of themselves, on the given tables and on planted cases."""

import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

import corpus_pipeline
from quotaknn.llm import ann, common, exact_dedup, langid, minhash, mixing, packing, suffix, tokens_out
from test_edge_cases import check_packed  # noqa: E402

SF = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def texts(spark):
    return {r["doc_id"]: r["text"] or "" for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").collect()}


# codes ---------------------------------------------------------------------------------------------------------------


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 2**32 - 1) | st.integers(0, 300), max_size=1500))
def test_codes_round_trip(values):
    ids = np.array(values, "<u4")
    codes = tokens_out.Codes(tokens_out.encode(ids))
    assert (codes.all() == ids).all() and len(codes) == len(ids)
    for i in range(0, len(ids), 97):
        assert codes[i] == ids[i]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.text(alphabet="ab7 \n\t.,'’—  é9ſΣσİ中ß́\x1cx<|>", max_size=300), min_size=1, max_size=30))
def test_pieces_equal_whole_texts(texts):
    for name in ("byte_bpe_50k.json", "word_bpe_49k.json"):
        path = common.tokenizer_path(name)
        want = common.Pieces(path).whole(texts)
        got = list(common.encoder(path, 5)(pa.array(texts)))
        assert all((g[:-1] == w).all() and len(g) == len(w) + 1 and g[-1] == 5 for g, w in zip(got, want))


def mirrored(bits: int) -> tuple[str, str]:
    """Two strings whose sums of powers of any odd number agree modulo 2 ** 64: each symbol tells the parity of the ones of
    its place."""
    one = "".join("ab"[i.bit_count() & 1] for i in range(1 << bits))
    return one, one.translate(str.maketrans("ab", "ba"))


def test_pieces_whose_hashes_collide():
    x, y = mirrored(11)
    data, offs = common.text_bytes(pa.array([x, y]))
    h1, h2 = common.slice_hashes(data, offs[:-1], np.diff(offs))
    assert h1[0] == h1[1] and h2[0] == h2[1]  # the hashes cannot tell them apart, the bytes can
    texts = ["filler " * 900, f"one {x} two", f"one {y} two", x, y, f" {y}{x}", "tail", x + "!" * 70_000 + y]
    for name in ("byte_bpe_50k.json", "word_bpe_49k.json"):
        path = common.tokenizer_path(name)
        want = common.Pieces(path).whole(texts)
        for order in (list(range(8)), [4, 3, 2, 1, 7, 5, 0, 6]):
            got = list(common.encoder(path, 5)(pa.array([texts[i] for i in order])))
            assert all((g[:-1] == want[i]).all() and len(g) == len(want[i]) + 1 for i, g in zip(order, got))


def test_long_texts_go_in_parts():
    texts = [" ".join(f"u{i % 977}v{i % 13}" for i in range(400_000)), "x" * 300_000, "end"]
    path = common.tokenizer_path("byte_bpe_50k.json")
    want = common.Pieces(path).whole(texts)
    assert all((g[:-1] == w).all() for g, w in zip(common.encoder(path, 0)(pa.array(texts)), want))


def test_shingles_of_long_mirrored_words():
    x, y = mirrored(11)
    a, b = (minhash.shingle_sets(*common.text_bytes(pa.array([f"one two three {w}"])), 4)[0] for w in (x, y))
    assert len(a) == len(b) == 1 and a[0] != b[0]


def test_blocks_are_closed_over_small_batches(spark):
    """Blocks end at their size however the rows are batched."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "5")
    try:
        docs = common.materialise(spark.range(600).selectExpr("id as doc_id", "concat('word ', id, ' and more') as text").coalesce(1), "d")
        path = common.scratch(spark, "t")
        tokens_out.write(docs, path, common.tokenizer_path("byte_bpe_50k.json"), block_tokens=100)
        sizes = [(r["n_tokens"], max(r["lengths"])) for r in tokens_out.read(spark, path).collect()]
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert sum(n for n, _ in sizes) > 3000 and all(n < 100 + longest for n, longest in sizes)


def test_full_table_is_emptied(monkeypatch):
    monkeypatch.setattr(common.Pieces, "MOST", 50)
    p = common.Pieces(common.tokenizer_path("byte_bpe_50k.json"))
    for r in range(5):
        text = " ".join(f"u{r}x{i}" for i in range(900))
        data, offs = common.text_bytes(pa.array([text]))
        (got,) = p.encode(data, offs, 0)
        assert (got[:-1] == p.whole([text])[0]).all()


# suffixes ------------------------------------------------------------------------------------------------------------


@settings(max_examples=40, deadline=None)
@given(st.binary(min_size=1, max_size=400), st.integers(1, 6))
def test_suffix_array_and_prefixes(data, fold):
    x = np.frombuffer(bytes(b % (fold + 1) + 97 for b in data), np.uint8)
    raw = x.tobytes()
    sa = suffix.suffix_array(x)
    assert list(sa) == sorted(range(len(raw)), key=lambda i: raw[i:])
    lcp = suffix.common_prefixes(x, sa, 40, 8)
    for i in range(1, len(raw)):
        a, b = raw[sa[i - 1] :], raw[sa[i] :]
        k = next((j for j, (u, v) in enumerate(zip(a, b)) if u != v), min(len(a), len(b)))
        assert lcp[i] == min(k, 40)


@pytest.mark.parametrize("hot", [1, 256])
def test_repeats(spark, monkeypatch, hot):
    """Small spans over texts full of repeats, with and without anchors dealt over shards; and texts cut in parts."""
    monkeypatch.setattr(suffix, "HOT", hot)
    monkeypatch.setattr(suffix, "PART", 700)
    rng = random.Random(5)
    words = ["ab", "abc", "xy", "z", "ü", "qq q"]
    phrases = [" ".join(rng.choice(words) for _ in range(40)) for _ in range(12)]
    docs = {i: " ".join(rng.choice(phrases) if rng.random() < 0.6 else "".join(rng.choice("abcdefgh") for _ in range(60)) for _ in range(rng.randint(0, 14))) for i in range(60)}
    docs |= {60: "abcdefg " * 200, 61: "tiny", 62: ""}
    span = 60
    df = common.materialise(spark.createDataFrame(list(docs.items()), "doc_id long, text string"), "d")
    seen = Counter(t.encode()[i : i + span] for t in docs.values() for i in range(len(t.encode()) - span + 1))
    for r in suffix.remove_repeats(df, span).collect():
        raw = docs[r["doc_id"]].encode()
        gone = np.zeros(len(raw), bool)
        for i in range(len(raw) - span + 1):
            if seen[raw[i : i + span]] > 1:
                gone[i : i + span] = True
        assert (r["n_removed"], r["n_spans"]) == (int(gone.sum()), int((np.diff(np.append(0, gone.astype(int))) == 1).sum()))


def test_a_passage_with_many_surroundings(spark):
    """A passage in more documents than one shard takes of an anchor, at the default setting: shards are merged. Its ends
    meet other bytes each time, a few of them twice."""
    rng = random.Random(3)
    word = lambda: "".join(rng.choice("abcdefghijk") for _ in range(6))
    passage, edges = " ".join(word() for _ in range(90)), [" ".join(word() for _ in range(70)) for _ in range(40)]
    text = lambda: rng.choice(edges) if rng.random() < 0.2 else " ".join(word() for _ in range(70))
    docs = {i: f"{text()} {passage[rng.randrange(3) * 50:]} {text()}" for i in range(600)}
    docs |= {600: "".join("ab"[i.bit_count() & 1] for i in range(2048)), 601: "".join("ba"[i.bit_count() & 1] for i in range(2048))}
    df = common.materialise(spark.createDataFrame(list(docs.items()), "doc_id long, text string").repartition(3), "d")
    seen = Counter(t[i : i + 400] for t in docs.values() for i in range(len(t) - 399))
    for r in suffix.remove_repeats(df).collect():
        raw = docs[r["doc_id"]]
        gone = np.zeros(len(raw), bool)
        for i in range(len(raw) - 399):
            if seen[raw[i : i + 400]] > 1:
                gone[i : i + 400] = True
        assert (r["n_removed"], r["n_spans"]) == (int(gone.sum()), int((np.diff(np.append(0, gone.astype(int))) == 1).sum()))
    assert suffix.HOT < 400  # so that the anchors at the passage's ends are dealt over shards


@settings(max_examples=30, deadline=None)
@given(st.lists(st.binary(min_size=0, max_size=60), min_size=1, max_size=12), st.integers(1, 3), st.integers(1, 20))
def test_suffixes_of_strings_apart(strings, fold, span):
    """With repeated runs of strings, too: windows that start elsewhere, and no others."""
    pieces = [bytes(b % (fold + 1) + 97 for b in s) for s in strings] * 2 + [b"b" * 40]
    seen = Counter(p[i : i + span] for p in pieces for i in range(len(p) - span + 1))
    for p, mark in zip(pieces, suffix.repeated(pieces, span)):
        assert mark.tolist() == [seen[p[i : i + span]] > 1 for i in range(len(p) - span + 1)]


# near duplicates -----------------------------------------------------------------------------------------------------


def components_of(texts, words, percent):
    sets = {}
    for i, t in texts.items():
        low = bytes(c + 32 if 65 <= c <= 90 else c for c in t.encode())
        w = re.findall(rb"[^\x20\x09-\x0D]+", low)
        sets[i] = {tuple(w[j : j + words]) for j in range(len(w) - words + 1)} if len(w) >= words else ({tuple(w)} if w else set())
    parent = {i: i for i in sets}

    def find(x):
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    inverted, by = defaultdict(list), sorted(sets)
    for i in by:
        shared = Counter(j for g in sets[i] for j in inverted[g])
        for g in sets[i]:
            inverted[g].append(i)
        for j, n in shared.items():
            if 100 * n >= percent * (len(sets[i]) + len(sets[j]) - n):
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    return sets, {i: find(i) for i in by}


def check_near(spark, texts, words=4, percent=80):
    df = common.materialise(spark.createDataFrame(list(texts.items()), "doc_id long, text string").repartition(3), "d")
    got = {r["doc_id"]: r for r in minhash.near_duplicates(df, words, percent).collect()}
    sets, want = components_of(texts, words, percent)
    assert {i: r["component_id"] for i, r in got.items()} == want
    assert {i: r["n_shingles"] for i, r in got.items()} == {i: len(s) for i, s in sets.items()}


def test_near_duplicates_of_the_table(spark, texts):
    check_near(spark, texts)


def test_a_large_group_of_near_copies(spark):
    """Copies whose edits put some just within and some just out of reach of each other, a line common to all, and chains."""
    rng = random.Random(11)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(5))
    line = " ".join(word() for _ in range(9))
    base = [word() for _ in range(150)]
    texts = {}
    for i in range(400):
        own = list(base)
        for _ in range(rng.randint(0, 12)):
            own[rng.randrange(150)] = word()
        texts[i] = line + "\n" + " ".join(own)
    for i in range(400, 700):
        texts[i] = line + "\n" + " ".join(word() for _ in range(rng.randint(20, 90)))
    chain = [word() for _ in range(200)]
    for i in range(700, 720):
        chain[(i - 700) * 9] = word()
        texts[i] = " ".join(chain)
    check_near(spark, texts)


# neighbours, languages, mixing, packing ------------------------------------------------------------------------------


def test_neighbours_are_found(spark):
    table = spark.read.parquet(f"{SF}/embeddings.parquet")
    rows = sorted((r["vec_id"], r["embedding"]) for r in table.collect())
    ids, x = np.array([r[0] for r in rows]), np.array([r[1] for r in rows], float)
    got = defaultdict(list)
    for r in ann.query(spark, SF).collect():
        got[r["query_id"]].append((r["rank"], r["vec_id"], r["score"]))
    hit = n = 0
    for i in np.flatnonzero(ids % 20 == 0):
        score = (x * x[i]).sum(1)
        score[i] = -np.inf
        best = ids[np.lexsort((ids, -score))[:20]].tolist()
        own = sorted(got[ids[i]])
        assert [s for _, _, s in own] == sorted((s for _, _, s in own), reverse=True) and len(own) == 20
        assert all(abs(s - score[np.searchsorted(ids, v)]) < 1e-12 for _, v, s in own)
        hit, n = hit + len(set(best) & {v for _, v, _ in own}), n + 20
    assert hit / n >= 0.9


def test_prefix_ranges_are_nested():
    rng = np.random.default_rng(0)
    codes = np.sort(rng.integers(0, 1 << ann.BITS, 3000))
    asked = np.append(codes[:20], rng.integers(0, 1 << ann.BITS, 20))
    lo, hi = ann.ranges(codes, asked, range(2, ann.BITS + 1))
    for i, q in enumerate(asked.tolist()):
        same = [next((x for x in range(ann.BITS, -1, -1) if c >> (ann.BITS - x) == q >> (ann.BITS - x)), 0) for c in codes.tolist()]
        assert [int(hi[x - 2, i] - lo[x - 2, i]) for x in range(2, ann.BITS + 1)] == [sum(s >= x for s in same) for x in range(2, ann.BITS + 1)]
        assert ann.matched(lo[:, i], hi[:, i], 2).tolist() == [s for s in same if s >= 2]
    assert ann.ranked(np.array([7, 3, 7, 5]), np.array([2, 3, 2, 3], np.int8)).tolist() == [7, 3, 5]


def test_forest_scores_few_vectors(spark):
    """The setting is measured on queries that did not choose it; well under half of the vectors are scored."""
    _, ((forest, asking),) = ann.forests(spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet"), 20, "vec_id", "embedding")
    got = forest.fit(asking, 20)
    assert got.recall >= 0.9 and got.scored < 0.35 * got.vectors


def test_many_equal_vectors(spark, monkeypatch):
    """A third of the rows hold one vector, pieces are cut in parts, blocks are many: as exact search has it, where all are scored."""
    monkeypatch.setattr(ann, "PIECE", 50)
    monkeypatch.setattr(ann, "BLOCK", 64)
    monkeypatch.setattr(ann, "AIM", 1.0)
    rng = np.random.default_rng(4)
    x = rng.standard_normal((600, 8)).round(2)
    x[rng.random(600) < 0.33] = x[0]
    x[300:310] = 2 * x[1]
    table = common.materialise(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>").repartition(3), "v")
    got = defaultdict(list)
    for r in ann.search(table, 20, 20).collect():
        got[r["query_id"]].append((r["rank"], r["vec_id"], r["score"]))
    hit = 0
    for i in range(0, 600, 20):
        score = (x * x[i]).sum(1)
        score[i] = -np.inf
        best = np.lexsort((np.arange(600), -score))[:20].tolist()
        own = sorted(got[i])
        assert len(own) == 20 and [s for _, _, s in own] == sorted((s for _, _, s in own), reverse=True)
        hit += len(set(best) & {v for _, v, _ in own})
    assert hit / 600 >= 0.97 and len(got) == 30


def test_language_accuracy_on_held_out_rows(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "lang")
    got = langid.query(spark, SF).join(docs, "doc_id").where("held_out").selectExpr("avg(cast(lang = lang_pred as double))").head()[0]
    assert got >= 0.97


def test_false_positives_are_corrected():
    m = langid.Model(["a", "b"], 4, 8, 1, np.zeros((256, 1), np.uint64))
    m.table[:128, 0] |= np.uint64(2)  # half full by chance
    best, score = m.score(pa.array(["some words that neither language knows at all"]))
    assert m.false_rate().tolist() == [0.0, 0.5] and score[0] < 0.5


def test_mixing_meets_targets(spark, texts):
    """Tokens, fitted probabilities and draws against loops over dictionaries."""
    got = mixing.query(spark, SF).toPandas().set_index("doc_id")
    whole = common.Pieces(common.tokenizer_path("word_bpe_49k.json")).whole
    assert all(got.n_tokens[i] == len(whole([texts[i]])[0]) for i in list(texts)[:200])
    assert got.topic.nunique() > 2 and (got.target_miss < 1e-9).all()
    cells = defaultdict(float)
    for r in got.itertuples():
        cells[r.source, r.lang, r.topic] += r.n_tokens
    total = sum(cells.values())
    part = lambda k: {v: sum(n for c, n in cells.items() if c[k] == v) / total for v in {c[k] for c in cells}}
    goals = [{v: 1 / len(part(0)) for v in part(0)}, {v: s**0.5 / sum(x**0.5 for x in part(1).values()) for v, s in part(1).items()}, defaultdict(float)]
    for lang, goal in goals[1].items():
        inside = defaultdict(float)
        for (_, own, t), n in cells.items():
            if own == lang and n:
                inside[t] += n
        for t, n in inside.items():
            goals[2][t] += goal * n**0.5 / sum(x**0.5 for x in inside.values())
    w = {c: n / total for c, n in cells.items()}
    miss = 1.0
    while miss > 1e-10:
        miss = 0.0
        for k in range(3):
            now = defaultdict(float)
            for c, x in w.items():
                now[c[k]] += x
            miss = max(miss, *(abs(now[v] - goals[k][v]) for v in now))
            w = {c: x * goals[k][c[k]] / now[c[k]] if now[c[k]] else 0.0 for c, x in w.items()}
    lo, hi = 0.0, 1e12
    for _ in range(200):
        mid = (lo + hi) / 2
        spent = sum(n * min(1, mid * w[c] / n) for c, n in cells.items() if n)
        lo, hi = (mid, hi) if spent < 0.5 * total else (lo, mid)
    for r in got.itertuples():
        c = (r.source, r.lang, r.topic)
        if r.n_tokens:
            assert abs(r.probability - min(1, lo * w[c] / cells[c])) < 1e-6 and abs(r.probability * r.weight - lo * w[c] / cells[c]) < 1e-6 * max(1, r.weight)
    draws = {r[0]: r[1] for r in spark.createDataFrame([(int(i),) for i in got.index], "d long").selectExpr("d", "pmod(xxhash64(cast(d as string), 7), 4503599627370496) / 4503599627370496.0D").collect()}
    assert all(r.kept == (draws[r.Index] < r.probability) for r in got.itertuples())
    assert abs((got.n_tokens * got.kept).sum() / total - 0.5) < 0.1


def test_targets_that_cannot_be_met_are_told(spark):
    rows = [(i, "one two three " * 5, f"s{i % 2}", f"l{i % 2}") for i in range(40)]
    docs = common.materialise(spark.createDataFrame(rows, "doc_id long, text string, source string, lang string"), "d")
    with pytest.warns(UserWarning, match="cannot be met"):
        got = mixing.mix(docs, targets=({"s0": 0.9, "s1": 0.1}, {"l0": 0.5, "l1": 0.5}, None)).select("mixed.target_miss").distinct().collect()
    assert len(got) == 1 and got[0][0] > 0.1


@settings(max_examples=25, deadline=None)
@given(st.lists(st.integers(1, 64), min_size=1, max_size=200))
def test_plans_hold_all_pieces(lengths):
    hist = Counter(lengths)
    chosen, by_patterns, pieces, least = packing.plan(dict(hist), 64)
    assert pieces == len(lengths) >= by_patterns and sum(chosen.values()) >= least
    assert all(sum(p) <= 64 for p in chosen)
    held = Counter()
    for p, n in chosen.items():
        for x in p:
            held[x] += n
    assert held == hist
    first_fit = []
    for x in sorted(lengths, reverse=True):
        i = next((i for i, r in enumerate(first_fit) if r >= x), None)
        if i is None:
            first_fit.append(64 - x)
        else:
            first_fit[i] -= x
    assert sum(chosen.values()) <= len(first_fit) + 1


def test_packed_sequences(spark, texts):
    got = packing.query(spark, SF).collect()
    n = check_packed(got, 4096)
    total = sum(r["length"] for r in got)
    made = packing.plan(Counter(r["length"] for r in got), 4096)
    assert n == sum(made.chosen.values()) == made.least == -(-total // 4096)
    assert made.by_patterns > 0.7 * made.pieces  # patterns carry the packing, best fit only the rest
    tok = common.Pieces(common.tokenizer_path("word_bpe_49k.json"))
    by = defaultdict(list)
    for r in got:
        by[r["doc_id"]].append(r)
    for i in list(texts)[:150]:
        ids = np.append(tok.whole([texts[i]])[0], 1).astype("<u4")
        for r in sorted(by[i], key=lambda r: r["piece"]):
            own = ids[r["start"] : r["start"] + r["length"]]
            assert zlib.crc32(own.tobytes()) == r["ids_crc32"] and (r["length"] == 4096 or r["start"] + r["length"] == len(ids))


def test_pipeline(spark, texts):
    """run() against the stages' own plain versions, decision by decision."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    meta = {r["doc_id"]: r for r in docs.collect()}
    left = [r["doc_id"] for r in corpus_pipeline.language_id(spark, docs, SF).collect()]
    assert set(left) == {i for i, t in texts.items() if re.search(r"[^\W\d_]", t)}  # here every text has letters
    last = {}
    for i in sorted(left):
        last[texts[i]] = i
    once = set(last.values())
    _, comp = components_of({i: texts[i] for i in once}, 5, 80)
    near = {i for i, c in comp.items() if i == c}
    mixed = mixing.sampled(common.materialise(docs.where(docs.doc_id.isin(sorted(near))), "n"), 0.7)
    want = {r["doc_id"] for r in mixed.select("doc_id").collect()}
    got = corpus_pipeline.run(spark, SF).collect()
    assert {r["doc_id"] for r in got} == want and len(meta) >= len(want) > 0
    check_packed(got, 4096)
