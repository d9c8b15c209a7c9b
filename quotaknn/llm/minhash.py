"""Near-duplicate documents by bottom-k sketches from one hash function.

A document's set holds a 64-bit hash of each distinct shingle of words. One fixed order, that of the hashes themselves,
makes all sketches: the `SKETCH` least values of a set. Equal sets are one node from the start. Two adjacent retained values
make a posting key: sets that share four fifths of their shingles differ in so few values that some two neighbours of their
joint order are common to both. That is certain while the union holds under about 90 shingles; beyond, each of the first
`RETAINED` places is common with chance 0.8, and no two neighbours are with chance below 3e-12.

Links are found in two rounds. First each inverted list is compared with its most central member alone (a star, as many
pairs as postings). Lists whose members are then all in one component are done; in the others every pair of members in
different components is still compared: short lists by a join, long ones in blocks whose pairs stay inside a task. In both
rounds the estimate from the union of two sketches filters and exact Jaccard on full sets decides.

Defined cases: null text, empty text or text without words has the empty set and links with nothing; a text shorter than a
shingle is one shingle; texts of any length are read whole; repeated rows are equal sets; rows with null doc_id take part
but cannot be the least id, and are kept where their component has no id at all; an empty table gives no rows; other columns
are not read, so names that clash do no harm.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from quotaknn.llm.common import col, components, discard, fresh, hash_rows, lean, materialise, placed, settled, slabs, text_bytes, with_place

SKETCH, RETAINED = 64, 40
LONG_LIST, BLOCK, WIDE = 16, 768, 256
#: Rows of a batch that are turned into Python objects at once, and rows of a block whose pairs are weighed at once.
AT_ONCE, STRIP = 1024, 128
#: An estimate below this from 64 values has a chance near 1e-8 for sets of similarity 0.8.
LEAST_ESTIMATE = 0.5
LONG_WORD = 64

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_BREAK = np.zeros(256, bool)
_BREAK[[32, 9, 10, 11, 12, 13]] = True
_BYTE = hash_rows(np.arange(1, 257, dtype=np.uint64))
_STEP = np.uint64(0xD1342543DE82EF95)
_ODD = hash_rows(np.arange(1001, 1065, dtype=np.uint64)) | np.uint64(1)


def shingle_sets(data: np.ndarray, offsets: np.ndarray, words: int) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text given as bytes end to end."""
    n = len(offsets) - 1
    if not len(data):
        return [np.zeros(0, np.uint64)] * n
    low = _LOWER[data]
    inside = ~_BREAK[low]
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    heads = offsets[:-1][offsets[:-1] < len(data)]
    first[heads] = inside[heads]
    starts = np.flatnonzero(first)
    if not len(starts):
        return [np.zeros(0, np.uint64)] * n
    place = np.arange(len(data)) - np.repeat(starts, np.diff(np.append(starts, len(data)))) if starts[0] == 0 else np.concatenate(
        [np.zeros(starts[0], np.int64), np.arange(starts[0], len(data)) - np.repeat(starts, np.diff(np.append(starts, len(data))))]
    )
    power = np.cumprod(np.full(int(place.max()) + 2, _STEP, np.uint64))
    part = _BYTE[low] * power[place]
    part[~inside] = 0
    size = np.add.reduceat(inside, starts, dtype=np.uint64)
    word = hash_rows(np.add.reduceat(part, starts) + size * _ODD[40])
    # sums of powers collide by their making on long words whose halves mirror each other; those get a digest instead
    for i in np.flatnonzero(size > LONG_WORD).tolist():
        own = low[starts[i] : starts[i] + int(size[i])].tobytes()
        word[i] = np.frombuffer(hashlib.blake2b(own, digest_size=8).digest(), np.uint64)[0]
    of = np.searchsorted(offsets, starts, side="right") - 1
    count = np.bincount(of, minlength=n)
    at = np.concatenate([[0], np.cumsum(count)])
    m = max(0, len(word) - words + 1)
    joint = np.zeros(m, np.uint64)
    for k in range(words):
        joint += word[k : k + m] * _ODD[k]
    joint = hash_rows(joint)
    out = []
    for i in range(n):
        c = int(count[i])
        if c >= words:
            out.append(np.unique(joint[at[i] : at[i] + c - words + 1]))
        elif c:
            own = (word[at[i] : at[i] + c] * _ODD[50 : 50 + c]).sum(dtype=np.uint64) + np.uint64(c)
            out.append(hash_rows(np.array([own])))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def sets_of(column, words: int):
    data, offs = text_bytes(column)
    for i, j in slabs(offs, 1 << 20):
        yield from shingle_sets(data[offs[i] : offs[j]], offs[i : j + 1] - offs[i], words)


def sketches(docs: DataFrame, words: int) -> DataFrame:
    """row_key, doc_id, n, digest of the set, sketch (the least hashes in order, as bytes) of (row_key, doc_id, text)."""

    def run(batches):
        import pyarrow as pa

        for b in batches:
            n, digest, sketch = [], [], []
            for s in sets_of(b.column(2), words):
                n.append(len(s))
                digest.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest())
                sketch.append(s[:SKETCH].tobytes())
            yield pa.RecordBatch.from_arrays(
                [b.column(0), b.column(1), pa.array(n, pa.int64()), pa.array(digest, pa.binary()), pa.array(sketch, pa.binary())],
                names=["row_key", "doc_id", "n", "digest", "sketch"],
            )

    return docs.select("row_key", "doc_id", "text").mapInArrow(lean(run), "row_key long, doc_id long, n long, digest binary, sketch binary")


def postings(nodes: DataFrame) -> DataFrame:
    """key, node, n: one row for each two neighbours among a node's retained values."""

    def run(batches):
        import pyarrow as pa

        for b in batches:
            keys, of = [], []
            for i, s in enumerate(b.column(2).to_pylist()):
                v = np.frombuffer(s, np.uint64)[:RETAINED]
                if len(v) > 1:
                    keys.append(hash_rows(v[:-1] * _ODD[60] + v[1:] * _ODD[61]))
                    of.append(np.full(len(v) - 1, i))
            if keys:
                at = pa.array(np.concatenate(of))
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.concatenate(keys).view(np.int64)), b.column(0).take(at), b.column(1).take(at)], names=["key", "node", "n"]
                )

    return nodes.select("node", "n", "sketch").mapInArrow(lean(run), "key long, node long, n long")


def estimate(a: bytes, b: bytes) -> float:
    """Jaccard similarity as seen in the least values of the union of two sketches."""
    x, y = np.frombuffer(a, np.uint64), np.frombuffer(b, np.uint64)
    both, times = np.unique(np.concatenate([x, y]), return_counts=True)
    return float((times[:SKETCH] == 2).mean()) if len(both) else 0.0


@F.pandas_udf(T.DoubleType())
def _estimates(a, b):
    import pandas as pd

    return pd.Series([estimate(x, y) for x, y in zip(a, b)], dtype="float64")


def plausible(pairs: DataFrame, nodes: DataFrame) -> DataFrame:
    """The pairs (a, b) whose sketches do not rule them out."""
    s = nodes.select("node", "sketch")
    own = pairs.join(s.select(F.col("node").alias("a"), F.col("sketch").alias("sa")), "a")
    own = own.join(s.select(F.col("node").alias("b"), F.col("sketch").alias("sb")), "b")
    return own.where(_estimates("sa", "sb") >= LEAST_ESTIMATE).select("a", "b")


def verify(pairs: DataFrame, texts: DataFrame, words: int, percent: int) -> DataFrame:
    """The pairs (a, b) whose full sets are similar enough. `a` and its partners meet in one place, in parts of about a
    thousand partners, so that no task holds a node of very many partners alone."""
    parts = pairs.groupBy("a").agg(F.ceil(F.count(F.lit(1)) / 1000).cast("int").alias("parts"))
    member = pairs.join(parts, "a").select(F.col("b").alias("node"), "a", F.pmod(F.xxhash64("b"), F.col("parts")).cast("int").alias("part"), F.lit(1).alias("role"))
    pivot = parts.select(F.col("a").alias("node"), "a", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.lit(0).alias("role"))
    sent = texts.join(member.unionByName(pivot), "node").select("a", "part", "role", "node", "text")
    sent = sent.repartition("a", "part").sortWithinPartitions("a", "part", "role")

    def run(batches):
        import pyarrow as pa

        mine = None
        for b in batches:
            us, vs = [], []
            for a, role, node, s in zip(b.column(0).to_pylist(), b.column(2).to_pylist(), b.column(3).to_pylist(), sets_of(b.column(4), words)):
                if role == 0:
                    mine = s
                    continue
                at = np.searchsorted(mine, s)
                common = int((mine[np.minimum(at, len(mine) - 1)] == s).sum())
                if 100 * common >= percent * (len(mine) + len(s) - common):
                    us.append(a)
                    vs.append(node)
            yield pa.RecordBatch.from_arrays([pa.array(us, pa.int64()), pa.array(vs, pa.int64())], names=["u", "v"])

    return sent.mapInArrow(lean(run), "u long, v long")


def fits(a: str, b: str, percent: int):
    return F.least(F.col(a), F.col(b)) * 100 >= F.greatest(F.col(a), F.col(b)) * percent


def shared_counts(values: list[np.ndarray], chunk: int) -> np.ndarray:
    """(i, j): how many values two arrays (of distinct values) share, by products of their incidence, some columns at once."""
    n = len(values)
    _, inv, times = np.unique(np.concatenate(values), return_inverse=True, return_counts=True)
    column, met = np.cumsum(times > 1) - 1, times[inv] > 1
    at, column = np.repeat(np.arange(n), [len(v) for v in values])[met], column[inv[met]]
    out = np.zeros((n, n), np.float32)
    for c in range(0, int((times > 1).sum()), chunk):
        own = (column >= c) & (column < c + chunk)
        m = np.zeros((n, chunk), np.float32)
        m[at[own], column[own] - c] = 1
        for i in range(0, n, 256):
            out[i : i + 256] += m[i : i + 256] @ m.T
    return out


def block_pairs(rows: list[tuple], percent: int) -> tuple[np.ndarray, np.ndarray]:
    """The pairs of nodes, each node once as the lesser, that meet in this block first and that sizes, cores and sketches leave.
    The matrices of pairs are made `STRIP` rows at a time; whole are only what two nodes share and what is still possible.

    A row is (own block, node, n, root, sketch, i, j, core, keys, key)."""
    ids = np.array([r[1] for r in rows])
    # two nodes are compared in the first list that they share
    lower = [np.array(r[8], np.int64) for r in rows]
    lower = [k[k < rows[0][9]] for k in lower]
    own, size, root, core = (np.array([r[k] for r in rows]) for k in (0, 2, 3, 7))
    ok = shared_counts(lower, 2048) == 0
    for s in (slice(i, i + STRIP) for i in range(0, len(rows), STRIP)):
        ok[s] &= (ids[s, None] < ids) & (root[s, None] != root)
        ok[s] &= 100 * np.minimum.outer(size[s], size) >= percent * np.maximum.outer(size[s], size)
        ok[s] &= (100 + percent) * np.minimum.outer(core[s], core) >= percent * np.add.outer(size[s], size)
        if rows[0][6] != rows[0][5]:
            ok[s] &= own[s, None] != own
    left = np.flatnonzero(ok.any(0) | ok.any(1))
    if not len(left):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    ids, size, ok = ids[left], size[left], ok[np.ix_(left, left)]
    values = [np.frombuffer(rows[i][4], np.uint64) for i in left]
    common = shared_counts(values, 1024)
    held = np.array([len(v) for v in values])
    for s in (slice(i, i + STRIP) for i in range(0, len(left), STRIP)):
        both, most = np.add.outer(size[s], size), np.maximum.outer(size[s], size)
        # where both sketches are whole sets this is exact; else what similar sets must share, less six deviations
        share = np.minimum(1.0, percent * both / ((100 + percent) * most))
        some = np.minimum.outer(held[s], held)
        ok[s] &= common[s] >= some * share - 6 * np.sqrt(some * share * (1 - share)) - 1e-3
        ok[s] &= (most > WIDE) | (100 * common[s] >= percent * (both - common[s]) - 1e-3)
    x, y = np.nonzero(ok)
    return ids[x], ids[y]


def cores(members: DataFrame, texts: DataFrame, words: int) -> DataFrame:
    """node, core: how many of a node's shingles occur in another node of `members` too. No partner there can share more."""

    def run(batches):
        import pyarrow as pa

        for b in (x.slice(at, AT_ONCE) for x in batches for at in range(0, x.num_rows, AT_ONCE)):
            nodes = b.column(0).to_numpy()
            sets = list(sets_of(b.column(1), words))
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.concatenate(sets).view(np.int64)), pa.array(np.repeat(nodes, [len(x) for x in sets]))], names=["shingle", "node"]
            )

    every = texts.join(members.select("node").distinct(), "node").select("node", "text").mapInArrow(lean(run), "shingle long, node long")
    own = every.groupBy("shingle").agg(F.count(F.lit(1)).alias("times"), F.min("node").alias("node")).where("times = 1")
    lone = own.groupBy("node").agg(F.count(F.lit(1)).alias("lone"))
    return members.join(lone, "node", "left").withColumn("core", F.col("n") - F.coalesce("lone", F.lit(0))).drop("lone")


def wide_sketches(members: DataFrame, texts: DataFrame, words: int) -> DataFrame:
    """node, sketch: the `WIDE` least values, for the nodes that meet in blocks."""

    def run(batches):
        import pyarrow as pa

        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x[:WIDE].tobytes() for x in sets_of(b.column(1), words)], pa.binary())], names=["node", "sketch"])

    return texts.join(members.select("node").distinct(), "node").select("node", "text").mapInArrow(lean(run), "node long, sketch binary")


def mixed(members: DataFrame) -> DataFrame:
    """The members of lists with more than one component, and `c`, how many the list has."""
    lists = members.groupBy("key").agg(F.min("root").alias("r0"), F.max("root").alias("r1"), F.count(F.lit(1)).alias("c"), F.min("n").alias("least"))
    lists = materialise(lists.where("r0 <> r1").select("key", "c", "least"), "lists")
    return members.drop("c", "least").join(lists, "key")


def unresolved(shared: DataFrame, roots: DataFrame, nodes: DataFrame, texts: DataFrame, words: int, percent: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Pairs (a, b) in one list that may still be links between two components, after two tables they are made from."""
    open_ = materialise(mixed(shared.join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))), "open")
    short = open_.where(F.col("c") <= LONG_LIST).select("key", "node", "n", "root")
    other = short.select("key", F.col("node").alias("b"), F.col("n").alias("nb"), F.col("root").alias("rb"))
    few = short.join(other, "key").where("node < b and root <> rb").where(fits("n", "nb", percent)).select(F.col("node").alias("a"), "b").distinct()
    # members that hold too many shingles of their own to be like any other member are done
    long_ = cores(open_.where(F.col("c") > LONG_LIST), texts, words)
    least = F.greatest(F.col("least") * 100, F.col("n") * percent)
    kept = materialise(mixed(long_.where(F.col("core") * (100 + percent) * 100 >= percent * (F.col("n") * 100 + least))), "long")
    # a long list is dealt into blocks; each two blocks meet in one place, where sizes, cores and sketches rule most pairs out
    many = kept.withColumn("blocks", F.ceil(F.col("c") / BLOCK).cast("int"))
    many = many.withColumn("own", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    many = many.withColumn("with", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    many = many.select("key", F.least("own", "with").alias("i"), F.greatest("own", "with").alias("j"), "own", "node", "n", "root", "core")
    lists = kept.groupBy("node").agg(F.collect_list("key").alias("keys"))
    many = many.join(lists.join(wide_sketches(kept, texts, words), "node"), "node").repartition("key", "i", "j").sortWithinPartitions("key", "i", "j")

    def run(batches):
        import pyarrow as pa

        def close(rows):
            a, b = block_pairs(rows, percent)
            return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

        rows, last = [], None
        for b in (x.slice(at, AT_ONCE) for x in batches for at in range(0, x.num_rows, AT_ONCE)):
            d = [b.column(k).to_pylist() for k in range(10)]
            for key, i, j, own, node, n, root, sk, core, keys in zip(*d):
                if (key, i, j) != last and rows:
                    yield close(rows)
                    rows = []
                last = (key, i, j)
                rows.append((own, node, n, root, sk, i, j, core, keys, key))
        if rows:
            yield close(rows)

    dense = many.select("key", "i", "j", "own", "node", "n", "root", "sketch", "core", "keys").mapInArrow(lean(run), "a long, b long")
    return open_, kept, plausible(few, nodes).unionByName(dense).distinct()


def near_duplicates(docs: DataFrame, words: int = 5, percent: int = 80, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """row_key, doc_id, n_shingles, component_id (least doc_id reachable), stays (one row of each component).

    `percent` is 80 or more: the sketch sizes and the filter are chosen for that, and lesser similarities would lose links."""
    if percent < 80:
        raise ValueError("sketches are sized for a similarity of 80 percent or more")
    docs = placed(docs, doc_id, text)
    rows = materialise(sketches(docs, words), "sketches")
    filled = rows.where("n > 0")
    nodes = materialise(
        filled.groupBy("digest").agg(F.min(F.struct(F.col("doc_id").isNull(), "doc_id", "row_key", "n", "sketch")).alias("m"))
        .select("digest", F.col("m.row_key").alias("node"), F.col("m.doc_id").alias("least_id"), F.col("m.n").alias("n"), F.col("m.sketch").alias("sketch")),
        "nodes",
    )
    every = postings(nodes)
    # tables of their own, as Spark can split a hot key in a join of two tables, not in one that continues an aggregation
    counts = materialise(every.groupBy("key").agg(F.count(F.lit(1)).alias("c")).where("c > 1"), "counts")
    shared = materialise(every.join(counts, "key"), "shared")
    score = shared.groupBy("node").agg(F.sum(F.log2("c")).alias("score"))
    rated = shared.join(score, "node")
    pivots = rated.groupBy("key").agg(F.max(F.struct("score", "node", "n")).alias("p")).select("key", F.col("p.node").alias("a"), F.col("p.n").alias("na"))
    pivots = materialise(pivots, "pivots")
    stars = rated.join(pivots, "key").where("node <> a").where(fits("n", "na", percent)).select("a", F.col("node").alias("b")).distinct()
    texts = materialise(
        docs.select(F.col("row_key").alias("node"), "text").join(shared.select("node").distinct(), "node"), "texts"
    )
    first = materialise(verify(plausible(stars, nodes), texts, words, percent), "verified")
    roots = materialise(components(first), "roots")
    open_, many, rest = unresolved(shared, roots, nodes, texts, words, percent)
    second = materialise(verify(rest, texts, words, percent), "verified")
    discard(open_, many, shared, texts)
    if not second.isEmpty():
        roots = materialise(components(first.unionByName(second)), "roots")
    rooted = nodes.select("digest", "node", "least_id").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    best = rooted.groupBy("root").agg(F.min(F.struct(F.col("least_id").isNull(), F.col("least_id").alias("component_id"), F.col("node").alias("stay"))).alias("m"))
    named = rooted.join(best, "root").select("digest", F.col("m.component_id").alias("component_id"), F.col("m.stay").alias("stay"))
    found = filled.select("row_key", "doc_id", "n", "digest").join(named, "digest").select(
        "row_key", "doc_id", F.col("n").alias("n_shingles"), "component_id", (F.col("row_key") == F.col("stay")).alias("stays")
    )
    alone = rows.where("n = 0").select("row_key", "doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id"), F.lit(True).alias("stays"))
    return found.unionByName(alone)


def drop_near_copies(docs: DataFrame, words: int = 5, percent: int = 80, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """`docs` with one row of each component; all columns stay as they are."""
    docs, key = settled(docs), fresh(docs, "row_key")
    gone = near_duplicates(docs, words, percent, doc_id, text).where(~F.col("stays")).select(F.col("row_key").alias(key))
    return with_place(docs, key).join(gone, key, "left_anti").select(*[col(c) for c in docs.columns])


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return near_duplicates(docs, words=4).select(
        "doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept")
    )
