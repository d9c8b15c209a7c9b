"""Approximate nearest neighbours by a hash-prefix forest.

A tree is the sorted array of one long sign-hash string for each vector. A query descends in every tree to the longest prefix
it matches; then all trees ascend together, a bit at a time, until their matches are `enough`. What more trees met, and at
longer prefixes, comes first; the first `scored` of a query's matches are scored exactly. Inner products become angles by one
more coordinate that gives all vectors the same norm.

The vectors are dealt at random into pieces of about `PIECE` at most, and each has a forest of its own, which a task builds in
memory. Every query meets every piece, ascends and is scored there, and only its k + 1 nearest of the piece (and ties) are handed
on: neither strings nor matches are ever written. So what is written is in proportion to vectors and to queries x pieces; the work
is queries x vectors in matches looked at, as the matches asked for are a share of a piece. Equal vectors are one node of the
forest, however many rows they have; they are known by digests of 128 bits.

`enough` and `scored` are fitted: for at most `SAMPLE` query vectors (that bound is documented) the true neighbours are found
by an exact scan, one half of them chooses the cheapest setting that reaches the recall `AIM`, the other half measures it.

Defined cases: vectors that are null, zero, or hold null or non-finite components take no part; vectors of each dimension are
searched among themselves; equal scores rank by smaller vec_id; fewer candidates than asked for are all returned; a row with a
null vec_id may be found but asks nothing; repeated rows find each other; an empty table gives no rows; other columns are not
read, so names that clash do no harm.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from quotaknn.llm.common import col, discard, materialise, release

TREES, BITS, HEAD = 128, 24, 12
#: Most vectors of a forest and most queries that meet it in one task; small tables have up to SPREAD forests of LEAST vectors.
PIECE, BLOCK = 65_536, 100_000
SPREAD, LEAST = 16, 4_096
SAMPLE, AIM = 128, 0.96
#: Matches of a query in a piece, as multiples of the piece's vectors, that the fit tries.
TRIED = (0.0625, 0.125, 0.25, 0.5, 1.0, 2.0, 4.0, 8.0)
#: What the exact score of a vector costs, in matches that are counted.
SCORE_COST = 24
RESULT = "query_id long, rank int, vec_id long, score double"


@dataclass(frozen=True)
class Setting:
    enough: float  # matches of a query in a piece, over all trees, as a multiple of the piece's vectors
    scored: int  # candidates of a piece that are scored
    recall: float  # on the half of the sample that did not choose the setting
    vectors: int  # distinct ones


class Hashes:
    """The trees' hash strings of vectors, as integers with the first bit highest."""

    def __init__(self, dim: int, norm: float, seed: int = 11):
        self.norm = norm
        self.planes = np.random.default_rng(seed).standard_normal((dim + 1, TREES * BITS)).astype(np.float32)

    def codes(self, vectors: np.ndarray, asks: bool) -> np.ndarray:
        """(rows, TREES); the coordinate more makes up for the norm, and is 0 for a vector that asks."""
        out = np.empty((len(vectors), TREES), np.int32)
        for i in range(0, len(vectors), 512):
            v = vectors[i : i + 512]
            rest = np.zeros(len(v)) if asks else np.sqrt(np.maximum(self.norm**2 - (v**2).sum(1), 0))
            # scaled, so that single precision holds the largest and the smallest vectors
            own = np.column_stack([v, rest]) / (np.abs(v).max(1, initial=0, keepdims=True) if asks else self.norm)
            three = np.packbits((own.astype(np.float32) @ self.planes > 0).reshape(-1, TREES, BITS), axis=-1).astype(np.int32)
            out[i : i + 512] = three[:, :, 0] << 16 | three[:, :, 1] << 8 | three[:, :, 2]
        return out


def ranges(strings: np.ndarray, asked: np.ndarray, lengths) -> tuple[np.ndarray, np.ndarray]:
    """First and end place in the sorted `strings` of the matches of each prefix length, as (length, query)."""
    lo, hi = [], []
    for x in lengths:
        head = asked >> (BITS - x)
        lo.append(np.searchsorted(strings, head << (BITS - x), side="left"))
        hi.append(np.searchsorted(strings, (head + 1) << (BITS - x), side="left"))
    return np.array(lo).reshape(len(lo), len(asked)), np.array(hi).reshape(len(lo), len(asked))


def matched(lo: np.ndarray, hi: np.ndarray, shortest: int) -> np.ndarray:
    """How long the prefix is that each place in [lo[0], hi[0]) matches; the ranges of longer prefixes are nested."""
    out = np.full(hi[0] - lo[0], shortest, np.int8)
    for k in range(1, len(lo)):
        if lo[k] == hi[k]:
            break
        out[lo[k] - lo[0] : hi[k] - lo[0]] = shortest + k
    return out


def ranked(nodes: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """The distinct nodes, those first that were matched by most bits in all trees."""
    own, at = np.unique(nodes, return_inverse=True)
    bits = np.bincount(at, weights=lengths)
    return own[np.lexsort((own, -bits))]


def flat(column) -> np.ndarray:
    """Arrow lists of equal length as a matrix."""
    values = column.flatten() if not hasattr(column, "combine_chunks") else column.combine_chunks().flatten()
    values = values.to_numpy(zero_copy_only=False).astype(np.float64, copy=False)
    return values.reshape(len(column), -1) if len(column) else np.zeros((0, 1))


class Trees:
    """The forest of one piece, in memory."""

    def __init__(self, hashes: Hashes, vectors: np.ndarray):
        codes = np.ascontiguousarray(hashes.codes(vectors, False).T)
        self.n = len(vectors)
        self.order = np.empty(codes.shape, np.int32)
        heads = (np.arange((1 << HEAD) + 1) << (BITS - HEAD)).astype(np.int32)
        self.starts = np.empty((TREES, len(heads)), np.int32)  # first place of each head, for prefixes of at most HEAD bits
        for t in range(TREES):
            self.order[t] = np.argsort(codes[t])
            codes[t] = codes[t][self.order[t]]
            self.starts[t] = np.searchsorted(codes[t], heads)
        self.strings = codes

    def spans(self, asked: np.ndarray, x: int) -> tuple[np.ndarray, np.ndarray]:
        """First and end place of the matches of prefix length x, as (query, tree)."""
        if x <= HEAD:
            at = ((asked >> (BITS - x)) << (HEAD - x)) + np.arange(TREES) * self.starts.shape[1]
            return self.starts.ravel()[at], self.starts.ravel()[at + (1 << (HEAD - x))]
        each = [ranges(s, a, [x]) for s, a in zip(self.strings, asked.T)]
        return np.stack([lo[0] for lo, _ in each], 1), np.stack([hi[0] for _, hi in each], 1)

    def ascend(self, asked: np.ndarray, enough: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The longest prefix length at which all trees together have `enough` matches, and their places there. Matches fall
        with the length, so it is found from the root."""
        reach, open_ = np.zeros(len(asked), np.int64), np.arange(len(asked))
        first, end = np.zeros(asked.shape, np.int64), np.full(asked.shape, self.n, np.int64)
        for x in range(1, BITS + 1):
            lo, hi = self.spans(asked[open_], x)
            still = (hi - lo).sum(1) >= enough
            open_ = open_[still]
            if not len(open_):
                break
            reach[open_], first[open_], end[open_] = x, lo[still], hi[still]
        return reach, first, end

    def matches(self, code: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The vectors in the trees' ranges, and how long a prefix each matches there (as `matched` has it for one tree)."""
        size = hi - lo
        at = np.repeat(lo + np.arange(TREES) * self.n - (np.cumsum(size) - size), size) + np.arange(size.sum())
        apart = (self.strings.ravel()[at] ^ np.repeat(code, size)).astype(np.float32)
        return self.order.ravel()[at], BITS - np.maximum((apart.view(np.int32) >> 23) - 126, 0)  # the exponent tells the first bit

    def first(self, code: np.ndarray, lo: np.ndarray, hi: np.ndarray, scored: int) -> np.ndarray:
        """The first `scored` of `ranked`, in no order."""
        bits = np.bincount(*self.matches(code, lo, hi), minlength=self.n).astype(np.int64)
        met = np.flatnonzero(bits)
        if len(met) <= scored:
            return met
        bits = bits[met]
        above = np.cumsum(np.bincount(bits)[::-1])[::-1]  # how many have at least so many bits
        last = int(np.flatnonzero(above >= scored)[-1])
        sure = met[bits > last]
        return np.append(sure, met[bits == last][: scored - len(sure)])


def best(x: np.ndarray, at: np.ndarray, v: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """Those of the rows `at` of x that are among the `most` nearest to v or tie with the last, with their exact scores."""
    score = np.einsum("ij,j->i", x[at], v)  # row by row and in one thread: equal rows have equal scores
    if len(at) > most:
        least = np.partition(score, len(score) - most)[len(score) - most]
        at, score = at[score >= least], score[score >= least]
    return at, score


class Forest:
    """The forests of the vectors of one dimension: `nodes` (node, v) are `total` distinct vectors."""

    def __init__(self, nodes: DataFrame, dim: int, norm: float, total: int):
        self.total, self.hashes = total, Hashes(dim, norm)
        self.count = max(-(-total // PIECE), min(SPREAD, -(-total // LEAST)), 1)
        self.nodes = nodes.select("node", "v", F.pmod(F.xxhash64("node", F.lit(5)), F.lit(self.count)).cast("int").alias("piece"))

    def fit(self, asking: DataFrame, k: int) -> Setting:
        """The cheapest (enough, scored) that finds `AIM` of the true neighbours of one half of a bounded sample."""
        drawn = sorted((r["node"], np.array(r["v"], float)) for r in asking.orderBy(F.xxhash64("node", F.lit(3)), "node").limit(SAMPLE).collect())
        if not drawn:
            return Setting(1.0, k + 1, 1.0, self.total)
        ids, q = np.array([n for n, _ in drawn]), np.array([v for _, v in drawn])
        hashes = self.hashes

        def places(table):
            """The k nearest of the piece and where each setting ranks them there."""
            import pyarrow as pa

            node, v = table.column("node").to_numpy(), flat(table.column("v"))
            trees, codes = Trees(hashes, v), hashes.codes(q, True)
            near, out = [], []
            for i, own in enumerate(ids):
                at, score = best(v, np.flatnonzero(node != own), q[i], k)
                near.append((at, score))
            for e in TRIED:
                reach, lo, hi = trees.ascend(codes, e * trees.n)
                for i, (at, score) in enumerate(near):
                    order = ranked(*trees.matches(codes[i], lo[i], hi[i])) if reach[i] else np.arange(0)
                    order = order[node[order] != ids[i]]
                    place = np.full(trees.n, -1 if reach[i] else 0)
                    place[order] = np.arange(len(order))
                    out += zip([int(ids[i])] * len(at), [e] * len(at), node[at].tolist(), score.tolist(), place[at].tolist())
            release()
            kinds = (pa.int64(), pa.float64(), pa.int64(), pa.float64(), pa.int64())
            return pa.Table.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*out)) or [[]] * 5, kinds)], names=["query", "enough", "node", "score", "place"])

        order = Window.partitionBy("query", "enough").orderBy(F.desc("score"), "node")
        found = self.nodes.repartition(4 * self.count, "piece").groupBy("piece").applyInArrow(places, "query long, enough double, node long, score double, place long")
        found = found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).collect()
        half, most, choices = set(ids[::2].tolist()), -(-self.total // self.count), []
        for e in TRIED:
            own = {h: [r["place"] for r in found if r["enough"] == e and (r["query"] in half) == h] for h in (True, False)}
            at = {h: np.sort([p for p in own[h] if p >= 0]) for h in own}
            need = int(np.ceil(AIM * len(own[True])))
            reached = len(at[True]) >= need
            scored = (int(at[True][need - 1]) + 1 if need else 1) if reached else self.total
            recall = float((at[False] < scored).sum() / len(own[False])) if own[False] else 1.0
            choices.append((not reached, scored * SCORE_COST + e * most, Setting(e, max(scored, k + 1), recall, self.total)))
        return min(choices, key=lambda c: c[:2])[2]

    def nearest(self, asking: DataFrame, setting: Setting, k: int) -> DataFrame:
        """query, node, score: at least the k + 1 best of each piece's candidates, exactly scored. A query that too few match
        ascends to the root, and is scored with the whole piece."""
        parts, hashes = max(1, -(-asking.count() // BLOCK)), self.hashes
        every = F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part")
        own = F.pmod(F.xxhash64("node", F.lit(7)), F.lit(parts)).cast("int").alias("part")
        pairs = [F.col("node").alias("id"), F.col("v").alias("x")]  # new names, as both sides stem from one table
        vectors = self.nodes.select(F.col("piece").alias("p"), every, *pairs)
        asked = asking.select(F.explode(F.sequence(F.lit(0), F.lit(self.count - 1))).alias("p"), own, *pairs)
        keys, tasks = ["p", "part"], min(20_000, 4 * parts * self.count)

        def run(vectors, queries):
            import pyarrow as pa

            out: list[list] = [[], [], []]
            if len(vectors) and len(queries):
                order = np.argsort(vectors.column("id").to_numpy())
                ids, x = vectors.column("id").to_numpy()[order], flat(vectors.column("x"))[order]
                trees, enough = Trees(hashes, x), setting.enough * len(ids)
                asks, v = queries.column("id").to_numpy(), flat(queries.column("x"))
                for i in range(0, len(asks), 512):
                    codes = hashes.codes(v[i : i + 512], True)
                    reach, lo, hi = trees.ascend(codes, enough)
                    mine = np.searchsorted(ids, asks[i : i + 512])
                    for j, query in enumerate(asks[i : i + 512].tolist()):
                        whole = not reach[j] or setting.scored >= len(ids)
                        at = np.arange(len(ids)) if whole else trees.first(codes[j], lo[j], hi[j], setting.scored + 1)
                        if len(at) <= k:
                            at = np.arange(len(ids))
                        elif mine[j] < len(ids) and ids[mine[j]] == query and mine[j] not in at:
                            at = np.append(at, mine[j])  # other rows may hold the query's own vector
                        at, score = best(x, at, v[i + j], k + 1)
                        out[0].append(np.full(len(at), query))
                        out[1].append(ids[at])
                        out[2].append(score)
                del trees, x
                release()
            kinds = (pa.int64(), pa.int64(), pa.float64())
            return pa.Table.from_arrays([pa.array(np.concatenate(c) if c else [], t) for c, t in zip(out, kinds)], names=["query", "node", "score"])

        vectors, asked = vectors.repartition(tasks, *keys), asked.repartition(tasks, *keys)
        return vectors.groupBy(*keys).cogroup(asked.groupBy(*keys)).applyInArrow(run, "query long, node long, score double")


def sound(v) -> object:
    """Whether a vector takes part."""
    return v.isNotNull() & ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists(v, lambda x: x != 0)


def forests(table: DataFrame, every: int, vec_id: str, vector: str) -> tuple[DataFrame, list[tuple[Forest, DataFrame]]]:
    """(vec_id, row, node) of all sound rows, and for each dimension its forest and the nodes (node, v) that ask."""
    # single precision stays as it is on disk; arithmetic is in double precision throughout
    narrow = dict(table.select(col(vector).alias("v")).dtypes)["v"] == "array<float>"
    v = col(vector) if narrow else col(vector).cast("array<double>")
    rows = table.select(F.monotonically_increasing_id().alias("row"), col(vec_id).cast("long").alias("vec_id"), v.alias("v")).where(sound(F.col("v")))
    rows = materialise(rows.withColumns({"a": F.xxhash64("v"), "b": F.xxhash64(F.lit(2), "v")}), "vectors")
    asks = F.coalesce(F.col("vec_id") % every == 0, F.lit(False))
    nodes = rows.groupBy("a", "b").agg(F.min("row").alias("node"), F.max(asks).alias("asks"), F.first("v").alias("v"))
    nodes = materialise(nodes.withColumn("dim", F.size("v")), "nodes")
    members = materialise(rows.select("vec_id", "row", "a", "b").join(nodes.select("a", "b", "node"), ["a", "b"]).select("vec_id", "row", "node"), "members")
    discard(rows)
    norm2 = F.aggregate("v", F.lit(0.0), lambda a, x: a + x.cast("double") * x)
    made = []
    for r in nodes.groupBy("dim").agg(F.sqrt(F.max(norm2)).alias("norm"), F.count(F.lit(1)).alias("n"), F.max("asks").alias("asks")).orderBy("dim").collect():
        if r["asks"]:
            own = nodes.where(F.col("dim") == r["dim"])
            made.append((Forest(own.select("node", "v"), r["dim"], r["norm"], r["n"]), own.where("asks").select("node", "v")))
    return members, made


def search(table: DataFrame, every: int = 20, k: int = 20, vec_id: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score for the rows whose id `every` divides, against all rows."""
    members, made = forests(table, every, vec_id, vector)
    if not made:
        return table.sparkSession.createDataFrame([], RESULT)
    found = [f.nearest(asking, f.fit(asking, k), k) for f, asking in made]
    # a query's k + 1 nearest of all pieces, and what ties with the last
    nearest = F.rank().over(Window.partitionBy("query").orderBy(F.desc("score")))
    found = reduce(DataFrame.unionByName, found).withColumn("place", nearest).where(F.col("place") <= k + 1).drop("place")
    # of equal vectors, the k + 1 rows with the least ids can be among a query's k nearest
    place = F.row_number().over(Window.partitionBy("node").orderBy(F.col("vec_id").asc_nulls_last(), "row"))
    heads = materialise(members.withColumn("place", place).where(F.col("place") <= k + 1).select("node", "vec_id", "row"), "heads")
    order = Window.partitionBy("query").orderBy(F.desc("score"), F.col("vec_id").asc_nulls_last(), "row")
    rows = found.join(heads, "node").withColumn("place", F.row_number().over(order)).where(F.col("place") <= k + 1)
    lists = rows.groupBy("query").agg(F.array_sort(F.collect_list(F.struct("place", "vec_id", "row", "score"))).alias("near"))
    lists = materialise(lists, "near")
    asked = members.where(F.col("vec_id") % every == 0).select(F.col("vec_id").alias("query_id"), F.col("row").alias("own"), F.col("node").alias("query"))
    each = asked.join(lists, "query").select("query_id", F.posexplode(F.slice(F.filter("near", lambda x: x["row"] != F.col("own")), 1, k)).alias("at", "x"))
    return each.select("query_id", (F.col("at") + 1).cast("int").alias("rank"), F.col("x.vec_id").alias("vec_id"), F.col("x.score").alias("score"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return search(spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding"))
