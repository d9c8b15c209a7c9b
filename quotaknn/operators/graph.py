"""Proximity-graph rivals: one graph over all records with a filter while walking, or a graph for each cell large enough.

Edges are a table. A walk serves all queries at once: the beams are a table, each hop one join with the edges, and the beam
is cut to its width by a window. A cell's own graph is walked in one task instead, up to `LOCAL` records. Hops end when no beam holds an unexpanded node, however many that takes (each expands at
least one node of a finite graph); only that one number reaches the driver.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from quotaknn.functions.distance import distance, distance_pairs, near_bound
from quotaknn.functions.lsh import lsh_keys
from quotaknn.operators import retrieve as r
from quotaknn.plans.index import Index
from quotaknn.plans.lineage import cut


@dataclass
class Graph:
    edges: DataFrame  # src, dst, dist
    entries: DataFrame  # scope, rec_id: where walks start; scope is 0 or a cell code
    per_cell: bool
    min_cell: int


#: Records of a cell that meet in one place as sources and as targets, in blocks that are scored as matrices.
GROUP, ROWS = 16_384, 256
#: Records of a cell whose graph is walked in one task; larger ones are walked by joins.
LOCAL = 200_000


def flat(column) -> np.ndarray:
    """Arrow lists of equal length as a matrix."""
    values = column.combine_chunks().flatten() if hasattr(column, "combine_chunks") else column.flatten()
    return values.to_numpy(zero_copy_only=False).reshape(len(column), -1) if len(column) else np.zeros((0, 1))


def nearest_pairs(metric: str, src: np.ndarray, v: np.ndarray, dst: np.ndarray, w: np.ndarray, degree: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each of `src` its `degree` nearest of `dst`, and all that could tie with the last, with exact distances."""
    found: list[tuple] = []
    for i in range(0, len(src), ROWS):
        far, slack = near_bound(metric, v[i : i + ROWS], w)
        far[src[i : i + ROWS, None] == dst[None, :]] = np.inf
        last = np.partition(far, degree - 1, axis=1)[:, degree - 1] if far.shape[1] > degree else np.full(len(far), np.inf, far.dtype)
        at, to = np.divmod(np.flatnonzero((far <= (last + slack)[:, None]).ravel()), far.shape[1])
        at, to = (c[far[at, to] < np.inf] for c in (at, to))
        found.append((src[i + at], dst[to], distance_pairs(metric, v[i + at], w[to]) if len(at) else np.zeros(0)))
    return tuple(np.concatenate(c) for c in zip(*found)) if found else (src[:0], dst[:0], np.zeros(0))


def exact_edges(index: Index, rows: DataFrame, degree: int, per_cell: bool) -> DataFrame:
    """All pairs (of a cell) in blocks: groups of sources meet groups of targets, both as matrices, and hand on `degree` each."""
    scope = F.col("cell_code") if per_cell else F.lit(0).cast("long")
    rows = rows.select("rec_id", "vec", scope.alias("scope"))
    small = F.least(F.lit(4), F.ceil(F.col("n") / 1024))
    sizes = rows.groupBy("scope").agg(F.count(F.lit(1)).alias("n")).select("scope", F.greatest(F.ceil(F.col("n") / GROUP), small).cast("int").alias("groups"))
    dealt = rows.join(sizes, "scope").withColumn("own", F.pmod(F.xxhash64("rec_id"), F.col("groups")).cast("int"))
    every = F.explode(F.sequence(F.lit(0), F.col("groups") - 1))
    side = [F.col(c).alias(d) for c, d in (("scope", "s"), ("rec_id", "id"), ("vec", "v"))]
    a = dealt.select(F.col("own").alias("g"), every.alias("p"), *side)
    b = dealt.select(every.alias("g"), F.col("own").alias("p"), *side)
    metric, keys = index.metric, ["s", "g", "p"]

    def run(sources, targets):
        import pyarrow as pa

        src, dst = sources.column("id").to_numpy(), targets.column("id").to_numpy()
        if not len(src) or not len(dst):
            return pa.table({"src": src[:0], "dst": dst[:0], "dist": np.zeros(0)})
        return pa.table(dict(zip(("src", "dst", "dist"), nearest_pairs(metric, src, flat(sources.column("v")), dst, flat(targets.column("v")), degree))))

    parts = int(min(2_000, max(1, sizes.agg(F.sum(F.col("groups") * F.col("groups"))).head()[0] or 0)))
    a, b = a.repartition(parts, *keys), b.repartition(parts, *keys)
    return a.groupBy(*keys).cogroup(b.groupBy(*keys)).applyInArrow(run, "src long, dst long, dist double")


def knn_edges(index: Index, degree: int, per_cell: bool = False, min_cell: int = 0, candidates: str = "exact") -> DataFrame:
    """src, dst, dist: each record's `degree` nearest others (of its cell). exact compares all pairs, as matrices; lsh only
    pairs that share a bucket."""
    rows = index.vectors.select("rec_id", "vec", "cell_code")
    if min_cell:
        rows = rows.join(index.cells.where(F.col("n_cell") >= min_cell).select("cell_code"), "cell_code")
    if candidates == "exact":
        pairs = exact_edges(index, rows, degree, per_cell)
    else:
        a = rows.select(F.col("rec_id").alias("src"), F.col("vec").alias("v_"))
        b = rows.select(F.col("rec_id").alias("dst"), F.col("vec").alias("w_"))
        keyed = rows.select("rec_id", "cell_code", F.posexplode(lsh_keys(index.family)(F.col("vec"))).alias("t_", "k_"))
        on = ["t_", "k_"] + (["cell_code"] if per_cell else [])
        left = keyed.select(F.col("rec_id").alias("src"), *on)
        right = keyed.select(F.col("rec_id").alias("dst"), *on)
        ids = left.join(right, on).where("src <> dst").select("src", "dst").distinct()
        pairs = ids.join(a, "src").join(b, "dst").select("src", "dst", distance(index.metric, "v_", "w_").alias("dist"))
    rank = F.row_number().over(Window.partitionBy("src").orderBy("dist", "dst"))
    return pairs.withColumn("rank_", rank).where(F.col("rank_") <= degree).drop("rank_")


def spread(metric: str, dist: np.ndarray, x: np.ndarray, degree: int, alpha: float) -> list[int]:
    """Which of a node's edges stay, nearest first: `degree` at most, none that a shorter one that stays makes needless."""
    open_, kept = np.ones(len(dist), bool), []
    while len(kept) < degree and open_.any():
        kept.append(int(open_.argmax()))
        open_ &= alpha * distance_pairs(metric, x[kept[-1]], x) >= dist
        open_[: kept[-1] + 1] = False
    return kept


def pruned(index: Index, near: DataFrame, degree: int, alpha: float, hub: int | None = None) -> DataFrame:
    """Edges both ways, without those that a shorter kept edge makes needless: b is dropped where some kept c has
    alpha * dist(c, b) < dist(node, b). At most `degree` for each node. `hub` bounds the edges of a node that are looked at (its
    nearest), for collections in which single records are near to very many; None looks at all."""
    both = near.unionByName(near.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist")).distinct()
    rows = both.join(index.vectors.select(F.col("rec_id").alias("dst"), "vec"), "dst").select("src", "dst", "dist", "vec")
    metric = index.metric

    def run(batches):
        import pyarrow as pa

        def picked(src, dst, dist, x):
            edge = np.flatnonzero(np.append(True, src[1:] != src[:-1])).tolist() if len(src) else []
            keep = [i + k for i, j in zip(edge, [*edge[1:], len(src)]) for k in spread(metric, dist[i:j], x[i:j], degree, alpha)]
            return pa.RecordBatch.from_arrays([pa.array(c[keep]) for c in (src, dst, dist)], names=["src", "dst", "dist"])

        held = None  # the last node of a batch may go on in the next
        for b in batches:
            own = [*[b.column(i).to_numpy() for i in range(3)], flat(b.column(3))]
            own = own if held is None else [np.concatenate(c) for c in zip(held, own)]
            last = int(np.searchsorted(own[0], own[0][-1])) if len(own[0]) else 0
            held = [c[last:] for c in own] if len(own[0]) else None
            if last:
                yield picked(*[c[:last] for c in own])
        if held is not None:
            yield picked(*held)

    if hub:
        # a hub's own list is cut to its nearest before it meets in one place
        rank = F.row_number().over(Window.partitionBy("src").orderBy("dist", "dst"))
        rows = rows.withColumn("rank_", rank).where(F.col("rank_") <= hub).drop("rank_")
    return rows.repartition("src").sortWithinPartitions("src", "dist", "dst").mapInArrow(run, "src long, dst long, dist double")


def build(index: Index, degree: int = 8, per_cell: bool = False, min_cell: int = 16, alpha: float = 1.0, candidates: str = "exact", hub: int | None = None) -> Graph:
    near = knn_edges(index, degree, per_cell, min_cell if per_cell else 0, candidates)
    edges = cut(pruned(index, near, degree, alpha, hub), "edges")
    scope = F.col("cell_code") if per_cell else F.lit(0).cast("long")
    dims = index.vectors.select(scope.alias("scope"), F.posexplode("vec").alias("i", "x"))
    centre = dims.groupBy("scope", "i").agg(F.avg("x").alias("x")).groupBy("scope").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "x"))), lambda s: s["x"]).alias("c_"))
    rows = index.vectors.select("rec_id", "vec", scope.alias("scope")).join(centre, "scope")
    medoid = rows.groupBy("scope").agg(F.min(F.struct(distance(index.metric, "vec", "c_").alias("d"), "rec_id"))["rec_id"].alias("rec_id"))
    return Graph(edges, cut(medoid, "entries"), per_cell, min_cell)


def walk(graph: Graph, index: Index, queries: DataFrame, starts: DataFrame, allowed: DataFrame | None, ef: int, strict: bool = False) -> DataFrame:
    """query_id, scope, rec_id, dist, accepted: all nodes visited from `starts` (query_id, scope, rec_id). `allowed`
    (query_id, cell_code) tells which nodes may be results; strict walks do not expand the others either."""
    vec = index.vectors.select("rec_id", "vec", "cell_code")
    q = queries.select("query_id", "qvec")

    def judged(ids: DataFrame) -> DataFrame:
        rows = ids.join(vec, "rec_id").join(q, "query_id").withColumn("dist", distance(index.metric, "vec", "qvec")).drop("vec", "qvec")
        if allowed is None:
            return rows.withColumn("accepted", F.lit(True)).drop("cell_code")
        ok = allowed.select("query_id", "cell_code", F.lit(True).alias("accepted")).distinct()
        return rows.join(ok, ["query_id", "cell_code"], "left").withColumn("accepted", F.coalesce("accepted", F.lit(False))).drop("cell_code")

    beam_order = Window.partitionBy("query_id", "scope").orderBy("dist", "rec_id")
    seen = cut(judged(starts).withColumn("expanded", F.lit(False)).select("query_id", "scope", "rec_id", "dist", "accepted", "expanded"), "beam")
    while True:
        inside = seen.where("accepted") if strict else seen
        beam = inside.withColumn("rank_", F.row_number().over(beam_order)).where(F.col("rank_") <= ef).drop("rank_")
        front = beam.where("not expanded").select("query_id", "scope", "rec_id")
        if strict:
            front = front.unionByName(seen.where("not accepted and not expanded").join(starts, ["query_id", "scope", "rec_id"], "left_semi").select("query_id", "scope", "rec_id"))
        front = cut(front.distinct(), "front")
        if front.isEmpty():
            break
        nxt = front.withColumnRenamed("rec_id", "src").join(graph.edges.select("src", F.col("dst").alias("rec_id")), "src").select("query_id", "scope", "rec_id").distinct()
        new = nxt.join(seen.select("query_id", "scope", "rec_id"), ["query_id", "scope", "rec_id"], "left_anti")
        marked = seen.join(front.withColumn("now_", F.lit(True)), ["query_id", "scope", "rec_id"], "left").withColumn("expanded", F.col("expanded") | F.coalesce("now_", F.lit(False))).drop("now_")
        seen = cut(marked.unionByName(judged(new).withColumn("expanded", F.lit(False)).select(marked.columns)), "beam")
    return seen


def beam_walk(metric: str, x: np.ndarray, to: list[np.ndarray], starts: list[int], q: np.ndarray, ef: int) -> tuple[np.ndarray, np.ndarray]:
    """Nodes visited and their distances: all nodes of the beam that are not expanded yet are expanded at once, as in walk."""
    seen = np.unique(starts)
    dist, done = distance_pairs(metric, x[seen], q), np.zeros(len(seen), bool)
    while True:
        beam = np.lexsort((seen, dist))[:ef]
        front = beam[~done[beam]]
        if not len(front):
            return seen, dist
        done[front] = True
        new = np.setdiff1d(np.concatenate([to[i] for i in seen[front]]), seen)
        if len(new):
            seen, dist, done = np.append(seen, new), np.append(dist, distance_pairs(metric, x[new], q)), np.append(done, np.zeros(len(new), bool))


def walk_cells(graph: Graph, index: Index, queries: DataFrame, starts: DataFrame, ef: int) -> DataFrame:
    """query_id, scope, rec_id, dist as from walk without filter, where each scope is a cell: its graph meets its queries once."""
    metric = index.metric
    to = graph.edges.groupBy("src").agg(F.collect_list("dst").alias("to"))
    nodes = index.vectors.select(F.col("cell_code").alias("s"), F.col("rec_id").alias("id"), F.col("vec").alias("x"))
    nodes = nodes.join(starts.select(F.col("scope").alias("s")).distinct(), "s", "left_semi")
    nodes = nodes.join(to.withColumnRenamed("src", "id"), "id", "left").select("s", "id", "x", F.coalesce("to", F.array().cast("array<long>")).alias("to"))
    asks = starts.join(queries.select("query_id", "qvec"), "query_id").select(F.col("scope").alias("s"), F.col("query_id").alias("q"), F.col("rec_id").alias("start"), F.col("qvec").alias("v"))

    def run(nodes, asks):
        import pyarrow as pa

        out: list[list] = [[], [], [], []]
        if len(nodes) and len(asks):
            order = np.argsort(nodes.column("id").to_numpy())
            ids, x = nodes.column("id").to_numpy()[order], flat(nodes.column("x"))[order]
            lists = nodes.column("to").combine_chunks()
            ends = np.append(0, np.cumsum(lists.value_lengths().to_numpy()))
            at = np.searchsorted(ids, lists.flatten().to_numpy())  # edges do not leave the cell
            edges = [at[ends[i] : ends[i + 1]] for i in order]
            scope, query, start, v = asks.column("s")[0].as_py(), asks.column("q").to_numpy(), asks.column("start").to_numpy(), flat(asks.column("v"))
            for one in np.unique(query):
                own = np.flatnonzero(query == one)
                seen, dist = beam_walk(metric, x, edges, np.searchsorted(ids, start[own]), v[own[0]], ef)
                for c, w in zip(out, (np.full(len(seen), one), np.full(len(seen), scope), ids[seen], dist)):
                    c.append(w)
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.float64())
        return pa.Table.from_arrays([pa.array(np.concatenate(c) if c else [], t) for c, t in zip(out, kinds)], names=["query_id", "scope", "rec_id", "dist"])

    nodes, asks = nodes.repartition(32, "s"), asks.repartition(32, "s")
    return nodes.groupBy("s").cogroup(asks.groupBy("s")).applyInArrow(run, "query_id long, scope long, rec_id long, dist double")


def retrieve(graph: Graph, kind: str, index: Index, queries: DataFrame, requests: DataFrame, ef: int = 8, strict: bool = False, exclude: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """graph_filtered walks the whole graph and keeps nodes of the cells asked for; graph_collection walks each cell's own
    graph and scans cells below `min_cell`. The beam holds `ef` nodes, but k at least."""
    if kind == "graph_filtered":
        starts = queries.select("query_id").join(F.broadcast(graph.entries))
        total = requests.select("query_id", "group_id", "quota").distinct().groupBy("query_id").agg(F.sum("quota").alias("k_"))
        width = max(ef, total.agg(F.max("k_")).head()[0] or 0)
        seen = walk(graph, index, queries, starts.select("query_id", "scope", "rec_id"), requests, width, strict)
        results = seen.where("accepted").select("query_id", "rec_id", "dist")
        cells = index.vectors.select("rec_id", "cell_code")
        met = results.join(cells, "rec_id").join(requests.select("query_id", "group_id", "cell_code", "quota"), ["query_id", "cell_code"]).select("query_id", "group_id", "rec_id", "dist", "quota")
        visited = seen.select("query_id", "rec_id")
    elif kind == "graph_collection":
        large = requests.where(F.col("n_cell") >= graph.min_cell)
        width = max(ef, r.most_asked(requests))
        scopes = large.select("query_id", F.col("cell_code").alias("scope"), "n_cell").distinct().join(graph.entries, "scope")
        near, far = (scopes.where(c).select("query_id", "scope", "rec_id").distinct() for c in (F.col("n_cell") <= LOCAL, F.col("n_cell") > LOCAL))
        seen = cut(walk_cells(graph, index, queries, near, width), "beam")
        if not far.isEmpty():
            seen = seen.unionByName(walk(graph, index, queries, far, None, width).select(seen.columns))
        met = seen.withColumnRenamed("scope", "cell_code").join(large.select("query_id", "group_id", "cell_code", "quota"), ["query_id", "cell_code"]).select("query_id", "group_id", "rec_id", "dist", "quota")
        small = requests.where(F.col("n_cell") < graph.min_cell).select("query_id", "group_id", "cell_code", "quota")
        scan = index.vectors.select("rec_id", "vec", "cell_code").join(small, "cell_code")
        scan = r.with_distance(scan, index, queries).select("query_id", "group_id", "rec_id", "dist", "quota")
        met = met.unionByName(scan)
        visited = met.select("query_id", "rec_id")
    else:
        raise ValueError(f"unknown retriever {kind!r}")
    met = r._without(met, exclude)
    return r.nearest(met, r.most_asked(requests)), r.scan_counts(visited)
