"""Packing documents into sequences by length patterns.

Only the histogram of piece lengths, at most `capacity` counts, reaches the driver. Patterns of two to five lengths that
nearly fill a sequence are enumerated from the lengths that occur; non-negative least squares fits their repeat counts to
the histogram; the counts are rounded up within what is there, which places most pieces, and the residual ones go, longest
first, where they fit best: into the room that patterns leave or into new sequences. The plan is a table of runs: the pieces of one length with ranks
in [from, to) fill the same place of successive sequences, so each row finds its own sequence from its length and rank.

Defined cases: null text is empty and has just the end id; only pieces of documents longer than the capacity are cut;
repeated rows are packed each for itself; texts of any length are read whole; ties between patterns go by their order, so a
plan is the same each time; an empty table gives no rows; other columns are not read, so names that clash do no harm.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections import defaultdict
from typing import NamedTuple

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from quotaknn.llm.common import encoder, keyed, materialise, numbered, tidied, tokenizer_path

PIECES = "row_key long, doc_id long, piece int, start long, length int, ids_crc32 long"


class Plan(NamedTuple):
    chosen: dict  # pattern (lengths, longest first) -> repeats
    by_patterns: int  # pieces placed by fitted patterns, full sequences among them; best fit placed the others
    pieces: int
    least: int  # no packing has fewer sequences


def patterns(hist: np.ndarray, capacity: int, most: int = 24_000, members: int = 5, seed: int = 1) -> np.ndarray:
    """Rows of two to `members` lengths (0: none) that nearly fill a sequence, about `most` in all.

    The lengths before the last are drawn from the pieces that still fit, evenly over their number, so that patterns take
    lengths as often as they occur; the last is the largest length that still fits."""
    have = np.flatnonzero(hist[:capacity])
    if not len(have):
        return np.zeros((0, members), np.int64)
    cum, rng, each, out = np.cumsum(hist[have]), np.random.default_rng(seed), most // (members - 1), []
    for m in range(2, members + 1):
        share = (np.argsort(rng.random((each, m - 1)), axis=0) + 0.5) / each
        room, rows = np.full(each, capacity), np.zeros((each, members), np.int64)
        for j in range(m):
            fit = np.searchsorted(have, room, side="right")
            pick = fit - 1
            if j < m - 1:
                pick = np.minimum(pick, np.searchsorted(cum, share[:, j] * cum[np.maximum(fit - 1, 0)], side="right"))
            rows[:, j] = np.where(fit > 0, have[np.maximum(pick, 0)], 0)
            room = room - rows[:, j]
        out.append(rows)
    found = -np.sort(-np.concatenate(out), axis=1)
    found = np.unique(found[found[:, 1] > 0], axis=0)
    return found[capacity - found.sum(1) <= max(1, capacity // 128)]


def nnls(pat: np.ndarray, hist: np.ndarray, steps: int = 250) -> np.ndarray:
    """Repeat counts x >= 0 with the least sum of squares of (pattern counts - histogram), by accelerated projection."""
    if not len(pat):
        return np.zeros(0)
    m = len(hist)
    used = pat > 0
    count = lambda x: np.bincount(pat[used], weights=np.repeat(x, used.sum(1)), minlength=m)
    back = lambda r: (r[pat] * used).sum(1)
    v = np.ones(len(pat))
    for _ in range(20):
        w = back(count(v))
        top = np.linalg.norm(w)
        v = w / top
    x = y = np.zeros(len(pat))
    t = 1.0
    for _ in range(steps):
        nxt = np.maximum(0, y - back(count(y) - hist) / (1.05 * top))
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        y = nxt + (t - 1) / t2 * (nxt - x)
        x, t = nxt, t2
    return x


def best_fit(residual: dict[int, int], started: dict[tuple, int], capacity: int) -> dict[tuple, int]:
    """Adds the residual pieces, longest first, to the sequences started or to new ones; pattern -> repeats."""
    room: dict[int, dict[tuple, int]] = defaultdict(dict)
    for p, n in started.items():
        room[capacity - sum(p)][p] = room[capacity - sum(p)].get(p, 0) + n
    spaces = sorted(room)

    def put(p: tuple, n: int) -> None:
        s = capacity - sum(p)
        if s not in room or not room[s]:
            insort(spaces, s) if s not in spaces[bisect_left(spaces, s) : bisect_left(spaces, s) + 1] else None
        room[s][p] = room[s].get(p, 0) + n

    for length in sorted(residual, reverse=True):
        left = residual[length]
        while left:
            i = bisect_left(spaces, length)
            if i == len(spaces):
                each = min(capacity // length, left)
                put((length,) * each, max(1, left // each))
                left -= each * max(1, left // each)
                continue
            s = spaces[i]
            p, n = next(iter(room[s].items()))
            k = min(n, left)
            if k == n:
                del room[s][p]
                if not room[s]:
                    spaces.pop(i)
            else:
                room[s][p] = n - k
            put(tuple(sorted((*p, length), reverse=True)), k)
            left -= k
    out: dict[tuple, int] = {}
    for own in room.values():
        for p, n in own.items():
            out[p] = out.get(p, 0) + n
    return out


def plan(hist: dict[int, int], capacity: int) -> Plan:
    """Patterns that hold exactly the pieces of the histogram. Fitted counts are rounded up, the largest first, within the
    pieces that are left; best fit packs the residual."""
    counts = np.zeros(capacity + 1, np.int64)
    for k, v in hist.items():
        counts[k] = v
    pieces, least = int(counts.sum()), -(-int((counts * np.arange(capacity + 1)).sum()) // capacity)
    placed = full = int(counts[capacity])
    counts[capacity] = 0
    pat = patterns(counts, capacity)
    fitted = nnls(pat, counts.astype(float))
    started: dict[tuple, int] = {}
    for i in np.lexsort((capacity - pat.sum(1), -fitted)).tolist():
        if fitted[i] <= 1e-3:
            break
        p = tuple(int(x) for x in pat[i] if x)
        n = min(int(np.ceil(fitted[i])), *(int(counts[x]) // p.count(x) for x in set(p)))
        if n > 0:
            started[p] = n
            placed += n * len(p)
            for x in p:
                counts[x] -= n
    chosen = best_fit({int(k): int(counts[k]) for k in np.flatnonzero(counts)}, started, capacity)
    return Plan(chosen | ({(capacity,): full} if full else {}), placed, pieces, least)


def runs(chosen: dict[tuple, int]) -> np.ndarray:
    """Rows (length, rank from, copies in a sequence, first sequence, first offset), by length and rank."""
    rows, taken, base = [], defaultdict(int), 0
    for p in sorted(chosen, reverse=True):
        n, at = chosen[p], 0
        for length in sorted(set(p), reverse=True):
            each = p.count(length)
            rows.append((length, taken[length], each, base, at))
            taken[length] += n * each
            at += each * length
        base += n
    return np.array(sorted(rows), np.int64).reshape(-1, 5)


def pieces(docs: DataFrame, tokenizer: str, end_id: int, capacity: int, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    def cut(batches):
        import pyarrow as pa

        run = encoder(tokenizer, end_id)
        for b in batches:
            cols: list[list] = [[], [], [], [], [], []]
            for key, k, ids in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), run(b.column(2))):
                for i, at in enumerate(range(0, len(ids), capacity)):
                    own = ids[at : at + capacity]
                    for c, v in zip(cols, (key, k, i, at, len(own), zlib.crc32(own.tobytes()))):
                        c.append(v)
            kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], names=["row_key", "doc_id", "piece", "start", "length", "ids_crc32"])

    rows = keyed(docs, doc_id, text).select("row_key", F.col("doc_id").cast("long").alias("doc_id"), "text")
    return rows.mapInArrow(tidied(cut), PIECES)


def pack(docs: DataFrame, tokenizer: str, end_id: int = 1, capacity: int = 4096, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """row_key, doc_id, piece, start, length, ids_crc32, sequence_id, offset for every piece of every row."""
    cut = materialise(pieces(docs, tokenizer, end_id, capacity, doc_id, text), "pieces")
    hist = {r[0]: r[1] for r in cut.groupBy("length").count().collect()}
    table = runs(plan(hist, capacity).chosen) if hist else np.zeros((0, 5), np.int64)
    shared = docs.sparkSession.sparkContext.broadcast(table)

    def place(batches):
        import pyarrow as pa

        t = shared.value
        keys = (t[:, 0] << 44) | t[:, 1]
        for b in batches:
            length = b.column(b.schema.get_field_index("length")).to_numpy().astype(np.int64)
            rank = b.column(b.schema.get_field_index("rank")).to_numpy().astype(np.int64)
            r = t[np.searchsorted(keys, (length << 44) | rank, side="right") - 1]
            at = rank - r[:, 1]
            made = [pa.array(r[:, 3] + at // r[:, 2]), pa.array(r[:, 4] + at % r[:, 2] * length)]
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], *made], names=[*b.schema.names[:-1], "sequence_id", "offset"])

    ranked = numbered(cut, "length", ["row_key", "piece"], "rank")
    return ranked.mapInArrow(place, PIECES + ", sequence_id long, offset long")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return pack(docs, tokenizer_path("word_bpe_49k.json")).drop("row_key")
