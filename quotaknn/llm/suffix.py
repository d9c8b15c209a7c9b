"""Removal of repeated byte strings with suffix arrays.

Every byte inside a string of `span` bytes that also starts elsewhere goes. All strings of that length meet their equals,
without all suffixes of the corpus in one place:

1. A window of `span` bytes has an anchor, the leftmost least hash among its grams; equal windows have equal anchors at
   equal places. A run of windows with one anchor is a segment, and its bytes hold these windows whole.
2. Anchors met with one content (told by a digest) are done: met once, nothing repeats; met again, as in whole copies of a
   text, the segment repeats as it is. Of other anchors, each content goes on in one copy, or in two where it occurs again:
   more copies of the same bytes could tell a suffix array nothing new.
3. Segments are dealt by their anchor's hash into shards of bounded size. A shard sorts its suffixes by Larsson-Sadakane
   refinement, finds common prefixes as Kasai does, and so marks windows whose neighbour shares `span` bytes.
4. An anchor with many contents is dealt over several shards. Each hands on the sorted digests of its windows; they are
   merged by binary search of each shard's digests in the others', in ranges of the digest.
5. Marks of a content are handed to all its copies, united for each document and cut out of its bytes.

Defined cases: null text is empty; matches never cross documents; texts of any length are read whole, in parts that overlap
by a window; repeated rows repeat each other's windows and are both cut; an empty table gives no rows; other columns are not
read, so names that clash do no harm.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from quotaknn.llm.common import discard, hash_rows, materialise, placed, slabs, text_bytes, tidied

GRAM = 32
PART = 1 << 20
SHARD_BYTES = 1 << 20
HOT = 256

_MUL = hash_rows(np.arange(71, 75, dtype=np.uint64)) | np.uint64(1)
_LOW = np.uint64(0xFFFFFFFF)


def digests(data: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """128 bits for each slice of the bytes, as rows of two words."""
    raw = memoryview(np.ascontiguousarray(data)).cast("B")
    made = b"".join(hashlib.blake2b(raw[i : i + k], digest_size=16).digest() for i, k in zip(starts.tolist(), sizes.tolist()))
    return np.frombuffer(made, "<u8").reshape(-1, 2)


def words8(data: np.ndarray, pad: int = 8, big: bool = False) -> np.ndarray:
    """The 8 bytes from each position as uint64, zeros beyond the end."""
    whole = np.concatenate([data, np.zeros(pad + 8, np.uint8)])
    out = np.empty(len(data) + pad, np.uint64)
    for r in range(8):
        own = out[r::8]
        own[:] = whole[r : r + 8 * len(own)].view(">u8" if big else "<u8")
    return out


def least_in(keys: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each `width` successive keys."""
    n = len(keys)
    blocks = np.full(-(-n // width) * width, np.uint64(0xFFFFFFFFFFFFFFFF))
    blocks[:n] = keys
    blocks = blocks.reshape(-1, width)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    back = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(back[: n - width + 1], ahead[width - 1 : n])


def segments(data: np.ndarray, offsets: np.ndarray, span: int) -> dict[str, np.ndarray]:
    """Anchor hash, digests, text number, start in the text and number of windows for each run of windows with one anchor.

    Neighbouring segments of equal content, as in a text of one period, make one row marked `twice`."""
    count = len(data) - span + 1
    names = ("anchor", "d1", "d2", "text", "start", "windows", "size", "twice")
    if count <= 0:
        return {k: np.zeros(0, np.int64) for k in names}
    w = words8(data)
    n = len(data) - GRAM + 1
    h = hash_rows(w[:n] * _MUL[0] + w[8 : n + 8] * _MUL[1] + w[16 : n + 16] * _MUL[2] + w[24 : n + 24] * _MUL[3])
    at = least_in((h & ~_LOW) | np.arange(n, dtype=np.uint64), span - GRAM + 1) & _LOW
    edge = np.zeros(count + 1, np.int64)
    first, last = offsets[:-1], offsets[1:] - span + 1
    long = last > first
    np.add.at(edge, first[long], 1)
    np.add.at(edge, last[long], -1)
    v = np.flatnonzero(np.cumsum(edge[:-1]) > 0)
    if not len(v):
        return {k: np.zeros(0, np.int64) for k in names}
    new = np.ones(len(v), bool)
    new[1:] = (at[v[1:]] != at[v[:-1]]) | (v[1:] != v[:-1] + 1)
    heads = np.zeros(count, bool)
    heads[first[long]] = True
    new |= heads[v]
    run = np.flatnonzero(new)
    windows = np.diff(np.append(run, len(v)))
    lo = v[run]
    size = windows + span - 1
    d1, d2 = digests(data, lo, size).T
    text = np.searchsorted(offsets, lo, side="right") - 1
    same = np.zeros(len(lo), bool)
    same[1:] = (d1[1:] == d1[:-1]) & (d2[1:] == d2[:-1]) & (text[1:] == text[:-1])
    keep = np.flatnonzero(~same)
    twice = np.diff(np.append(keep, len(lo))) > 1
    return {
        "anchor": h[at[lo[keep]].astype(np.int64)].view(np.int64), "d1": d1[keep].astype(np.uint64).view(np.int64), "d2": d2[keep].astype(np.uint64).view(np.int64),
        "text": text[keep], "start": lo[keep] - offsets[text[keep]], "windows": np.add.reduceat(windows, keep), "size": size[keep], "twice": twice,
    }


def suffix_array(data: np.ndarray, ends: np.ndarray | None = None) -> np.ndarray:
    """Positions in the order of their suffixes: groups sorted by 8 bytes, then refined by the rank h places on, h doubling,
    only where groups still hold more than one suffix (Larsson-Sadakane).

    `ends` tells for each place where its string ends (the place of a separator). Strings are then apart: a separator is
    larger than a byte, and of two the first comes first, so that copies of long runs of strings are soon told from each other."""
    n = len(data)
    key = words8(data, 0, big=True)
    if ends is not None:
        ahead = ends - np.arange(n)
        near = np.flatnonzero(ahead < 7)
        key[near] &= ~((np.uint64(1) << (np.uint64(8) * (7 - ahead[near]).astype(np.uint64))) - np.uint64(1))
    sa = np.argsort(key)
    key = key[sa]
    head = np.ones(n, bool)
    head[1:] = key[1:] != key[:-1]
    slot = np.maximum.accumulate(np.where(head, np.arange(n), 0))
    rank = np.empty(n, np.int64)
    rank[sa] = slot + 1
    h = 8
    tail = np.append(head[1:], True)
    open_ = np.flatnonzero(~(head & tail))
    while len(open_) and h < 2 * n:
        pos = sa[open_]
        nxt = pos + h
        second = np.where(nxt < n, rank[np.minimum(nxt, n - 1)], 0)
        if ends is not None:
            second = np.where(nxt > ends[pos], ends[pos], second)
        pair = (rank[pos].astype(np.uint64) << np.uint64(32)) | second.astype(np.uint64)
        order = np.argsort(pair)
        pair, pos = pair[order], pos[order]
        sa[open_] = pos
        head = np.ones(len(open_), bool)
        head[1:] = pair[1:] != pair[:-1]
        lead = np.maximum.accumulate(np.where(head, np.arange(len(open_)), 0))
        rank[pos] = open_[lead] + 1
        tail = np.append(head[1:], True)
        open_ = open_[~(head & tail)]
        h *= 2
    return sa


def common_prefixes(data: np.ndarray, sa: np.ndarray, cap: int, lanes: int = 4096, ends: np.ndarray | None = None) -> np.ndarray:
    """lcp[i]: common prefix of suffixes sa[i - 1] and sa[i], up to `cap` and to the end of the string. Kasai's walk in text order, where each suffix
    starts from its forerunner's length less one, in many lanes of the text at once and eight bytes a step."""
    n = len(data)
    before = np.empty(n, np.int64)
    before[sa[0]] = -1
    before[sa[1:]] = sa[:-1]
    w = words8(data, cap + 16)
    each = -(-n // lanes)
    i = np.arange(0, n, each)
    end = np.minimum(i + each, n)
    length = np.zeros(len(i), np.int64)
    plcp = np.zeros(n, np.int64)
    while len(i):
        j = before[i]
        x = w[i + length] ^ w[np.maximum(j, 0) + length]
        low = x & (np.uint64(0) - x)
        step = np.where(x == 0, 8, np.bitwise_count(low - np.uint64(1)) >> 3).astype(np.int64)
        most = cap if ends is None else np.minimum(cap, ends[i] - i)
        length = np.where(j < 0, 0, np.minimum(length + step, most))
        done = (j < 0) | (x != 0) | (length >= most)
        plcp[i[done]] = length[done]
        i = i + done
        length = np.where(done, np.maximum(length - 1, 0), length)
        on = i < end
        if not on.all():
            i, end, length = i[on], end[on], length[on]
    return plcp[sa]


def repeated(pieces: list[bytes], span: int) -> list[np.ndarray]:
    """For each piece, whether the window from each of its places also starts elsewhere in the pieces."""
    sizes = np.array([len(p) for p in pieces])
    data = np.frombuffer(b"".join(p + b"\xff" for p in pieces), np.uint8)
    at = np.concatenate([[0], np.cumsum(sizes + 1)])
    ends = np.repeat(at[1:] - 1, sizes + 1)
    sa = suffix_array(data, ends)
    far = common_prefixes(data, sa, span, ends=ends) >= span
    mark = np.zeros(len(data), bool)
    mark[sa[far]] = True
    mark[sa[:-1][far[1:]]] = True
    return [mark[a : a + max(0, k - span + 1)] for a, k in zip(at[:-1], sizes)]


def find_segments(docs: DataFrame, span: int) -> DataFrame:
    def run(batches):
        import pyarrow as pa

        for b in batches:
            keys = b.column(0).to_numpy()
            data, offs = text_bytes(b.column(1))
            for i, j in slabs(offs, PART):
                lo, hi = int(offs[i]), int(offs[j])
                for c in range(0, max(1, hi - lo - span + 1), PART) if j == i + 1 else (0,):
                    stop = min(hi, lo + c + PART + span - 1) if j == i + 1 else hi
                    own = offs[i : j + 1] - lo if j > i + 1 else np.array([0, stop - lo - c])
                    s = segments(data[lo + c : stop], own, span)
                    if len(s["start"]):
                        cols = [pa.array(s[k], pa.int64()) for k in ("anchor", "d1", "d2")]
                        cols += [pa.array(keys[i + s["text"]]), pa.array(s["start"] + c), pa.array(s["windows"]), pa.array(s["size"]), pa.array(s["twice"].astype(bool))]
                        yield pa.RecordBatch.from_arrays(cols, names=["anchor", "d1", "d2", "row_key", "start", "windows", "size", "twice"])

    return docs.select("row_key", "text").mapInArrow(
        tidied(run), "anchor long, d1 long, d2 long, row_key long, start long, windows long, size long, twice boolean"
    )


def marks(docs: DataFrame, span: int = 400) -> DataFrame:
    """row_key, start, windows: runs of windows of (row_key, doc_id, text) that also start elsewhere."""
    found = materialise(find_segments(docs, span), "segments")
    content = ["anchor", "d1", "d2"]
    kinds = found.groupBy(*content).agg(
        F.count(F.lit(1)).alias("n"), F.max("twice").alias("twice"), F.min(F.struct("row_key", "start", "size")).alias("one"),
        F.max(F.struct("row_key", "start", "size")).alias("two"),
    ).withColumn("single", (F.col("n") == 1) & ~F.col("twice"))
    kinds = materialise(kinds, "kinds")
    met = kinds.groupBy("anchor").agg(F.count(F.lit(1)).alias("contents"), F.min("single").alias("all_single"))
    met = materialise(met.where("contents > 1 or not all_single"), "met")
    # a text of one period holds the next copy right behind the windows of the one before
    behind = F.when(F.col("n") == 1, F.col("one.size") - span + 1).otherwise(F.lit(0))
    again = F.struct(F.col("two.row_key").alias("row_key"), (F.col("two.start") + behind).alias("start"), F.col("two.size").alias("size"), F.lit(False).alias("told"))
    first = F.struct(F.col("one.row_key").alias("row_key"), F.col("one.start").alias("start"), F.col("one.size").alias("size"), F.lit(True).alias("told"))
    copies = F.explode(F.when(F.col("single"), F.array(first)).otherwise(F.array(first, again)))
    mixed = kinds.join(met.where("contents > 1"), "anchor")
    chosen = materialise(mixed.select(*content, "contents", "single", copies.alias("copy")).select(*content, "contents", "single", "copy.*"), "chosen")
    total = chosen.agg(F.sum("size")).head()[0] or 0
    shards = max(1, -(-total // SHARD_BYTES))
    parts = F.when(F.col("contents") > HOT, F.ceil(F.col("contents") / HOT).cast("int")).otherwise(F.lit(1))
    dealt = chosen.withColumn("hot", F.col("contents") > HOT).withColumn("salt", F.pmod(F.col("d1"), parts))
    dealt = dealt.withColumn("shard", F.pmod(F.xxhash64("anchor", "salt"), F.lit(shards)).cast("int"))
    asked = dealt.groupBy("row_key").agg(F.collect_list(F.struct("shard", "hot", "single", "told", *content, "start", "size")).alias("asked"))
    sent = docs.select("row_key", "text").join(asked, "row_key")

    def cut(batches):
        import pyarrow as pa

        kinds = [("shard", pa.int32()), ("hot", pa.bool_()), ("single", pa.bool_()), ("told", pa.bool_()), *[(c, pa.int64()) for c in content], ("row_key", pa.int64()), ("start", pa.int64()), ("piece", pa.binary())]
        for b in batches:
            rows: list[list] = [[] for _ in kinds]
            for key, t, asked_here in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist()):
                raw = t.encode()
                for a in asked_here:
                    for c, v in zip(rows, (*[a[k] for k, _ in kinds[:7]], key, a["start"], raw[a["start"] : a["start"] + a["size"]])):
                        c.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(r, k) for r, (_, k) in zip(rows, kinds)], names=[k for k, _ in kinds])

    bytes_ = sent.mapInArrow(tidied(cut), "shard int, hot boolean, single boolean, told boolean, anchor long, d1 long, d2 long, row_key long, start long, piece binary")

    hot_windows = chosen.where(F.col("contents") > HOT).agg(F.sum(F.col("size") - span + 1)).head()[0] or 0
    ranges = max(1, -(-hot_windows // 100_000))
    kind = [("d1", "<u8"), ("d2", "<u8"), ("row_key", "<i8"), ("start", "<i8")]

    def sort_shard(table):
        import pyarrow as pa

        pieces = table.column("piece").to_pylist()
        names = ["row_key", "start", "windows", "anchor", "d1", "d2", "part", "run"]
        out: list[list] = [[] for _ in names]
        told = []
        rows = zip(pieces, repeated(pieces, span), *[table.column(c).to_pylist() for c in ("single", "told", "hot", "row_key", "start", *content)])
        for piece, mark, single, speaks, hot, key, start, *own in rows:
            if speaks and mark.any():
                edge = np.diff(np.concatenate([[0], mark.view(np.int8), [0]]))
                lo, hi = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
                n = len(lo)
                # a content met once tells its own place, any other the place inside each copy
                place = ([key] * n, lo + start, hi - lo, [None] * n, [None] * n, [None] * n) if single else ([-1] * n, lo, hi - lo, *[[c] * n for c in own])
                for c, v in zip(out, (*place, [0] * n, [None] * n)):
                    c.extend(v)
            if hot and speaks:
                own = np.empty(len(mark), kind)
                at = np.arange(len(mark))
                own["d1"], own["d2"] = digests(np.frombuffer(piece, np.uint8), at, np.full(len(at), span)).T
                # a window that needs no mark (any more) is told without its place
                own["row_key"], own["start"] = np.where(single & ~mark, key, -1), np.where(single & ~mark, at + start, -1)
                told.append(own)
        if told:
            run = np.unique(np.concatenate(told))
            part = ((run["d1"] >> np.uint64(32)) * np.uint64(ranges)) >> np.uint64(32)
            for r in np.unique(part).tolist():
                for c, v in zip(out, (-1, -1, 0, None, None, None, r, run[part == r].tobytes())):
                    c.append(v)
        kinds = [pa.int64()] * 7 + [pa.binary()]
        return pa.Table.from_arrays([pa.array(c, t) for c, t in zip(out, kinds)], names=names)

    schema = "row_key long, start long, windows long, anchor long, d1 long, d2 long, part long, run binary"
    sorted_ = materialise(bytes_.groupBy("shard").applyInArrow(sort_shard, schema), "shards")

    def merge(table):
        import pyarrow as pa

        runs_ = [np.frombuffer(r, kind) for r in table.column("run").to_pylist()]
        d1, d2 = (np.concatenate([r[c] for r in runs_]) for c in ("d1", "d2"))
        order = np.lexsort((d2, d1))
        d1, d2 = d1[order], d2[order]
        # a shard tells a digest once, so equal neighbours come from two shards
        same = (d1[1:] == d1[:-1]) & (d2[1:] == d2[:-1])
        across_ = np.append(same, False) | np.append(False, same)
        hit = []
        for own in runs_:
            own = own[own["row_key"] >= 0]
            at = np.searchsorted(d1, own["d1"])
            while (off := d2[at] != own["d2"]).any():
                at = at + off
            hit.append(own[across_[at]])
        found = np.concatenate(hit)
        return pa.Table.from_arrays([pa.array(found["row_key"].copy()), pa.array(found["start"].copy()), pa.array(np.ones(len(found), np.int64))], names=["row_key", "start", "windows"])

    across = sorted_.where("windows = 0").select("part", "run").groupBy("part").applyInArrow(merge, "row_key long, start long, windows long")
    spoken = sorted_.where("windows > 0")
    shared = spoken.where("anchor is not null").select(*content, F.col("start").alias("place"), F.col("windows").alias("run_"))
    handed = found.join(shared, content).select("row_key", (F.col("start") + F.col("place")).alias("start"), F.when(F.col("twice"), F.col("windows")).otherwise(F.col("run_")).alias("windows"))
    same = found.join(met.where("contents = 1").select("anchor"), "anchor", "left_semi").select("row_key", "start", "windows")
    every = materialise(handed.unionByName(same).unionByName(spoken.where("anchor is null").select("row_key", "start", "windows")).unionByName(across), "marks")
    discard(found, kinds, met, chosen, sorted_)
    return every


def remove_repeats(docs: DataFrame, span: int = 400, doc_id: str = "doc_id", text: str = "text", with_text: bool = False) -> DataFrame:
    """row_key, doc_id, n_bytes, n_removed, n_spans, kept_sha256 and, if asked for, the removed spans [from, to) in bytes of
    the original and the bytes kept."""
    docs = placed(docs, doc_id, text)
    per = marks(docs, span).groupBy("row_key").agg(F.collect_list(F.struct("start", "windows")).alias("marks"))
    whole = docs.join(per, "row_key", "left")

    def cut(batches):
        import hashlib

        import pyarrow as pa

        names = ["row_key", "doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"]
        for b in batches:
            rows: list[list] = [[], [], [], []]
            spans, kept = [], []
            for t, m in zip(b.column(2).to_pylist(), b.column(3)):
                raw, gone = t.encode(), []
                if m.is_valid:
                    s = m.values.field("start").to_numpy()
                    e = s + m.values.field("windows").to_numpy() + span - 1
                    order = np.argsort(s)
                    s, e = s[order], np.maximum.accumulate(e[order])
                    head = np.flatnonzero(np.append(True, s[1:] > e[:-1]))
                    gone = list(zip(s[head].tolist(), e[np.append(head[1:] - 1, len(e) - 1)].tolist()))
                rest, at = [], 0
                for i, j in gone:
                    rest.append(raw[at:i])
                    at = j
                left = b"".join([*rest, raw[at:]])
                for c, v in zip(rows, (len(raw), len(raw) - len(left), len(gone), hashlib.sha256(left).hexdigest())):
                    c.append(v)
                spans.append([{"start": i, "stop": j} for i, j in gone])
                kept.append(left)
            cols = [b.column(0), b.column(1), *[pa.array(c, pa.int64()) for c in rows[:3]], pa.array(rows[3], pa.string())]
            if with_text:
                cols += [pa.array(spans, pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))), pa.array(kept, pa.binary())]
            yield pa.RecordBatch.from_arrays(cols, names=names + ["spans", "kept"] * with_text)

    schema = "row_key long, doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"
    return whole.mapInArrow(tidied(cut), schema + ", spans array<struct<start:long,stop:long>>, kept binary" * with_text)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return remove_repeats(docs).drop("row_key")
