"""Shared helpers: durable scratch tables, fresh column names, row keys and byte-level hashing."""

from __future__ import annotations

import tempfile
import uuid
from contextlib import contextmanager

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

MIX = np.uint64(0x9E3779B97F4A7C15)
#: Bits of a row's number for its place in the file, and the most files whose numbers are broadcast.
PLACE_BITS, MOST_FILES = 36, 100_000


def scratch(spark: SparkSession, name: str) -> str:
    """A new path in the folder that driver and executors share (`spark.checkpoint.dir`).

    Only where that setting is missing on one machine, as in tests, a local temporary folder takes its place.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        base = "file://" + tempfile.mkdtemp(prefix="quotaknn-")
        spark.conf.set("spark.checkpoint.dir", base)
    path = f"{base.rstrip('/')}/llm/{name}-{uuid.uuid4().hex}"
    if _open:
        _open[-1].append(path)
    return path


_open: list[list[str]] = []


@contextmanager
def passing(spark: SparkSession):
    """Scratch tables made inside go at the end: whatever is to stay must be written to a path from outside."""
    _open.append([])
    try:
        yield
    finally:
        for path in _open.pop():
            remove(spark, path)


def remove(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write to the shared folder and read again: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = scratch(spark, name)
    df.write.parquet(path)
    table = spark.read.schema(df.schema).parquet(path)
    table.scratch_path = path
    return table


def discard(*tables: DataFrame) -> None:
    """Delete materialised tables that no plan to come reads."""
    for t in tables:
        remove(t.sparkSession, t.scratch_path)


def fresh(df: DataFrame, base: str) -> str:
    """A column name that `df` does not have (case ignored, as Spark resolves names)."""
    taken = {c.lower() for c in df.columns}
    name = base
    while name.lower() in taken:
        name = "_" + name
    return name


def release() -> None:
    """Give memory that a worker has freed back to the machine, as idle workers stay beside later stages."""
    import ctypes
    import gc

    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        pass  # another C library: nothing to give back by this call


def tidied(run):
    """`run`, a generator over Arrow batches, with release() at the end of each task."""

    def both(batches):
        yield from run(batches)
        release()

    return both


def forget() -> None:
    """Free the tokenizer tables that earlier tasks left in this worker."""
    import sys

    if sys.__dict__.pop("_quotaknn_encoders", None):
        _powers.clear()
        release()


def lean(run):
    """tidied() for a step that does not tokenise: tables kept for steps that do are freed before it starts."""

    def both(batches):
        forget()
        yield from tidied(run)(batches)

    return both


def col(name: str) -> Column:
    return F.col(f"`{name}`")


def keyed(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", *more: str) -> DataFrame:
    """(row_key, doc_id, text, ...): null text is empty; row_key tells repeated rows apart.

    The key is a position in this one reading of `docs`: another reading may deal the files otherwise. What reads texts
    more than once takes placed().
    """
    picked = docs.select(
        col(doc_id).alias("doc_id"), F.coalesce(col(text), F.lit("")).alias("text"), *[col(c).alias(c) for c in more]
    )
    return picked.withColumn("row_key", F.monotonically_increasing_id())


def is_scan(docs: DataFrame) -> bool:
    """Whether each row of `docs` is one row of a Parquet file, so that it has a place there."""
    plan = docs._jdf.queryExecution().analyzed()
    if not plan.deterministic():
        return False
    while plan.children().size() == 1 and plan.nodeName() in ("Project", "Filter", "SubqueryAlias"):
        plan = plan.children().head()
    return plan.children().size() == 0 and "parquet" in plan.toString().lower() and "Relation" in plan.getClass().getSimpleName()


def settled(docs: DataFrame) -> DataFrame:
    """`docs`, written first if it is no scan: its rows have places that stay."""
    return docs if is_scan(docs) else materialise(docs, "docs")


def located(docs: DataFrame) -> tuple[DataFrame, str, str]:
    """`docs` with the columns file and row at the end (by names it does not have); written first, if it is no scan."""
    docs = settled(docs)
    file, row = fresh(docs, "file"), fresh(docs, "row")
    meta = docs.metadataColumn("_metadata")
    return docs.select("*", meta["file_path"].alias(file), meta["row_index"].alias(row)), file, row


def with_place(docs: DataFrame, name: str) -> DataFrame:
    """`docs` with a last column `name`, a number of its own for each row: the number of its file in the order of paths, then
    its place in the file. Readings agree on it however many executors there are and however the files are dealt to them.

    The paths reach the driver, which lists them for each scan anyway; up to `MOST_FILES` are broadcast."""
    own, file, row = located(docs)
    paths = sorted(r[0] for r in own.select(col(file)).distinct().collect())
    number = fresh(own, "number")
    kind = T.StructType([T.StructField(file, T.StringType()), T.StructField(number, T.LongType())])
    table = docs.sparkSession.createDataFrame(list(zip(paths, range(len(paths)))), kind)
    joined = own.join(F.broadcast(table) if len(paths) <= MOST_FILES else table, file)
    return joined.select(*[col(c) for c in docs.columns], F.shiftleft(col(number), PLACE_BITS).bitwiseOR(col(row)).alias(name))


def placed(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(row_key, doc_id, text): null text is empty; row_key tells repeated rows apart, alike in every reading."""
    rows = with_place(docs.select(col(doc_id).alias("doc_id"), col(text).alias("text")), "row_key")
    return rows.select("row_key", F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))


def hash_rows(values: np.ndarray) -> np.ndarray:
    """Mixes uint64 values (a splitmix finaliser), wrapping silently."""
    x = values.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def text_bytes(column) -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes of an Arrow string array, end to end, and the n + 1 offsets (nulls are empty)."""
    import pyarrow as pa
    import pyarrow.compute as pc

    arr = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    arr = pc.fill_null(arr, "").cast(pa.large_string())
    offs = np.frombuffer(arr.buffers()[1], dtype=np.int64)[arr.offset : arr.offset + len(arr) + 1]
    if not len(arr):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    data = arr.buffers()[2]
    whole = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)
    return whole[offs[0] : offs[-1]], offs - offs[0]


def slabs(offsets: np.ndarray, limit: int):
    """Runs [i, j) of rows with at most `limit` bytes in all, one row at least: bounds working memory."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + limit, side="right")) - 1)
        yield i, j
        i = j


def numbered(rows: DataFrame, group: str, order: list[str], name: str) -> DataFrame:
    """Adds `name`, gapless from 0 within each value of the integer column `group` (no nulls), in the given order.

    Range partitions in the order (group, *order) are numbered from their own starts, then moved by the count of that
    group's rows in the partitions before. Only those counts, one for each partition and group in it, reach the driver,
    and no task holds more than its range, however large one group is.
    """
    cols = rows.columns
    ranged = rows.repartitionByRange(*[F.col(c) for c in [group, *order]]).sortWithinPartitions(group, *order)

    def number(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        part, last, seen = TaskContext.get().partitionId(), None, 0
        for b in batches:
            g = b.column(b.schema.get_field_index(group)).to_numpy(zero_copy_only=False)
            if not len(g):
                continue
            starts = np.flatnonzero(np.diff(g, prepend=g[0] - 1))
            at = np.arange(len(g)) - np.repeat(starts, np.diff(np.append(starts, len(g))))
            if g[0] == last:
                head = starts[1] if len(starts) > 1 else len(g)
                at[:head] += seen
            last, seen = g[-1], int(at[-1]) + 1
            yield pa.RecordBatch.from_arrays(
                [*b.columns, pa.array(np.full(len(g), part, np.int32)), pa.array(at.astype(np.int64))],
                names=[*cols, "part_", "local_"],
            )

    schema = T.StructType([*ranged.schema.fields, T.StructField("part_", T.IntegerType()), T.StructField("local_", T.LongType())])
    done = materialise(ranged.mapInArrow(number, schema), "numbered")
    base, total = [], {}
    for r in sorted(done.groupBy("part_", group).count().collect(), key=lambda r: (r[group], r["part_"])):
        base.append((r["part_"], r[group], total.get(r[group], 0)))
        total[r[group]] = total.get(r[group], 0) + r["count"]
    kind = rows.schema[group].dataType
    starts = done.sparkSession.createDataFrame(
        base, T.StructType([T.StructField("part_", T.IntegerType()), T.StructField(group, kind), T.StructField("start_", T.LongType())])
    )
    joined = done.join(F.broadcast(starts), ["part_", group])
    return joined.withColumn(name, F.col("start_") + F.col("local_")).select(*cols, name)


def tokenizer_path(name: str) -> str:
    """Where a public vocabulary file lies; pass a path of your own to the operators to use another."""
    import public_tokenizers

    return public_tokenizers.path(name)


def encoder(path: str, end_id: int, at_once: int = 1 << 20):
    """Arrow array of texts -> iterator of little-endian uint32 id arrays, `end_id` appended to each.

    Where the vocabulary file says that no token crosses from text into a following blank, texts are cut before runs of
    blanks and the ids of a piece are kept for its next occurrence (in a table of bounded size, emptied when full). A piece
    is found by its hashes and then compared byte by byte; a text with a piece whose place in the table another piece of
    equal hashes holds goes whole to the library, as do other tokenizers and texts with blanks outside ASCII.
    """
    import os
    import sys

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    known = sys.__dict__.setdefault("_quotaknn_encoders", {})  # outlives a task where workers are used again
    if path not in known:
        known[path] = Pieces(path)
    pieces = known[path]

    def run(column):
        data, offs = text_bytes(column)
        for i, j in slabs(offs, at_once):
            yield from pieces.encode(data[offs[i] : offs[j]], offs[i : j + 1] - offs[i], end_id)

    return run


BLANK = np.zeros(256, bool)
BLANK[[9, 10, 11, 12, 13, 32]] = True
_RARE = np.zeros(256, bool)
_RARE[[0x1C, 0x1D, 0x1E, 0x1F, 0xC2, 0xE1, 0xE2, 0xE3]] = True
ODD_BLANK = "[\x1c-\x1f\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]"
#: The splitting pattern of the lower-casing vocabulary file.
WORDS_ONLY = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"


def grown(own: np.ndarray, least: int) -> np.ndarray:
    """`own` with room for `least` values, a quarter more than it had or what is asked for."""
    return own if least <= len(own) else np.concatenate([own, np.zeros(max(least - len(own), len(own) >> 2), own.dtype)])


class Pieces:
    #: Numbers and places are kept in 32 bits; a part of a text (1 MB) at most comes on top of MOST_BYTES.
    SLOTS, MOST, MOST_BYTES = 1 << 21, 1_200_000, 48 << 20

    def __init__(self, path: str):
        import json

        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        pre, norm = spec.get("pre_tokenizer") or {}, spec.get("normalizer")
        steps = pre.get("pretokenizers", [])
        self.mode = "whole"
        if pre.get("type") == "ByteLevel" and pre.get("use_regex") and not pre.get("add_prefix_space") and norm is None:
            self.mode, mark = "blanks kept", " 7"
        elif steps and steps[0].get("pattern", {}).get("Regex") == WORDS_ONLY and steps[0].get("behavior") == "Removed" and steps[0].get("invert"):
            self.mode, mark = "blanks dropped", " 7 "
        if self.mode != "whole":
            ids = self.tok.encode(mark, add_special_tokens=False).ids
            self.mark, self.mark_id = mark, ids[0]
            if len(ids) != 1:
                self.mode = "whole"
        self.empty()

    def empty(self) -> None:
        self.k1, self.k2 = np.zeros(self.SLOTS, np.uint64), np.zeros(self.SLOTS, np.uint64)
        self.at = np.full(self.SLOTS, -1, np.int32)
        self.begin, self.size, self.n = np.zeros(1 << 16, np.int32), np.zeros(1 << 16, np.int32), 0
        self.flat, self.used = np.zeros(1 << 18, "<u4"), 0
        self.text_at, self.text_size = np.zeros(1 << 16, np.int32), np.zeros(1 << 16, np.int32)
        self.text, self.held = np.zeros(1 << 20, np.uint8), 0

    def whole(self, texts: list[str]) -> list[np.ndarray]:
        out, i = [], 0
        while i < len(texts):
            j, size = i, 0
            while j < len(texts) and (j == i or size < 128 << 10):
                size += len(texts[j])
                j += 1
            out += [np.array(e.ids, "<u4") for e in self.tok.encode_batch_fast(texts[i:j], add_special_tokens=False)]
            i = j
        return out

    def find(self, h1: np.ndarray, h2: np.ndarray) -> np.ndarray:
        """Number of each piece, -1 where it is new."""
        out = np.full(len(h1), -1, np.int64)
        slot = (h1 & np.uint64(self.SLOTS - 1)).astype(np.int64)
        todo = np.arange(len(h1))
        while len(todo):
            s = slot[todo]
            a = self.at[s]
            hit = (a >= 0) & (self.k1[s] == h1[todo]) & (self.k2[s] == h2[todo])
            out[todo[hit]] = a[hit]
            on = (a >= 0) & ~hit
            todo = todo[on]
            slot[todo] = (slot[todo] + 1) & (self.SLOTS - 1)
        return out

    def differs(self, data: np.ndarray, lo: np.ndarray, size: np.ndarray, number: np.ndarray) -> np.ndarray:
        """Whether the bytes of each piece are others than those kept under its number."""
        out = self.text_size[number] != size
        same = np.flatnonzero(~out & (size > 0))
        if len(same):
            length = size[same]
            head = np.cumsum(length) - length
            inside = np.arange(int(length.sum())) - np.repeat(head, length)
            odd = data[np.repeat(lo[same], length) + inside] != self.text[np.repeat(self.text_at[number[same]], length) + inside]
            out[same] = np.logical_or.reduceat(odd, head)
        return out

    def add(self, h1: np.ndarray, h2: np.ndarray, ids: list[np.ndarray], texts: list[bytes]) -> None:
        """Distinct new pieces with their ids and bytes."""
        m = len(ids)
        size, length = np.array([len(x) for x in ids], np.int64), np.array([len(x) for x in texts], np.int64)
        total, long_ = int(size.sum()), int(length.sum())
        for name in ("begin", "size", "text_at", "text_size"):
            setattr(self, name, grown(getattr(self, name), self.n + m))
        self.text, self.flat = grown(self.text, self.held + long_), grown(self.flat, self.used + total)
        self.text[self.held : self.held + long_] = np.frombuffer(b"".join(texts), np.uint8)
        self.text_at[self.n : self.n + m] = self.held + np.cumsum(length) - length
        self.text_size[self.n : self.n + m] = length
        self.held += long_
        self.begin[self.n : self.n + m] = self.used + np.cumsum(size) - size
        self.size[self.n : self.n + m] = size
        self.flat[self.used : self.used + total] = np.concatenate(ids) if m else []
        number = np.arange(self.n, self.n + m, dtype=np.int32)
        self.n, self.used = self.n + m, self.used + total
        slot = (h1 & np.uint64(self.SLOTS - 1)).astype(np.int64)
        todo = np.arange(m)
        while len(todo):
            s = slot[todo]
            free = self.at[s] < 0
            _, first = np.unique(s[free], return_index=True)
            won = todo[free][first]
            w = slot[won]
            self.at[w], self.k1[w], self.k2[w] = number[won], h1[won], h2[won]
            placed = np.zeros(m, bool)
            placed[won] = True
            todo = todo[~placed[todo]]
            slot[todo] = (slot[todo] + 1) & (self.SLOTS - 1)

    def look_up(self, texts: list[str]) -> list[np.ndarray]:
        """The ids of new pieces, most of them in one call with a word of one token between each two."""
        plain = [i for i, t in enumerate(texts) if "7" not in t and t[-1:] not in " \t\n\r\v\f" and (self.mode == "blanks dropped" or t[:1] in " \t\n\r\v\f")]
        out: list = [None] * len(texts)
        for a in range(0, len(plain), 2000):
            own = plain[a : a + 2000]
            ids = np.array(self.tok.encode_batch_fast([self.mark.join(texts[i] for i in own)], add_special_tokens=False)[0].ids, "<u4")
            cut = np.flatnonzero(ids == self.mark_id)
            if len(cut) == len(own) - 1:
                for i, x, y in zip(own, np.append(0, cut + 1).tolist(), np.append(cut, len(ids)).tolist()):
                    out[i] = ids[x:y]
        rest = [i for i, x in enumerate(out) if x is None]
        for i, x in zip(rest, self.whole([texts[i] for i in rest])):
            out[i] = x
        return out

    def known(self, data: np.ndarray, lo: np.ndarray, hi: np.ndarray, raw) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids of successive pieces, how many each has, and which pieces the table cannot tell (their ids are not right)."""
        if not len(lo):
            return np.zeros(0, "<u4"), np.zeros(0, np.int64), np.zeros(0, np.int64)
        first, last = int(lo[0]), int(hi[-1])
        h1, h2 = slice_hashes(data[first:last], lo - first, hi - lo)
        number = self.find(h1, h2)
        new = np.flatnonzero(number < 0)
        if len(new):
            if self.n + len(new) > self.MOST or self.held + int((hi - lo)[new].sum()) > self.MOST_BYTES:
                self.empty()
                new = np.arange(len(lo))
            _, once = np.unique(h1[new] ^ (h2[new] << np.uint64(1)), return_index=True)
            own = new[once]
            texts = [raw(i, j) for i, j in zip(lo[own].tolist(), hi[own].tolist())]
            self.add(h1[own], h2[own], self.look_up(texts), [t.encode() for t in texts])
            number[new] = self.find(h1[new], h2[new])
        # -1: the hashes of another piece agree in the one word that tells new pieces apart
        wrong = (number < 0) | self.differs(data, lo, hi - lo, np.maximum(number, 0))
        number[wrong] = 0
        size = self.size[number]
        ends = np.cumsum(size)
        ids = self.flat[np.repeat(self.begin[number] - (ends - size), size) + np.arange(int(ends[-1]))]
        return ids, size, np.flatnonzero(wrong)

    def encode(self, data: np.ndarray, offs: np.ndarray, end_id: int):
        n = len(offs) - 1
        raw = lambda i, j: data[i:j].tobytes().decode()
        end = np.array([end_id], "<u4")
        if self.mode == "whole" or not len(data):
            for ids in self.whole([raw(i, j) for i, j in zip(offs[:-1], offs[1:])]):
                yield np.append(ids, end)
            return
        odd: dict = {}
        if self.mode == "blanks kept":
            import regex

            maybe = np.unique(np.searchsorted(offs, np.flatnonzero(_RARE[data]), side="right") - 1)
            rare = [d for d in maybe.tolist() if regex.search(ODD_BLANK, raw(offs[d], offs[d + 1]))]
            odd = dict(zip(rare, self.whole([raw(offs[d], offs[d + 1]) for d in rare])))
        blank = BLANK[data]
        turn = np.empty(len(data), bool)
        turn[0] = True
        if self.mode == "blanks kept":
            turn[1:] = blank[1:] & ~blank[:-1]
            turn[offs[:-1][offs[:-1] < len(data)]] = True
            lo = np.flatnonzero(turn)
            hi = np.append(lo[1:], len(data))
        else:
            turn[0] = not blank[0]
            turn[1:] = ~blank[1:] & blank[:-1]
            heads = offs[:-1][offs[:-1] < len(data)]
            turn[heads] = ~blank[heads]
            lo = np.flatnonzero(turn)
            stop = np.ones(len(data) + 1, bool)
            stop[:-1] = blank
            stop[offs] = True
            ends = np.flatnonzero(stop)
            hi = ends[np.searchsorted(ends, lo, side="right")]
        parts, sizes, wrong = [], [], []
        for i, j in slabs(np.append(lo, len(data)), 1 << 20):  # a long text goes through the table in parts
            own, size, odd_here = self.known(data, lo[i:j], hi[i:j], raw)
            parts.append(own)
            sizes.append(size)
            wrong.append(i + odd_here)
        wrong = np.concatenate(wrong) if wrong else np.zeros(0, np.int64)
        if len(wrong):
            clash = [d for d in np.unique(np.searchsorted(offs, lo[wrong], side="right") - 1).tolist() if d not in odd]
            odd |= dict(zip(clash, self.whole([raw(offs[d], offs[d + 1]) for d in clash])))
        ids = np.concatenate(parts) if parts else np.zeros(0, "<u4")
        ends = np.cumsum(np.concatenate(sizes)) if sizes else np.zeros(0, np.int64)
        bounds = np.concatenate([[0], ends])[np.searchsorted(lo, offs)]
        for d in range(n):
            yield np.concatenate([odd[d] if d in odd else ids[bounds[d] : bounds[d + 1]], end])


_BYTES = [hash_rows(np.arange(1, 257, dtype=np.uint64) * np.uint64(k)) for k in (3, 5)]
_STEPS = [0xD1342543DE82EF95, 0xA3B195354A39B70D]
_LENGTH = [np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)]
_powers: dict = {}


def slice_hashes(data: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> list[np.ndarray]:
    """Two 64-bit hashes of each slice of the bytes, from prefix sums. Long slices may collide by their making (strings whose
    halves mirror each other), so they only find what is then compared."""
    out = []
    for k in (0, 1):
        if k not in _powers or len(_powers[k][0]) < len(data) + 1:
            size = max(len(data) + 1, (1 << 20) + 4096)
            _powers[k] = tuple(np.cumprod(np.full(size, s, np.uint64)) for s in (_STEPS[k], pow(_STEPS[k], -1, 1 << 64)))
        up, down = _powers[k]
        sums = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(_BYTES[k][data] * up[: len(data)], out=sums[1:])
        out.append(hash_rows((sums[starts + lengths] - sums[starts]) * down[starts] + lengths.astype(np.uint64) * _LENGTH[k]))
    return out


def components(edges: DataFrame) -> DataFrame:
    """(node, root) of every node in `edges` (u, v), root the least node reachable.

    Alternating star contractions, each two joins on narrow rows, until nothing changes; only a count and a checksum of
    each round reach the driver. A node with very many links is pre-aggregated (minimum) and its join may be split.
    """
    spark = edges.sparkSession

    def stamp(df: DataFrame):
        return tuple(df.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v") % (1 << 31))).head())

    def star(e: DataFrame, large: bool) -> DataFrame:
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v"))) if large else e.select(
            F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")
        )
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        moved = both.join(least, "u")
        moved = moved.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")) if large else moved.select(
            F.col("v").alias("u"), F.col("m").alias("v")
        ).unionByName(least.select("u", F.col("m").alias("v")))
        return moved.where("u <> v").distinct()

    now = materialise(edges.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v")).where("u <> v").distinct(), "links")
    mark = stamp(now)
    while mark[0]:
        last, now = now, materialise(star(star(now, True), False), "links")
        discard(last)
        new = stamp(now)
        if new == mark:
            break
        mark = new
    pairs = now.select(F.greatest("u", "v").alias("node"), F.least("u", "v").alias("root"))
    return pairs.unionByName(pairs.select(F.col("root").alias("node"), "root")).groupBy("node").agg(F.min("root").alias("root"))
