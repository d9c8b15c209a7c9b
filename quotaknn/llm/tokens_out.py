"""Token ids as directly addressable codes.

A block splits its ids into one-byte chunks, least significant first. Level 0 holds the first chunk of every id and a
bitmap of those that go on; level 1 holds the next chunk of just those, and so on. A rank directory (ones before every 512th
bit) turns an id's place in one level into its place in the next, so any id is read by a few direct accesses, with no
decoding of the block. Blocks lie in shards: ascending runs of the order by doc_id, each written by one task.

Block layout, little-endian: magic DAC1, uint32 levels, uint64 ids; then for each level uint64 entries, the chunk bytes,
and but for the last level the bitmap bytes (bit i of byte j for entry 8 j + i) and the uint32 rank directory.

Defined cases: null text is empty and has just the end id; null doc_ids come first; rows with the same doc_id lie in the
order of the source; an empty table gives no blocks; a document is never split over blocks, however long, so a block holds at
most `block_tokens` ids and one document more; other columns are not read, so names that clash do no harm.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from quotaknn.llm.common import encoder, keyed, scratch, tokenizer_path

EVERY = 512
BLOCKS = "shard int, block int, start_in_shard long, n_tokens long, doc_ids array<long>, lengths array<long>, codes binary"


def encode(ids: np.ndarray) -> bytes:
    rest, levels = np.ascontiguousarray(ids, "<u4"), []
    while True:
        more = rest > 255
        levels.append(((rest & 255).astype(np.uint8), more))
        if not more.any():
            break
        rest = rest[more] >> 8
    out = [b"DAC1", struct.pack("<IQ", len(levels), len(ids))]
    for k, (chunk, more) in enumerate(levels):
        out += [struct.pack("<Q", len(chunk)), chunk.tobytes()]
        if k < len(levels) - 1:
            bits = np.packbits(more, bitorder="little")
            ones = np.concatenate([[0], np.cumsum(np.bitwise_count(bits), dtype=np.int64)])
            out += [bits.tobytes(), ones[: -1 : EVERY // 8].astype("<u4").tobytes()]
    return b"".join(out)


class Codes:
    """Random access to a block: codes[i] and codes.all()."""

    def __init__(self, data: bytes):
        if data[:4] != b"DAC1":
            raise ValueError("not a block of directly addressable codes")
        n_levels, self.n = struct.unpack_from("<IQ", data, 4)
        at, self.levels = 16, []
        for k in range(n_levels):
            (n,) = struct.unpack_from("<Q", data, at)
            at += 8
            chunk = np.frombuffer(data, np.uint8, n, at)
            at += n
            bits = ranks = None
            if k < n_levels - 1:
                bits = np.frombuffer(data, np.uint8, (n + 7) // 8, at)
                at += len(bits)
                ranks = np.frombuffer(data, "<u4", -(-len(bits) // (EVERY // 8)), at)
                at += ranks.nbytes
            self.levels.append((chunk, bits, ranks))

    def __len__(self) -> int:
        return self.n

    def __getitem__(self, i: int) -> int:
        if not 0 <= i < self.n:
            raise IndexError(i)
        value = 0
        for k, (chunk, bits, ranks) in enumerate(self.levels):
            value |= int(chunk[i]) << (8 * k)
            if bits is None or not bits[i >> 3] >> (i & 7) & 1:
                break
            first = i // EVERY * (EVERY // 8)
            before = int(np.bitwise_count(bits[first : i >> 3]).sum()) + int(bits[i >> 3] & ((1 << (i & 7)) - 1)).bit_count()
            i = int(ranks[i // EVERY]) + before
        return value

    def all(self) -> np.ndarray:
        values = None
        for chunk, bits, _ in reversed(self.levels):
            own = chunk.astype("<u4")
            if values is not None:
                own[np.unpackbits(bits, bitorder="little", count=len(chunk)).astype(bool)] |= values << np.uint32(8)
            values = own
        return values if values is not None else np.zeros(0, "<u4")


def write(docs: DataFrame, path: str, tokenizer: str, end_id: int = 0, doc_id: str = "doc_id", text: str = "text",
          block_tokens: int = 1 << 19) -> None:
    """Encodes `docs` in ascending doc_id order into blocks of about `block_tokens` ids at `path`."""
    rows = keyed(docs, doc_id, text).select(F.col("doc_id").cast("long").alias("doc_id"), "row_key", "text")
    ordered = rows.repartitionByRange("doc_id", "row_key").sortWithinPartitions("doc_id", "row_key")

    def blocks(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        run, shard = encoder(tokenizer, end_id), TaskContext.get().partitionId()
        kind = pa.schema([("shard", pa.int32()), ("block", pa.int32()), ("start_in_shard", pa.int64()), ("n_tokens", pa.int64()), ("doc_ids", pa.list_(pa.int64())), ("lengths", pa.list_(pa.int64())), ("codes", pa.binary())])
        ids, parts, held, block, start = [], [], 0, 0, 0

        def close():
            nonlocal ids, parts, held, block, start
            whole = np.concatenate(parts)
            row = {"shard": shard, "block": block, "start_in_shard": start, "n_tokens": len(whole), "doc_ids": ids, "lengths": [len(p) for p in parts], "codes": encode(whole)}
            ids, parts, held, block, start = [], [], 0, block + 1, start + len(whole)
            return pa.RecordBatch.from_pylist([row], schema=kind)

        for b in batches:
            for k, own in zip(b.column(0).to_pylist(), run(b.column(2))):
                ids.append(k)
                parts.append(own)
                held += len(own)
                if held >= block_tokens:
                    yield close()
        if parts:
            yield close()

    ordered.mapInArrow(blocks, BLOCKS).write.option("compression", "none").parquet(path)


def read(spark: SparkSession, path: str) -> DataFrame:
    """The blocks, with the number of ids before each. One count for each shard reaches the driver."""
    rows = spark.read.schema(BLOCKS).parquet(path)
    base, total = [], 0
    for r in sorted(rows.groupBy("shard").agg(F.sum("n_tokens").alias("n")).collect(), key=lambda r: r["shard"]):
        base.append((r["shard"], total))
        total += r["n"]
    starts = spark.createDataFrame(base, "shard int, shard_start long")
    return rows.join(F.broadcast(starts), "shard").withColumn("start", F.col("shard_start") + F.col("start_in_shard"))


def token_at(spark: SparkSession, path: str, position: int) -> int:
    """The id at a place of the whole sequence; only its own block is read."""
    block = read(spark, path).where((F.col("start") <= position) & (F.col("start") + F.col("n_tokens") > position)).select("start", "codes").head()
    if block is None:
        raise IndexError(position)
    return Codes(bytes(block["codes"]))[position - block["start"]]


def documents(spark: SparkSession, path: str, with_ids: bool = False) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 (and ids) of each document, decoded from the files."""

    def decode(batches):
        import pyarrow as pa

        for b in batches:
            for start, keys, lengths, codes in zip(*[b.column(i).to_pylist() for i in range(4)]):
                ids = Codes(codes).all()
                ends = np.cumsum(np.array(lengths, np.int64))
                cut = np.concatenate([[0], ends])
                own = [ids[i:j] for i, j in zip(cut[:-1], cut[1:])]
                arrays = [pa.array(keys, pa.int64()), pa.array(cut[:-1] + start), pa.array(np.diff(cut)), pa.array([zlib.crc32(x.tobytes()) for x in own], pa.int64())]
                names = ["doc_id", "start", "n_tokens", "ids_crc32"]
                if with_ids:
                    arrays, names = [*arrays, pa.array([x.tolist() for x in own], pa.list_(pa.int64()))], [*names, "ids"]
                yield pa.RecordBatch.from_arrays(arrays, names=names)

    schema = "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids array<long>" * with_ids
    return read(spark, path).select("start", "doc_ids", "lengths", "codes").mapInArrow(decode, schema)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = scratch(spark, "tokens")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    write(docs, path, tokenizer_path("byte_bpe_50k.json"), 0)
    return documents(spark, path)
