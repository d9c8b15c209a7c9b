"""Sharding by a hierarchical weighted hash tree.

A row descends region, rack and shard; at each level every child draws -ln(u) / weight, with u from a hash of the row's
key and the child's name, and the least draw wins. A child's draws depend on its own name and weight alone, so a changed
weight moves rows only into or out of the subtrees whose weights changed. A tree grows by one shard as a region of its own:
then no other subtree's weight changes and rows move only into the new shard (law `key`).

Defined cases: a null key is a key of its own; null text has size 1 and the checksum of no bytes; repeated rows go to the
same shard and have slots of their own; rows of equal texts lie side by side within a shard; texts of any length are read
whole; an empty table gives no rows; other columns are not read, so names that clash do no harm.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from quotaknn.llm.common import keyed, numbered


@dataclass(frozen=True)
class Tree:
    """Weights of shards, as regions of racks of shards: {region: {rack: {shard number: weight}}}."""

    regions: dict

    @classmethod
    def balanced(cls, shards: int, per_rack: int = 4, racks_per_region: int = 2) -> "Tree":
        out: dict = {}
        for s in range(shards):
            rack = s // per_rack
            out.setdefault(f"g{rack // racks_per_region}", {}).setdefault(f"r{rack}", {})[s] = 1.0
        return cls(out)

    def shards(self) -> list[int]:
        return sorted(s for racks in self.regions.values() for own in racks.values() for s in own)

    def grown(self, weight: float = 1.0) -> "Tree":
        """With one more shard, in a new region and rack."""
        n = max(self.shards(), default=-1) + 1
        return Tree(self.regions | {f"g+{n}": {f"r+{n}": {n: weight}}})

    def with_weight(self, shard: int, weight: float) -> "Tree":
        return Tree({g: {r: {s: weight if s == shard else w for s, w in own.items()} for r, own in racks.items()} for g, racks in self.regions.items()})


def _draw(key: Column, level: str, name: str, weight: float) -> Column:
    u = (F.pmod(F.xxhash64(key, F.lit(level), F.lit(name)), F.lit(1 << 52)) + F.lit(0.5)) / F.lit(float(1 << 52))
    return -F.ln(u) / F.lit(float(weight))


def place(key: Column, tree: Tree) -> Column:
    """The shard of a key, as a chain of nested choices; each row evaluates only the branch it takes."""
    region_w = {g: sum(w for own in racks.values() for w in own.values()) for g, racks in tree.regions.items()}

    def pick(level: str, options: dict[str, float], below) -> Column:
        live = [(n, w) for n, w in options.items() if w > 0]
        if len(live) == 1:
            return below(live[0][0])
        draws = F.array(*[_draw(key, level, n, w) for n, w in live])
        chosen = F.array_position(draws, F.array_min(draws))

        def branch(c: Column) -> Column:
            out = None
            for i, (n, _) in enumerate(live):
                out = F.when(c == i + 1, below(n)) if out is None else out.when(c == i + 1, below(n))
            return out

        # the choice is named once, so that its expression is not repeated for each branch
        return F.get(F.transform(F.array(chosen), branch), F.lit(0))

    def rack(g: str) -> Column:
        racks = tree.regions[g]
        return pick(f"rack {g}", {r: sum(own.values()) for r, own in racks.items()}, lambda r: shard(g, r))

    def shard(g: str, r: str) -> Column:
        return pick(f"shard {r}", {str(s): w for s, w in tree.regions[g][r].items()}, lambda s: F.lit(int(s)))

    return pick("region", region_w, rack)


def shard_documents(docs: DataFrame, tree: Tree, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every row."""
    key = F.coalesce(F.concat(F.lit("id "), F.col("doc_id").cast("string")), F.lit("no id"))
    rows = keyed(docs, doc_id, text).select(
        F.col("doc_id"),
        (F.octet_length("text") + 1).cast("long").alias("size"),
        F.crc32(F.col("text").cast("binary")).alias("text_crc32"),
        F.lit("key").alias("law"),
        place(key, tree).cast("int").alias("shard"),
        place(key, tree.grown()).cast("int").alias("grown_shard"),
        F.xxhash64("text").alias("group_hash"),
        "row_key",
    )
    return numbered(rows, "shard", ["group_hash", "row_key"], "slot").drop("group_hash", "row_key")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return shard_documents(docs, Tree.balanced(16)).select(
        "doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard"
    )
