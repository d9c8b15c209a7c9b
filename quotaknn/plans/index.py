"""The index: vectors with cell codes, one posting for each record and table, cell sizes, dictionary and hash family.

All cells are indexed by one job: the cell code is the first part of a posting's key. Postings hold ids only; vectors are
joined last, for the few records that are inspected.
"""

from __future__ import annotations

import json
import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from quotaknn.functions.cells import CellDictionary, build_dictionary
from quotaknn.functions.lsh import Family, family_for, lsh_keys, plan_cells
from quotaknn.plans.lineage import bytes_under, cut, shared_path
from quotaknn.sources.catalog import sound


@dataclass
class Index:
    vectors: DataFrame  # rec_id, vec, attributes, cell_code
    postings: DataFrame  # cell_code, table_no, bucket, rec_id
    cells: DataFrame  # cell_code, n_cell
    dictionary: CellDictionary
    family: Family
    metric: str = "l2"
    path: str | None = None
    seconds: dict = field(default_factory=dict)

    @property
    def attrs(self) -> list[str]:
        return self.dictionary.attrs

    @property
    def spark(self) -> SparkSession:
        return self.vectors.sparkSession


def postings_of(coded: DataFrame, family: Family) -> DataFrame:
    keys = lsh_keys(family)(F.col("vec"))
    return coded.select("cell_code", "rec_id", F.posexplode(keys).alias("table_no", "bucket")).select("cell_code", "table_no", "bucket", "rec_id")


def planned_postings(coded: DataFrame, family: Family, cells: DataFrame) -> DataFrame:
    """Postings by the numbers of each cell, where cells have them (hashes, tables); a new cell takes the family's own."""
    if "hashes" not in cells.columns:
        return postings_of(coded, family)
    plan = cells.select("cell_code", "hashes", "tables")
    rows = coded.join(plan, "cell_code", "left").select("cell_code", "rec_id", "vec", F.coalesce("hashes", F.lit(family.hashes)).alias("hashes"), F.coalesce("tables", F.lit(family.tables)).alias("tables"))
    out = None
    for n in range(1, family.hashes + 1):
        keys = lsh_keys(family.prefix(n))(F.col("vec"))
        own = rows.where(F.col("hashes") == n).select("cell_code", "rec_id", "tables", F.posexplode(keys).alias("table_no", "bucket"))
        own = own.where(F.col("table_no") < F.col("tables")).select("cell_code", "table_no", "bucket", "rec_id")
        out = own if out is None else out.unionByName(own)
    return out


def build_index(vectors: DataFrame, attrs: list[str], metric: str = "l2", tables: int = 16, hashes: int = 2, width: float = 1.0, seed: int = 42,
                order: dict | None = None, dim: int | None = None, path: str | None = None, per_cell: dict | None = None, compact: bool = True) -> Index:
    """Build and, with a path or with compact, write the index. Unsound vectors are left out (see catalog.bad_vectors).

    per_cell = {p1, p2, near, delta} plans hashes and tables for each cell by its size; a cell's keys then join the first of
    the family's hashes that it needs, in the first of its tables. A record never changes its cell, as attributes are
    immutable."""
    spark, began = vectors.sparkSession, time.monotonic()
    if dim is None:
        head = vectors.where("vec is not null").select(F.size("vec").alias("d")).head()
        dim = head["d"] if head else 1
    dictionary = build_dictionary(vectors, attrs, order)
    family = family_for(metric, dim, tables=tables, hashes=hashes, width=width, seed=seed)
    coded = vectors.where(sound(F.col("vec"), dim)).select("rec_id", "vec", *attrs).withColumn("cell_code", dictionary.cell_code())
    seconds = {"dictionary": time.monotonic() - began}
    if not (path or compact):
        cells = coded.groupBy("cell_code").agg(F.count(F.lit(1)).alias("n_cell"))
        return Index(coded, postings_of(coded, family), cells, dictionary, family, metric, None, seconds)
    path = path or shared_path(spark, "index")
    began = time.monotonic()
    # clustered by cell, so that a probe reads few row groups of the vectors
    coded.repartitionByRange("cell_code", "rec_id").sortWithinPartitions("cell_code", "rec_id").write.parquet(f"{path}/vectors")
    stored = spark.read.schema(coded.schema).parquet(f"{path}/vectors")
    cells = stored.groupBy("cell_code").agg(F.count(F.lit(1)).alias("n_cell"))
    if per_cell:
        plan = plan_cells(F.col("n_cell"), **per_cell)
        cells = cells.select("*", F.least(plan["hashes"], F.lit(hashes)).alias("hashes"), F.least(plan["tables"], F.lit(tables)).alias("tables"))
    cells.write.parquet(f"{path}/cells")
    cells = spark.read.schema(cells.schema).parquet(f"{path}/cells")
    seconds["cells"] = time.monotonic() - began
    began = time.monotonic()
    postings = planned_postings(stored, family, cells)
    postings.repartitionByRange("table_no", "cell_code", "bucket").sortWithinPartitions("table_no", "cell_code", "bucket").write.parquet(f"{path}/postings")
    postings = spark.read.schema(postings.schema).parquet(f"{path}/postings")
    seconds["postings"] = time.monotonic() - began
    meta = {"values": dictionary.values, "metric": metric, "family": family.__dict__}
    spark.createDataFrame([(json.dumps(meta),)], "meta string").coalesce(1).write.text(f"{path}/meta")
    return Index(stored, postings, cells, dictionary, family, metric, path, seconds)


def load_index(spark: SparkSession, path: str) -> Index:
    meta = json.loads(spark.read.text(f"{path}/meta").head()[0])
    dictionary, family = CellDictionary(meta["values"]), Family(**meta["family"])
    read = lambda part: spark.read.parquet(f"{path}/{part}")
    return Index(read("vectors"), read("postings"), read("cells"), dictionary, family, meta["metric"], path)


def append_index(index: Index, fresh: DataFrame) -> Index:
    """Add new records to a stored index: only their own keys are computed. Values outside the dictionary count as absent
    until the index is built anew."""
    coded = fresh.where(sound(F.col("vec"), index.family.dim)).select("rec_id", "vec", *index.attrs).withColumn("cell_code", index.dictionary.cell_code())
    coded = cut(coded, "fresh")
    # postings and sizes first: a record counts as held once its vector is there, so what a crash cut off is done again
    planned_postings(coded, index.family, index.cells).write.mode("append").parquet(f"{index.path}/postings")
    sizes = coded.groupBy("cell_code").agg(F.count(F.lit(1)).alias("n_cell"))
    if "hashes" in index.cells.columns:
        sizes = sizes.join(index.cells.select("cell_code", "hashes", "tables"), "cell_code", "left").select("cell_code", "n_cell", F.coalesce("hashes", F.lit(index.family.hashes)).alias("hashes"), F.coalesce("tables", F.lit(index.family.tables)).alias("tables"))
    sizes.write.mode("append").parquet(f"{index.path}/cells")
    coded.write.mode("append").parquet(f"{index.path}/vectors")
    return refreshed(index)


def refreshed(index: Index) -> Index:
    again = load_index(index.spark, index.path)
    plan = [F.max(c).alias(c) for c in ("hashes", "tables") if c in again.cells.columns]
    again.cells = again.cells.groupBy("cell_code").agg(F.sum("n_cell").alias("n_cell"), *plan).where("n_cell > 0")
    return again


def delete_from_index(index: Index, gone: DataFrame) -> Index:
    """The index without the records in `gone` (rec_id): tombstones, applied when read; compact by building anew."""
    gone = gone.select("rec_id").distinct()
    vectors = index.vectors.join(gone, "rec_id", "left_anti")
    cells = vectors.groupBy("cell_code").agg(F.count(F.lit(1)).alias("n_cell"))
    return Index(vectors, index.postings.join(gone, "rec_id", "left_anti"), cells, index.dictionary, index.family, index.metric, index.path)


def index_bytes(index: Index) -> dict[str, int]:
    """Bytes by part of a stored index, with those of the hash functions."""
    if not index.path:
        raise ValueError("the index is not stored")
    parts = {p: bytes_under(index.spark, f"{index.path}/{p}") for p in ("vectors", "postings", "cells", "meta")}
    return parts | {"hash_functions": 8 * index.family.tables * index.family.hashes * (index.family.dim + 1)}
