"""Exact deduplication by a keyed streaming state on disk.

Arrivals (digest, stable identifier, content locator) flow through a Structured Streaming aggregation whose RocksDB
state never expires; the state is then read back as a table. A row's locator, the file that holds it and its place there, is
its identifier too: it is the same in every run over the same files, and files that come later bring locators of their own.
A digest seen more than once is a hit: the texts of all its locators are fetched and their full bytes compared before they
count as copies. Everything is DataFrame operations.

Defined cases: null text is the empty text; texts of any length are read whole; the row with the largest doc_id of equal
texts stays, null ids last, and among repeated rows (same id, same text) the one with the last locator; an empty table gives no
rows; other columns are neither read nor changed, so names that clash do no harm.
"""

from __future__ import annotations

from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from quotaknn.llm.common import col, located, materialise, scratch, settled

ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
LOG = "file string, row long, doc_id long, digest binary, n_bytes long"


@contextmanager
def state_on_disk(spark: SparkSession):
    """RocksDB holds the state for the streams started inside, and lets go of its working folder with each commit; the
    session's own choices come back after."""
    chosen = {"spark.sql.streaming.stateStore.providerClass": ROCKS, "spark.sql.streaming.stateStore.unloadOnCommit": "true"}
    before = {k: spark.conf.get(k, None) for k in chosen}
    for k, v in chosen.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def texts_of(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """file, row, doc_id, text."""
    own, file, row = located(docs)
    return own.select(col(file).alias("file"), col(row).alias("row"), col(doc_id).cast("long").alias("doc_id"), F.coalesce(col(text), F.lit("")).alias("text"))


def arrivals(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One narrow row per document: what the state needs to know, without the text."""
    return texts_of(docs, doc_id, text).select(
        "file", "row", "doc_id", F.unhex(F.sha2("text", 256)).alias("digest"), F.octet_length("text").cast("long").alias("n_bytes")
    )


def run_state(spark: SparkSession, log_path: str, state_path: str, files_per_batch: int = 64) -> DataFrame:
    """Feed all arrivals not yet seen to the state at `state_path`; returns the state: digest, keeper, n.

    Call it again after more files have come to `log_path`: it goes on where it stopped, as the checkpoint tells.
    """
    log = spark.readStream.schema(LOG).option("maxFilesPerTrigger", files_per_batch).parquet(log_path)
    seen = log.groupBy("digest").agg(
        F.max(F.struct("doc_id", "file", "row", "n_bytes")).alias("keeper"), F.count(F.lit(1)).alias("n")
    )
    with state_on_disk(spark):
        query = (
            seen.writeStream.format("noop").outputMode("update").option("checkpointLocation", state_path)
            .trigger(availableNow=True).start()
        )
        query.awaitTermination()
        state = spark.read.format("statestore").load(state_path)
        keeper, n = (f"`{f.name}`" for f in state.schema["value"].dataType.fields)
        return state.select(F.col("key.digest").alias("digest"), F.col(f"value.{keeper}").alias("keeper"), F.col(f"value.{n}").alias("n"))


def fetched(texts: DataFrame, log: DataFrame, state: DataFrame) -> DataFrame:
    """digest, file, row, doc_id, text of every row whose digest was seen more than once, found by its locator."""
    hits = log.join(state.where("n > 1").select("digest"), "digest").select("digest", "file", "row")
    return texts.join(hits, ["file", "row"])


def differing(found: DataFrame) -> DataFrame:
    """digest of the hits whose texts are not all equal, byte by byte. Each task first finds its own least and greatest text
    of a digest, so a hot one is spread over as many tasks as hold its rows."""
    return found.groupBy("digest").agg(F.min("text").alias("a"), F.max("text").alias("b")).where("a <> b").select("digest")


def exact_dedup(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Decisions, one per row: file, row, doc_id, digest, keep_id, keep_file, keep_row, group_size, kept."""
    spark = docs.sparkSession
    docs = settled(docs)
    log_path = scratch(spark, "arrivals")
    arrivals(docs, doc_id, text).write.parquet(log_path)
    log = spark.read.schema(LOG).parquet(log_path)
    if log.isEmpty():
        state = spark.createDataFrame([], "digest binary, keeper struct<doc_id:long,file:string,row:long,n_bytes:long>, n long")
    else:
        with state_on_disk(spark):
            state = materialise(run_state(spark, log_path, scratch(spark, "state")), "seen")
    members = fetched(texts_of(docs, doc_id, text), log, state)
    differ = materialise(differing(members), "collisions")
    found = log.join(state, "digest").select(
        "file", "row", "doc_id", "digest", F.col("keeper.doc_id").alias("keep_id"), F.col("keeper.file").alias("keep_file"),
        F.col("keeper.row").alias("keep_row"), F.col("n").alias("group_size"),
    )
    if not differ.isEmpty():
        own = members.join(differ, "digest")
        groups = own.groupBy("digest", "text").agg(F.max(F.struct("doc_id", "file", "row")).alias("k"), F.count(F.lit(1)).alias("group_size"))
        redone = own.join(groups, ["digest", "text"]).select(
            "file", "row", "doc_id", "digest", F.col("k.doc_id").alias("keep_id"), F.col("k.file").alias("keep_file"), F.col("k.row").alias("keep_row"), "group_size"
        )
        found = found.join(differ, "digest", "left_anti").unionByName(redone)
    return found.withColumn("kept", (F.col("file") == F.col("keep_file")) & (F.col("row") == F.col("keep_row")))


def drop_copies(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """`docs` without the rows that exact_dedup drops; all columns stay as they are."""
    docs = settled(docs)
    own, file, row = located(docs)
    gone = exact_dedup(docs, doc_id, text).where(~F.col("kept")).select(F.col("file").alias(file), F.col("row").alias(row))
    return own.join(gone, [file, row], "left_anti").select(*[col(c) for c in docs.columns])


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return exact_dedup(docs).select(
        "doc_id", "keep_id", "group_size", "kept", F.lower(F.hex("digest")).alias("text_sha256")
    )


SQL = """
select doc_id, max(doc_id) over w as keep_id, count(*) over w as group_size,
       doc_id = max(doc_id) over w as kept, sha256(coalesce(text, '')) as text_sha256
from documents window w as (partition by coalesce(text, ''))
"""
