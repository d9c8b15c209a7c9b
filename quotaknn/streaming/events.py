"""Streams: continuous ingestion into an index, queries against it, and monitors over event streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from quotaknn.operators.search import search
from quotaknn.plans.index import Index, append_index
from quotaknn.plans.lineage import shared_path

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def read_stream(spark: SparkSession, path: str, schema, files_per_batch: int = 1) -> DataFrame:
    """Files that arrive at a path (a folder, a file or a pattern), in batches."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def run_to_end(stream: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Process all that is there, then read the result: a Parquet sink for append, where each row is final; for update and
    complete each batch overwrites its own folder and the last batch that has a row counts."""
    spark = stream.sparkSession
    out, checkpoint = shared_path(spark, f"stream-{name}"), checkpoint or shared_path(spark, f"state-{name}")
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)

    def put(batch: DataFrame, batch_id: int) -> None:
        path = f"{out}/b{batch_id:012d}"
        batch.withColumn("batch_", F.lit(batch_id)).write.mode("overwrite").parquet(path)
        seen.append(path)

    seen: list[str] = []

    q = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    if not seen:  # the stream had no batch
        return spark.createDataFrame([], stream.schema)
    rows = spark.read.parquet(*seen)
    if mode == "complete":
        last = rows.agg(F.max("batch_").alias("batch_"))
        return rows.join(F.broadcast(last), "batch_").drop("batch_")
    return rows.drop("batch_")


def late_rows(events: DataFrame, keys: list[str], late: str = "2 hours") -> DataFrame:
    """batch, rows, late_rows: how many rows each batch had and how many of them came behind the watermark and were dropped, as
    the state of a deduplication by `keys` counts them."""
    spark = events.sparkSession
    q = deduplicated(events, keys, late).writeStream.format("noop").option("checkpointLocation", shared_path(spark, "late")).trigger(availableNow=True).start()
    q.awaitTermination()
    told = [(p["batchId"], p["numInputRows"], sum(s["numRowsDroppedByWatermark"] for s in p["stateOperators"])) for p in q.recentProgress if p["numInputRows"]]
    return spark.createDataFrame(told, "batch long, rows long, late_rows long")


def tumbling(events: DataFrame, length: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Counts by window and value; a window is final once the watermark has passed it."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", length), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, length: str = "6 hours", step: str = "3 hours", late: str = "2 hours") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", length, step), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    s = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return s.select("user_id", F.col("session_window.start").alias("start"), "n")


def quota_monitor(counts: DataFrame, needs: dict[str, int]) -> DataFrame:
    """start, event_type, n, need, gap: windowed counts against the counts wanted."""
    need = F.element_at(F.create_map(*[F.lit(x) for kv in needs.items() for x in kv]), F.col("event_type"))
    return counts.withColumn("need", F.coalesce(need, F.lit(0))).withColumn("gap", F.col("n") - F.col("need"))


def deduplicated(events: DataFrame, keys: list[str], late: str = "2 hours") -> DataFrame:
    """First arrival of each key; state is kept only as long as the watermark needs it."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def followed(first: DataFrame, second: DataFrame, within: str = "10 minutes", late: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: events of `second` by the same user within a time after those of `first`."""
    a = first.select(F.col("event_id").alias("first_id"), F.col("user_id").alias("u_"), F.col("ts").alias("a_")).withWatermark("a_", late)
    b = second.select(F.col("event_id").alias("second_id"), "user_id", F.col("ts").alias("b_")).withWatermark("b_", late)
    return a.join(b, F.expr(f"u_ = user_id and b_ > a_ and b_ <= a_ + interval {within}")).select("first_id", "second_id", "user_id")


def ingest(stream: DataFrame, index: Index, checkpoint: str | None = None) -> Index:
    """Append arriving vectors to a stored index. A batch that is tried again after a failure adds nothing twice: records
    that the index holds already are left out."""
    checkpoint = checkpoint or shared_path(index.spark, "ingest")
    state = {"index": index}

    def put(batch: DataFrame, batch_id: int) -> None:
        here = state["index"]
        new = batch.dropDuplicates(["rec_id"]).join(here.vectors.select("rec_id"), "rec_id", "left_anti")
        state["index"] = append_index(here, new)

    q = stream.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return state["index"]


def answer_stream(queries: DataFrame, index: Index, checkpoint: str | None = None, **options) -> DataFrame:
    """Queries that arrive with their needs as a map of maps in JSON (query_id, qvec, needs); answers as a table."""
    spark, out = index.spark, shared_path(index.spark, "answers")
    checkpoint = checkpoint or shared_path(spark, "queries")

    def put(batch: DataFrame, batch_id: int) -> None:
        needs = F.from_json("needs", "map<string, map<string, int>>")
        long = batch.select("query_id", F.explode(needs).alias("attr", "own")).select("query_id", "attr", F.explode("own").alias("value", "need"))
        path = f"{out}/b{batch_id:012d}"
        search(index, batch.select("query_id", "qvec"), long, **options).answer.write.mode("overwrite").parquet(path)
        seen.append(path)

    seen: list[str] = []

    q = queries.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    if not seen:
        own = [f for f in index.vectors.schema.fields if f.name in index.attrs]
        return spark.createDataFrame([], T.StructType([T.StructField("query_id", T.LongType()), T.StructField("pos", T.IntegerType()), T.StructField("rec_id", T.LongType()), T.StructField("dist", T.DoubleType()), *own]))
    return spark.read.parquet(*seen)


def running_best(spark: SparkSession, events: DataFrame, k: int, length: str = "1 day") -> DataFrame:
    """The k smallest values by window and type. Each batch is merged with the table of the best so far, which holds k rows
    of each group and no more; versions are written beside each other, so a batch tried again starts from the same table."""
    out, checkpoint = shared_path(spark, "best"), shared_path(spark, "best-state")
    keep = "start timestamp, event_type string, value double, event_id long"
    from pyspark.sql import Window

    order = Window.partitionBy("start", "event_type").orderBy("value", "event_id")

    def put(batch: DataFrame, batch_id: int) -> None:
        new = batch.select(F.window("ts", length)["start"].alias("start"), "event_type", "value", "event_id")
        if batch_id:
            new = new.unionByName(spark.read.schema(keep).parquet(f"{out}/v{batch_id - 1}"))
        new.withColumn("rank_", F.row_number().over(order)).where(F.col("rank_") <= k).drop("rank_").write.mode("overwrite").parquet(f"{out}/v{batch_id}")
        done["last"] = batch_id

    done: dict = {}
    q = events.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    if "last" not in done:
        return spark.createDataFrame([], keep)
    return spark.read.schema(keep).parquet(f"{out}/v{done['last']}")
