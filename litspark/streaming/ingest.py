"""Streaming: pages arriving are parsed, chunked and indexed; windows over the event log; queries against the index.

Event times of the given tables carry no zone, so they are cast to timestamps
(the session runs in UTC).  Checked runs take everything that is there
(``availableNow``) into a table and equal the batch result.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from litspark.catalog import SCHEMAS
from litspark.operators import chunk, parse


def stream(spark: SparkSession, folder: str, table: str, files_per_trigger: int = 4) -> DataFrame:
    """A table as a file stream: the Parquet file of ``folder`` named after the table, or the files in the folder of that name."""
    # as a pattern, since the source takes a path without one for a folder
    return spark.readStream.schema(SCHEMAS[table]).option("maxFilesPerTrigger", files_per_trigger).parquet(f"{folder}/{table}.parque[t]")


def _work_folder(spark: SparkSession) -> str:
    context = spark.sparkContext
    named = context.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not named and context.master.split("[")[0] == "local":  # driver and executors are one process
        import tempfile

        named = tempfile.mkdtemp(prefix="litspark-stream-")
    named = named or spark.conf.get("spark.sql.warehouse.dir")
    return f"{named.rstrip('/')}/stream-{uuid.uuid4().hex}"


def drained(df: DataFrame, mode: str = "append") -> DataFrame:
    """The result of a stream over all that is there now."""
    spark, folder = df.sparkSession, _work_folder(df.sparkSession)
    name = f"drained_{uuid.uuid4().hex}"
    if mode == "append":
        df.writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{folder}/out")
    # complete results are small reports (one row per window and key)
    df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.table(name)


def timed_events(events: DataFrame) -> DataFrame:
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def windowed(events: DataFrame, kind: str) -> DataFrame:
    """Counts per event type over tumbling days, sliding 7 days by one, or sessions with gaps of 7 days."""
    when = {"tumbling": F.window("ts", "1 day"), "sliding": F.window("ts", "7 days", "1 day"), "session": F.session_window("ts", "7 days")}[kind]
    marked = timed_events(events)
    marked = marked.withWatermark("ts", "1 hour") if events.isStreaming else marked
    return marked.groupBy(when.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), F.date_format("w.end", "yyyy-MM-dd HH:mm:ss").alias("end"), "event_type", "n")


def deduplicated(events: DataFrame) -> DataFrame:
    """First event of each (user, type, hour): state is dropped behind the watermark."""
    keyed = timed_events(events).withColumn("hour", F.date_trunc("hour", "ts"))
    keys = ["user_id", "event_type", "hour"]
    if events.isStreaming:
        return keyed.withWatermark("hour", "2 hours").dropDuplicates(keys).select(*keys[:2], F.col("hour").cast("string").alias("hour"))
    return keyed.dropDuplicates(keys).select(*keys[:2], F.col("hour").cast("string").alias("hour"))


def indexed_chunks(pages: DataFrame) -> DataFrame:
    """Pages to chunks with their number, no shuffle: the ingest plan of the index."""
    parsed = parse.two_stage(pages).withColumn("doc_id", F.col("page_id"))
    return chunk.semantic_chunks(parsed).select("chunk_id", "doc_id", "chunk_no", "n_tokens")


def ingest(pages: DataFrame, sink: Callable[[DataFrame, int], None]) -> None:
    """Runs the ingest plan; each micro-batch goes to ``sink`` with its number, which must write idempotently."""
    folder = _work_folder(pages.sparkSession)
    indexed_chunks(pages).writeStream.foreachBatch(sink).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()


def query_log_topk(events: DataFrame, neighbours: DataFrame) -> DataFrame:
    """Stream-static join: each search event with the precomputed neighbours of its vector."""
    asked = timed_events(events).withColumn("query_id", F.pmod("user_id", F.lit(10)) * 50)
    return asked.join(neighbours, "query_id").select("event_id", "query_id", "rank", "id")


def paired_events(events: DataFrame, first: str, second: str) -> DataFrame:
    """Stream-stream interval join: second events of a user within a day after a first one."""
    timed = timed_events(events)
    timed = timed.withWatermark("ts", "1 hour") if events.isStreaming else timed
    a = timed.where(F.col("event_type") == first).select(F.col("event_id").alias("first_id"), F.col("user_id").alias("u"), F.col("ts").alias("t"))
    b = timed.where(F.col("event_type") == second).select(F.col("event_id").alias("second_id"), "user_id", "ts")
    return a.join(b, F.expr("u = user_id AND ts >= t AND ts <= t + INTERVAL 1 DAY")).select("first_id", "second_id")


def running_users(events: DataFrame) -> DataFrame:
    """Custom state: per user the number of events and the sum of gaps in seconds, updated batch by batch (latest row counts)."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, total = state.get if state.exists else (0, 0.0)
        for batch in batches:
            n += len(batch)
            total += float(batch["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "events": [n], "total": [total]})

    return timed_events(events).select("user_id", "value").groupBy("user_id").applyInPandasWithState(update, "user_id long, events long, total double", "n long, total double", "update", GroupStateTimeout.NoTimeout)
