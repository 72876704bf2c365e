"""Structured Streaming over call events: windows, exactly-once calls, the live reach monitor, ledgers.

Every stream reads Parquet with a given schema, casts the zoneless time to a timestamp for watermarks,
and keeps its checkpoint in the shared folder, so a restart goes on where it stopped.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from statewitness.sources.formats import scratch_path
from statewitness.sources.tables import SCHEMAS


def event_stream(spark: SparkSession, sf_dir: str, per_trigger: int = 1, path: str | None = None) -> DataFrame:
    """The event table as a stream of files, with ``at`` as its event time."""
    source = path or f"{sf_dir}/events.parquet"
    reader = spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", per_trigger)
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(source)
    if target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(target).isFile():
        reader, source = reader.option("pathGlobFilter", "events.parquet"), sf_dir  # a stream reads folders
    rows = reader.parquet(source)
    return rows.withColumn("at", F.col("ts").cast("timestamp"))


def split_files(spark: SparkSession, sf_dir: str, files: int, late: int | None = None) -> str:
    """Events in several files by ranges of ids (one of them written last, so it comes late)."""
    path = scratch_path(spark, "stream")
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    top = events.agg(F.max("event_id")).first()[0] + 1
    order = [k for k in range(files) if k != late] + ([late] if late is not None else [])
    for k in order:
        part = events.filter((F.col("event_id") >= top * k // files) & (F.col("event_id") < top * (k + 1) // files))
        part.coalesce(1).write.mode("append").parquet(path)
    return path


def drained(stream: DataFrame, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Run a stream over all that is there and return what it wrote, as Parquet.

    In append mode each batch adds its rows; else each batch replaces the table by its whole result, which the
    tasks write (nothing is gathered at the driver).
    """
    spark = stream.sparkSession
    checkpoint, out = checkpoint or scratch_path(spark, "checkpoint"), scratch_path(spark, "sink")
    if mode == "append":
        writer = stream.writeStream.format("parquet").option("path", out)
    else:
        spark.createDataFrame([], stream.schema).write.parquet(out)  # a stream without rows has no batch
        writer = stream.writeStream.foreachBatch(lambda batch, _epoch: batch.write.mode("overwrite").parquet(out))
    writer.option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def tumbling(stream: DataFrame) -> DataFrame:
    return stream.withWatermark("at", "1 day").groupBy(F.window("at", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").cast("string").alias("start"), "event_type", "n")


def sliding(stream: DataFrame) -> DataFrame:
    return stream.withWatermark("at", "1 day").groupBy(F.window("at", "2 days", "1 day").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").cast("string").alias("start"), "n")


def sessions(stream: DataFrame, gap: str = "6 hours") -> DataFrame:
    return stream.withWatermark("at", "1 day").groupBy(F.session_window("at", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").cast("string").alias("start"), "user_id", "n")


def once(stream: DataFrame) -> DataFrame:
    """Each call once, however often it was delivered within the watermark."""
    return stream.withWatermark("at", "1 day").dropDuplicatesWithinWatermark(["event_id"])


def live_reach(stream: DataFrame) -> DataFrame:
    """Purchases with whether their user was held at that moment: one state (held or not) for each user."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = state.get[0] if state.exists else False
        rows = pd.concat(list(batches)).sort_values(["at", "event_id"])
        out = []
        for event_id, kind in zip(rows["event_id"], rows["event_type"]):
            if kind == "purchase":
                out.append((key[0], int(event_id), held))
            held = True if kind == "error" else False if kind == "signup" else held
        state.update((held,))
        yield pd.DataFrame(out, columns=["user_id", "event_id", "reaches"])

    return stream.select("user_id", "event_id", "event_type", "at").groupBy("user_id").applyInPandasWithState(step, "user_id long, event_id long, reaches boolean", "held boolean", "append", GroupStateTimeout.NoTimeout)


def with_static(stream: DataFrame, contracts: DataFrame) -> DataFrame:
    """Calls with the contract of their operation (a small static side)."""
    return stream.join(F.broadcast(contracts), "event_type")


def effects_within(calls: DataFrame, results: DataFrame, limit: str = "1 hour") -> DataFrame:
    """Calls with the effects that followed within a limit (stream-stream join bounded by watermarks)."""
    c = calls.withWatermark("at", "1 day").select(F.col("event_id").alias("call"), F.col("user_id").alias("u"), F.col("at").alias("call_at"))
    r = results.withWatermark("at", "1 day").select(F.col("event_id").alias("effect"), F.col("user_id").alias("v"), F.col("at").alias("effect_at"))
    return c.join(r, F.expr(f"u = v AND effect_at > call_at AND effect_at <= call_at + INTERVAL {limit}")).select("call", "effect")


def into_ledger(stream: DataFrame, path: str, keys: list[str]) -> None:
    """Append each batch's new rows to a Parquet ledger; a batch that runs twice adds nothing."""
    spark = stream.sparkSession

    def write(batch: DataFrame, _epoch: int) -> None:
        try:
            have = spark.read.parquet(path).select(*keys)
            batch = batch.join(have, keys, "left_anti")
        except Exception as missing:  # the first batch has no ledger yet
            if "PATH_NOT_FOUND" not in str(missing) and "UNABLE_TO_INFER_SCHEMA" not in str(missing):
                raise
        batch.dropDuplicates(keys).write.mode("append").parquet(path)

    run(stream, write)


def run(stream: DataFrame, write: Callable[[DataFrame, int], None]) -> None:
    q = stream.writeStream.foreachBatch(write).option("checkpointLocation", scratch_path(stream.sparkSession, "checkpoint")).trigger(availableNow=True).start()
    q.awaitTermination()
