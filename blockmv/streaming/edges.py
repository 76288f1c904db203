"""Edges from an event stream: windows with watermarks, running degrees, and warm starts on what has come so far.

The matrix of an analysis is constant; a stream adds to it between analyses. Timestamps without a zone are cast, since
watermarks need zoned ones.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..plans.session import shared_folder

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """A folder of Parquet files as a stream; ts is a timestamp."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(events: DataFrame, size: str = "1 day", late: str = "1 hour") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", size), "event_type")
    return w.agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("window.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, size: str = "2 days", step: str = "1 day", late: str = "1 hour") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", size, step), "event_type")
    return w.agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id")
    return w.agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def first_seen(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each event_id once, also if it is sent again within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def windowed_edges(events: DataFrame, size: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Edges user -> event type per window with their counts as weights."""
    w = events.withWatermark("ts", late).groupBy(F.window("ts", size), F.col("user_id").alias("src"), F.xxhash64("event_type").alias("dst"))
    return w.agg(F.count("*").cast("double").alias("w")).select(F.col("window.start").alias("start"), "src", "dst", "w")


def running_degrees(events: DataFrame) -> DataFrame:
    """Out-degree so far of each user; for the update mode."""
    return events.groupBy(F.col("user_id").alias("node")).agg(F.count("*").alias("deg"))


def with_ranks(events: DataFrame, ranks: DataFrame) -> DataFrame:
    """Stream-static join with the current ranks (node, val)."""
    return events.join(ranks.select("node", F.col("val").alias("rank")), events["user_id"] == F.col("node"), "left").drop("node")


def stateful_degrees(events: DataFrame) -> DataFrame:
    """Out-degree so far of each user, kept by a state of our own: a row whenever a user's degree has grown."""

    def grow(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        deg = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((deg,))
        yield pd.DataFrame({"node": [key[0]], "deg": [deg]})

    return events.groupBy("user_id").applyInPandasWithState(grow, "node bigint, deg bigint", "deg bigint", "update", GroupStateTimeout.NoTimeout)


def run_to_end(stream: DataFrame, mode: str = "append", path: str | None = None) -> DataFrame:
    """Everything that is available now, as a Parquet table in the shared folder: no result passes through the driver.

    A batch that is repeated replaces its own folder. mode: append (all batches), complete (the last one), update (all
    batches, with the column ``batch``, which tells the latest row of a key).
    """
    spark = stream.sparkSession
    folder = path or f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"

    def write(batch: DataFrame, k: int) -> None:
        to = f"{folder}/rows" if mode == "complete" else f"{folder}/rows/batch={k}"
        batch.write.mode("overwrite").parquet(to)

    query = stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    schema = stream.schema if mode == "complete" else T.StructType([*stream.schema.fields, T.StructField("batch", T.IntegerType())])
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{folder}/rows")
    if not where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(where):
        return spark.createDataFrame([], schema)
    rows = spark.read.schema(schema).parquet(f"{folder}/rows")
    return rows if mode != "append" else rows.drop("batch")


def split_late(events: DataFrame, path: str, late: str = "1 hour") -> tuple[DataFrame, DataFrame]:
    """The events in time, and those that came when the watermark - the latest time of the batches before, less ``late`` -
    had passed them: nothing is lost silently. One number per batch reaches the driver."""
    spark, latest = events.sparkSession, []

    def write(batch: DataFrame, k: int) -> None:
        held = batch.persist()
        mark = F.lit(max(latest)) - F.expr(f"INTERVAL {late}") if latest else None
        is_late = F.lit(False) if mark is None else F.coalesce(F.col("ts") < mark, F.lit(False))
        held.filter(~is_late).write.mode("overwrite").parquet(f"{path}/in_time/batch={k}")
        held.filter(is_late).write.mode("overwrite").parquet(f"{path}/late/batch={k}")
        if (top := held.agg(F.max("ts")).first()[0]) is not None:
            latest.append(top)
        held.unpersist()

    events.writeStream.foreachBatch(write).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    return tuple(spark.read.schema(events.schema).parquet(f"{path}/{k}/*") for k in ("in_time", "late"))


def append_blocks(edges: DataFrame, path: str, checkpoint: str, after: Callable[[DataFrame, int], None] | None = None) -> None:
    """Append each micro-batch of edges to a folder, one sub-folder per batch (a repeated batch replaces its own), then
    call ``after`` with all edges so far - a warm-started analysis, for example."""

    def write(batch: DataFrame, k: int) -> None:
        batch.select("src", "dst", "w").write.mode("overwrite").parquet(f"{path}/batch={k}")
        if after:
            after(batch.sparkSession.read.parquet(path).select("src", "dst", "w"), k)

    query = edges.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
