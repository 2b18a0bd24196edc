"""Streams of events: traversal counts, windows, trips and monitoring.

Every stream reads files of events as they come and ends when it has read all
that are there (``availableNow``); a caller who wants it to go on passes another
trigger. State lives below the checkpoint in the shared folder.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import mutual
from ..scratch import new_path

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, sf_dir: str, *, files: int = 1) -> DataFrame:
    """Events as a stream, with a zoned time and the cell ``k``."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/events.parquet")
    system = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    # A table of one file is found by its name in the folder, as streams read folders.
    folder, names = (sf_dir, "events.parquet") if system.getFileStatus(path).isFile() else (f"{sf_dir}/events.parquet", "*.parquet")
    own = spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files).option("pathGlobFilter", names).parquet(folder)
    return own.withColumn("ts", F.col("ts").cast("timestamp")).withColumn("k", F.get_json_object("props", "$.k").cast("int"))


def run(stream: DataFrame, name: str, *, mode: str = "append") -> DataFrame:
    """Run a stream to the end and return its result.

    Append writes files that a table reads. Complete and update keep the last
    batch or each key's last row; their batches go to folders of their own.
    """
    spark = stream.sparkSession
    out, checkpoint = new_path(spark, f"stream-{name}"), new_path(spark, f"stream-{name}-state")
    writer = stream.writeStream.trigger(availableNow=True).option("checkpointLocation", checkpoint)
    if mode == "append":
        query = writer.outputMode("append").format("parquet").option("path", out).start()
    else:
        query = writer.outputMode(mode).foreachBatch(lambda df, i: df.withColumn("batch", F.lit(i)).write.mode("overwrite").parquet(f"{out}/part={i:09d}")).start()
    query.awaitTermination()
    if mode == "append":
        return spark.read.schema(stream.schema).parquet(out)
    schema = stream.schema.add("batch", "long").add("part", "string")
    return spark.read.schema(schema).parquet(out).drop("part")


def latest(df: DataFrame) -> DataFrame:
    """The last batch that a complete-mode stream wrote."""
    last = df.agg(F.max("batch").alias("batch"))
    return df.join(F.broadcast(last), "batch").drop("batch")


def edge_counts(stream: DataFrame) -> DataFrame:
    """Visits of each user to each cell, as state."""
    return stream.groupBy(F.col("user_id").alias("t"), F.col("k").cast("long").alias("s")).agg(F.count(F.lit(1)).alias("n"))


def tumbling(stream: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    """Events and their values by window."""
    window = F.window("ts", size, slide) if slide else F.window("ts", size)
    own = stream.groupBy(window.alias("w")).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("value"))
    return own.select(F.col("w.start").alias("start"), "n", "value")


def sessions(stream: DataFrame, gap: str) -> DataFrame:
    """Trips by a pause, as session windows."""
    own = stream.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return own.select("user_id", F.col("w.start").alias("start"), "n")


def trip_states(stream: DataFrame, gap_seconds: int = 86_400) -> DataFrame:
    """Trips through state of our own: each user's open trip, closed by a later event beyond the pause or by the watermark."""

    def step(key: tuple[Any], frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        closed: list[tuple[int, float, float, int]] = []
        held = list(state.get) if state.exists else None
        if state.hasTimedOut:
            closed.append((key[0], held[0], held[1], held[2]))
            state.remove()
        else:
            every = pd.concat(list(frames)).sort_values("second")["second"].tolist()
            for second in every:
                if held is not None and second - held[1] > gap_seconds:
                    closed.append((key[0], held[0], held[1], held[2]))
                    held = None
                held = [second, second, 1] if held is None else [min(held[0], second), max(held[1], second), held[2] + 1]
            state.update(tuple(held))
            ends = int((held[1] + gap_seconds) * 1000)
            state.setTimeoutTimestamp(max(ends, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame(closed, columns=["user_id", "first", "last", "n"])

    own = stream.withWatermark("ts", "1 hour").withColumn("second", F.col("ts").cast("double"))
    return own.groupBy("user_id").applyInPandasWithState(step, "user_id long, first double, last double, n long", "first double, last double, n long", "append", GroupStateTimeout.EventTimeTimeout)


def monitor(stream: DataFrame) -> DataFrame:
    """Block counts of half-grid cells by user groups, from which mutual information is read."""
    own = stream.groupBy(F.pmod("user_id", F.lit(4)).alias("ct"), F.floor(F.col("k") / 25).cast("long").alias("cs"))
    return own.agg(F.count(F.lit(1)).alias("m"))


def monitored(df: DataFrame) -> DataFrame:
    return mutual.contributions(df)
