"""Blocking of arriving records with Structured Streaming."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from recblock.session import checkpoint_root, stored


def replay(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """A table's file as a stream."""
    schema = spark.read.parquet(f"{sf_dir}/{table}.parquet").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", f"{table}.parquet").parquet(sf_dir)


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is there now; its rows, from the shared folder. A batch that is
    run again replaces its own folder, so a restart adds nothing twice."""
    spark = stream.sparkSession
    folder = f"{checkpoint_root(spark)}/stream-{uuid.uuid4().hex}"

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/rows/batch={number}")

    query = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    rows = spark.read.option("basePath", f"{folder}/rows").parquet(f"{folder}/rows")
    return rows.drop("batch") if mode == "append" else rows


def key_block_counts(events: DataFrame) -> DataFrame:
    return events.groupBy("user_id", "event_type").agg(F.count("*").alias("block_size"))


def windowed_blocks(events: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """Arrivals of each key in tumbling or sliding windows; what comes later than the watermark is dropped."""
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))
    return timed.withWatermark("ts", late).groupBy(window, "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("window_start"), "event_type", "n")


def session_blocks(events: DataFrame, gap: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))
    return timed.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("session_start"), "user_id", "n")


def distinct_arrivals(events: DataFrame, late: str = "10 minutes") -> DataFrame:
    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))
    return timed.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def interval_join(left: DataFrame, right: DataFrame, key: str, within: str = "10 minutes", late: str = "10 minutes") -> DataFrame:
    """Candidate pairs of two streams: equal key, the right one not later than ``within`` after the left."""
    side = lambda x, s: x.select(F.col("event_id").alias(f"id_{s}"), F.col(key).alias(f"key_{s}"), F.col("ts").cast("timestamp").alias(f"ts_{s}")).withWatermark(f"ts_{s}", late)
    a, b = side(left, "a"), side(right, "b")
    return a.join(b, F.expr(f"key_a = key_b AND ts_b >= ts_a AND ts_b <= ts_a + INTERVAL {within} AND id_a <> id_b")).select("id_a", "id_b")


def band_index(keys: DataFrame, most: int = 100_000) -> DataFrame:
    """Edges that arrive with records: each (band, key) keeps its members and gives one edge to the
    least member so far for each new one, so the components equal the batch's."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        least = state.get[0] if state.exists else None
        src, dst = [], []
        for pdf in frames:
            for r in pdf["rec_id"].tolist():
                if least is None:
                    least = r
                elif r != least:
                    src.append(max(r, least))
                    dst.append(min(r, least))
                    least = min(r, least)
        if least is not None:
            state.update((int(least),))
        yield pd.DataFrame({"src": src, "dst": dst}, dtype="int64")

    return keys.groupBy("band", "key").applyInPandasWithState(step, "src long, dst long", "least long", "append", GroupStateTimeout.NoTimeout)


def assign_arrivals(stream: DataFrame, blocks: DataFrame, columns: list[str]) -> DataFrame:
    """Arriving records to the fitted blocks of their key, by a join with the stored blocks."""
    return stream.join(stored(blocks), columns, "left")


def late_and_early(stream: DataFrame, sink: Callable[[DataFrame, int], None], folder: str) -> None:
    """Hands each micro-batch to ``sink``, which may count late rows beside the main path."""
    stream.writeStream.foreachBatch(sink).option("checkpointLocation", folder).trigger(availableNow=True).start().awaitTermination()
