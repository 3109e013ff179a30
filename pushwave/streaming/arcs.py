"""Arcs from a stream of events (an addition: the methods themselves take a static graph).

Successive users of an ordered stream become arcs. Plans work on any streaming DataFrame with the
columns of events; run() drains what is there and returns the written table.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from pushwave.plans.durable import new_folder

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
LATE = "1 hour"


def source(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    """The events table as a file stream."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(f"{sf_dir}/event[s].parquet")


def run(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Process all that is available, with a checkpoint in the shared folder; the result as a table."""
    spark = stream.sparkSession
    out, state = new_folder(spark, "stream"), new_folder(spark, "stream-state")
    stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", state).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def run_batches(stream: DataFrame, each: Callable[[DataFrame, int], None]) -> None:
    """Hand every micro-batch to a function, e.g. to refresh the answers of changed sources."""
    stream.writeStream.foreachBatch(each).option("checkpointLocation", new_folder(stream.sparkSession, "stream-state")).trigger(availableNow=True).start().awaitTermination()


def daily_counts(events: DataFrame) -> DataFrame:
    """Events of each user and day, final once the watermark has passed the day."""
    w = events.withWatermark("ts", LATE).groupBy(F.window("ts", "1 day"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return w.select(F.col("window.start").alias("day"), "user_id", "n")


def sliding_counts(events: DataFrame) -> DataFrame:
    w = events.withWatermark("ts", LATE).groupBy(F.window("ts", "1 day", "6 hours")).agg(F.count(F.lit(1)).alias("n"))
    return w.select(F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Sessions of each user: begin, end and number of events."""
    w = events.withWatermark("ts", LATE).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return w.select("user_id", F.col("session_window.start").alias("begin"), F.col("session_window.end").alias("finish"), "n")


def distinct_pairs(events: DataFrame) -> DataFrame:
    """(user_id, event_type) once within the watermark."""
    return events.withWatermark("ts", "60 days").select("user_id", "event_type", "ts").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")


def with_answers(events: DataFrame, answers: DataFrame) -> DataFrame:
    """Stream-static join: events of users that a stored answer (v, score) knows."""
    return events.join(answers.select(F.col("v").alias("user_id"), "score"), "user_id").select("event_id", "user_id", "score")


def click_then_purchase(events: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: a user's click and a later purchase within a time."""
    a = events.filter("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", F.col("ts").alias("t")).withWatermark("t", LATE)
    b = events.filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("u"), F.col("ts").alias("s")).withWatermark("s", LATE)
    return a.join(b, F.expr(f"user_id = u and s >= t and s <= t + interval {within}")).select("click", "purchase", "user_id")


def successive_types(events: DataFrame) -> DataFrame:
    """Arcs (user_id, src, dst) between a user's successive event types; the state is one type a user."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last = state.get[0] if state.exists else None
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        kinds = ([last] if last is not None else []) + rows["event_type"].tolist()
        state.update((kinds[-1],))
        yield pd.DataFrame({"user_id": [key[0]] * (len(kinds) - 1), "src": kinds[:-1], "dst": kinds[1:]})

    return events.groupBy("user_id").applyInPandasWithState(step, "user_id long, src string, dst string", "last string", "append", GroupStateTimeout.NoTimeout)
