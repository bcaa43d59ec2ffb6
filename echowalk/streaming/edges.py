"""Graphs from event streams."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..sources.graphs import from_edges

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, path: str, files_per_trigger: int | None = None) -> DataFrame:
    reader = spark.readStream.schema(EVENTS)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(path)


def fresh(stream: DataFrame, delay: str = "1 hour", key: str = "event_id") -> DataFrame:
    """Late rows (behind the watermark) and repeats of ``key`` within it go."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark([key])


def windowed_counts(stream: DataFrame, kind: str = "tumbling", size: str = "1 hour", slide: str = "15 minutes", gap: str = "30 minutes", by: str = "user_id") -> DataFrame:
    """window_start, window_end, ``by``, n for tumbling, sliding or session windows of a stream that has
    a watermark."""
    w = {"tumbling": lambda: F.window("ts", size), "sliding": lambda: F.window("ts", size, slide), "session": lambda: F.session_window("ts", gap)}[kind]()
    return stream.groupBy(w.alias("w"), F.col(by)).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("window_start"), F.col("w.end").alias("window_end"), by, "n")


def transitions(stream: DataFrame, key: str = "event_type") -> DataFrame:
    """key, src, dst, ts: each event's user after the last one before it with the same key (state: one
    user for each key). Events are taken in the order of time within a trigger."""

    def step(k: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        last = state.get[0] if state.exists else None
        out = []
        for user, ts in zip(rows["user_id"], rows["ts"]):
            if last is not None and last != user:
                out.append((k[0], int(last), int(user), ts))
            last = int(user)
        state.update((last,))
        yield pd.DataFrame(out, columns=["key", "src", "dst", "ts"])

    rows = stream.select(F.col(key).alias("key"), "event_id", "ts", "user_id")
    return rows.groupBy("key").applyInPandasWithState(step, "key string, src long, dst long, ts timestamp", "last long", "append", GroupStateTimeout.NoTimeout)


def with_attributes(stream: DataFrame, static: DataFrame, key: str) -> DataFrame:
    return stream.join(static, key, "left")


def rolling_scores(edges: DataFrame, score: Callable[[DataFrame], DataFrame], sink: Callable[[DataFrame, int], None], store: str):
    """Starts a query that adds each trigger's edges to Parquet at ``store`` and gives
    ``score`` of the graph so far to ``sink``. A trigger that runs again replaces what it wrote."""

    def trigger(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        batch.select("src", "dst").write.mode("overwrite").parquet(f"{store}/trigger={number}")
        so_far = spark.read.parquet(store).select("src", "dst")
        sink(score(from_edges(so_far)), number)

    return edges.writeStream.foreachBatch(trigger)
