"""Graphs from streams of events (event_id, ts, user_id, event_type)."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def source(spark: SparkSession, folder: str, files: int = 1) -> DataFrame:
    """A stream over a folder of Parquet files of events."""
    return spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files).parquet(folder)


def window_degrees(events: DataFrame, length: str = "1 hour", slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """start, user_id, events, types of each time window; rows later than the watermark are dropped and counted by Spark's query progress."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.withWatermark("ts", late).groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("events"), F.approx_count_distinct("event_type").alias("types")).select(F.col("w.start").alias("start"), "user_id", "events", "types")


def session_counts(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("events")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "events")


def user_pairs(events: DataFrame, within: str = "5 minutes", late: str = "10 minutes") -> DataFrame:
    """Edges (src, dst, ts) between users of events of one type close in time: a stream-stream interval join."""
    a = events.select(F.col("user_id").alias("src"), F.col("event_type").alias("kind"), F.col("ts").alias("ta")).withWatermark("ta", late)
    b = events.select(F.col("user_id").alias("dst"), F.col("event_type").alias("other"), F.col("ts").alias("tb")).withWatermark("tb", late)
    near = F.expr(f"kind = other and src < dst and tb between ta - interval {within} and ta + interval {within}")
    return a.join(b, near).select("src", "dst", F.greatest("ta", "tb").alias("ts"))


def distinct_edges(pairs: DataFrame, late: str = "10 minutes") -> DataFrame:
    """Each edge once within the watermark."""
    return pairs.withWatermark("ts", late).dropDuplicatesWithinWatermark(["src", "dst"])


def running_stars(edges: DataFrame) -> DataFrame:
    """(v, degree, path3, star4) of each vertex that a batch touches, kept up to date by state: counts of its pairs and triples of neighbours.

    ``edges`` (src, dst) holds both directions and no repeats; the state is one number a vertex.
    """

    def update(key: tuple, parts, state: GroupState):
        d = state.get[0] if state.exists else 0
        d += sum(len(p) for p in parts)
        state.update((d,))
        yield pd.DataFrame({"v": [key[0]], "degree": [d], "path3": [d * (d - 1) // 2], "star4": [d * (d - 1) * (d - 2) // 6]})

    return edges.groupBy("src").applyInPandasWithState(update, "v long, degree long, path3 long, star4 long", "degree long", "update", GroupStateTimeout.NoTimeout)


def each_batch(edges: DataFrame, use: Callable[[DataFrame, int], None], checkpoint: str):
    """Hands every micro-batch of edges to ``use``, for instance to estimate on it; processes what there is and stops."""
    return edges.writeStream.foreachBatch(use).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
