"""Accuracy and cost measures, as DataFrames over estimates, timings and Spark's own event logs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def relative_error(a: DataFrame, b: DataFrame, on: list[str], value: str) -> DataFrame:
    """on, rel_error: |a - b| / |b| cell by cell; a cell that only one side has counts as 0 on the other."""
    x, y = a.select(*on, F.col(value).cast("double").alias("x")), b.select(*on, F.col(value).cast("double").alias("y"))
    both = x.join(y, on, "full_outer").select(*on, F.coalesce("x", F.lit(0.0)).alias("x"), F.coalesce("y", F.lit(0.0)).alias("y"))
    return both.select(*on, F.when(F.col("x") == F.col("y"), 0.0).otherwise(F.try_divide(F.abs(F.col("x") - F.col("y")), F.abs("y"))).alias("rel_error"))


def estimate_error(estimates: DataFrame, exact: float) -> DataFrame:
    """it, rel_error of each estimate; with exact as 0 that of another estimate than 0 is null."""
    if not exact:
        return estimates.select("it", F.when(F.col("estimate") == 0, 0.0).alias("rel_error"))
    return estimates.select("it", (F.abs(F.col("estimate") - exact) / exact).alias("rel_error"))


def failure_rate(estimates: DataFrame, exact: float, eps: float) -> DataFrame:
    """runs and the share of them with an error above eps: the empirical delta."""
    return estimate_error(estimates, exact).agg(F.count("*").alias("runs"), F.avg((F.col("rel_error") > eps).cast("double")).alias("failure_rate"))


def speedup(timings: DataFrame, base: str = "v0") -> DataFrame:
    """graph, template, variant, speedup: the base variant's seconds over each variant's; null where the base has none."""
    b = timings.where(F.col("variant") == base).groupBy("graph", "template").agg(F.min("seconds").alias("base"))
    return timings.groupBy("graph", "template", "variant").agg(F.min("seconds").alias("seconds")).join(b, ["graph", "template"], "left").select("graph", "template", "variant", (F.col("base") / F.col("seconds")).alias("speedup"))


def pivoted(timings: DataFrame, variants: list[str]) -> DataFrame:
    """graph, template and the best seconds of each variant side by side."""
    return timings.groupBy("graph", "template").pivot("variant", variants).agg(F.min("seconds"))


def task_metrics(spark: SparkSession, event_log: str) -> DataFrame:
    """One row per finished task of an event log (spark.eventLog.enabled): stage, run_s, cpu_s, gc_s, read, shuffle and spill bytes, records."""
    m = "struct<`Executor Run Time`: long, `Executor CPU Time`: long, `JVM GC Time`: long, `Disk Bytes Spilled`: long, `Input Metrics`: struct<`Bytes Read`: long>, `Shuffle Read Metrics`: struct<`Remote Bytes Read`: long, `Local Bytes Read`: long, `Total Records Read`: long>, `Shuffle Write Metrics`: struct<`Shuffle Bytes Written`: long>>"
    raw = spark.read.schema(f"Event string, `Stage ID` int, `Task Info` struct<`Launch Time`: long, `Finish Time`: long>, `Task Metrics` {m}").json(event_log)
    t = F.col("Task Metrics")
    read = t["Shuffle Read Metrics"]
    return raw.where("Event = 'SparkListenerTaskEnd'").select(
        F.col("Stage ID").alias("stage"), (t["Executor Run Time"] / 1e3).alias("run_s"), (t["Executor CPU Time"] / 1e9).alias("cpu_s"), (t["JVM GC Time"] / 1e3).alias("gc_s"), t["Input Metrics"]["Bytes Read"].alias("input_bytes"),
        (read["Remote Bytes Read"] + read["Local Bytes Read"]).alias("shuffle_read"), t["Shuffle Write Metrics"]["Shuffle Bytes Written"].alias("shuffle_written"), t["Disk Bytes Spilled"].alias("spilled"), read["Total Records Read"].alias("records"),
        F.col("Task Info.Launch Time").alias("launched_ms"), F.col("Task Info.Finish Time").alias("finished_ms"),
    )


def utilisation(tasks: DataFrame, cores: int) -> DataFrame:
    """active_cores: task time over wall time and cores; bytes_per_s over all bytes moved; imbalance: longest over median task by stage, the worst of all."""
    wall = (F.max("finished_ms") - F.min("launched_ms")) / 1e3
    moved = F.sum(F.col("input_bytes") + F.col("shuffle_read") + F.col("shuffle_written"))
    per_stage = tasks.groupBy("stage").agg((F.max("run_s") / F.greatest(F.expr("percentile(run_s, 0.5)"), F.lit(1e-3))).alias("skew")).agg(F.max("skew").alias("imbalance"))
    return tasks.agg((F.sum("run_s") / wall / cores).alias("active_cores"), (moved / wall).alias("bytes_per_s"), moved.alias("bytes"), wall.alias("wall_s")).crossJoin(per_stage)


def roofline(timings: DataFrame, peak_flops: float, peak_bytes: float) -> DataFrame:
    """intensity (operations per byte), throughput (operations per second), roof and share of the roof; timings need flops, bytes, seconds."""
    i, p = F.col("flops") / F.col("bytes"), F.col("flops") / F.col("seconds")
    roof = F.least(F.lit(peak_flops), i * peak_bytes)
    return timings.select("*", i.alias("intensity"), p.alias("throughput"), roof.alias("roof"), (p / roof).alias("share"))


def partition_balance(df: DataFrame) -> DataFrame:
    """partitions, and rows of the largest over rows of the mean one."""
    per = df.groupBy(F.spark_partition_id().alias("p")).count()
    return per.agg(F.count("*").alias("partitions"), (F.max("count") / F.avg("count")).alias("imbalance"))
