"""Where results go."""

from __future__ import annotations

from pyspark.sql import DataFrame


def counts(df: DataFrame, path: str, sub: str) -> None:
    """A count table under its sub-template; blocked tables also by block, so that a batch of color sets is read alone."""
    by = [c for c in ("blk",) if c in df.columns]
    df.write.mode("overwrite").partitionBy(*by).parquet(f"{path}/sub={sub}")


def bucketed(df: DataFrame, name: str, buckets: int = 64, key: str = "v") -> None:
    """A table bucketed and sorted by vertex: later joins on the vertex need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def results(df: DataFrame, path: str, fmt: str = "csv") -> None:
    """Small result tables for people, as csv with a header or json."""
    df.write.mode("overwrite").option("header", True).format(fmt).save(path)


def nowhere(df: DataFrame) -> None:
    """Runs a plan for its time."""
    df.write.format("noop").mode("overwrite").save()


def view(df: DataFrame, name: str) -> None:
    df.createOrReplaceTempView(name)
