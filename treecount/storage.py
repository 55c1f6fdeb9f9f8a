"""Where intermediate tables live: in the plan, in executor memory, or in the shared folder."""

from __future__ import annotations

import tempfile
import uuid
from contextlib import contextmanager

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

POLICIES = ("plan", "persist", "table")


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session. Only a local master may go without, in a temporary folder (tests)."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="treecount-shared-")
        spark.conf.set("spark.checkpoint.dir", base)
    return base.rstrip("/") + "/treecount"


def settle(df: DataFrame, policy: str = "plan", name: str = "table") -> DataFrame:
    """"plan" leaves ``df`` lazy (small inputs), "persist" keeps it in memory and on executor disks, "table" writes it to
    the shared folder and reads it back, which cuts its lineage and outlives any executor."""
    if policy == "plan":
        return df
    if policy == "persist":
        return df.persist(StorageLevel.MEMORY_AND_DISK)
    if policy != "table":
        raise ValueError(f"policy must be one of {POLICIES}")
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


@contextmanager
def brief_shuffles(spark: SparkSession):
    """Shuffle files of queries that are made and run inside go with their query, and not when the driver next cleans up."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, "false")
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.set(key, before)


def sent(df: DataFrame, row_bytes: int, most_bytes: int = 64 << 20) -> DataFrame:
    """``df`` with a broadcast hint if it is counted and found to stay below the bound; as it is otherwise, so that joins shuffle it."""
    most = most_bytes // row_bytes
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


def merged(df: DataFrame) -> DataFrame:
    """``df`` with a hint that its joins shuffle and sort. Spark goes by the bytes of files and shuffles, and counts take ten
    times as many in a hashed table, so it would send tables that a driver can't hold."""
    return df.hint("merge")
