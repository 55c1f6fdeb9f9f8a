"""Reading tables and edge files, with their columns checked."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

FORMATS = ("parquet", "orc", "csv", "json", "text")


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """Some columns of a Parquet table; the projection reaches the scan. Absent columns raise."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    missing = [c for c in columns if c not in df.columns]
    if missing:
        raise ValueError(f"{name} has no {', '.join(missing)}")
    return df.select(*columns) if columns else df


def edges(spark: SparkSession, path: str, fmt: str = "parquet", src: str = "src", dst: str = "dst") -> DataFrame:
    """Pairs (a, b) from a file of edges. "text" is white-space separated with # or % before comments, as public network
    collections have it; rows that aren't two whole numbers are dropped there."""
    if fmt not in FORMATS:
        raise ValueError(f"fmt must be one of {FORMATS}")
    if fmt == "text":
        parts = F.split(F.trim("value"), r"\s+")
        lines = spark.read.text(path).where(~F.trim("value").rlike("^[#%]"))
        return lines.select(F.try_element_at(parts, F.lit(1)).try_cast("long").alias("a"), F.try_element_at(parts, F.lit(2)).try_cast("long").alias("b")).where("a is not null and b is not null")
    reader = spark.read
    if fmt == "csv":
        reader = reader.option("header", True).schema(f"`{src}` long, `{dst}` long")
    elif fmt == "json":
        reader = reader.schema(f"`{src}` long, `{dst}` long")
    return reader.format(fmt).load(path).select(F.col(src).cast("long").alias("a"), F.col(dst).cast("long").alias("b"))
