"""What the operators of this subpackage share: shared storage, column hygiene, byte access to Arrow text."""

from __future__ import annotations

import os
import tempfile
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: ``spark.checkpoint.dir``. Only a local master may go without, in a temporary folder (tests)."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="treecount-shared-")
        spark.conf.set("spark.checkpoint.dir", base)
    return base.rstrip("/") + "/treecount"


def commit(df: DataFrame, name: str, partition_by: str | None = None) -> DataFrame:
    """Writes ``df`` as a table in the shared folder and reads it back: lineage ends there, lost executors cost nothing."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    writer = df.write.mode("overwrite")
    if partition_by:
        writer = writer.partitionBy(partition_by)
    writer.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.committed_at = path
    return out


def discard(*tables: DataFrame) -> None:
    """Deletes tables that :func:`commit` made; nothing may read them afterwards."""
    for df in tables:
        spark = df.sparkSession
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(df.committed_at)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def ready(spark: SparkSession) -> SparkSession:
    """Lets Python workers import this package when only the driver has it on its path."""
    env = spark.sparkContext.environment
    paths = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if ROOT not in paths:
        env["PYTHONPATH"] = os.pathsep.join([ROOT, *paths])
    return spark


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ready(spark).read.parquet(f"{sf_dir}/documents.parquet")


def labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ready(spark).read.parquet(f"{sf_dir}/labels.parquet")


def keep_rows(docs: DataFrame, score, below: float | None = None, at_least: float | None = None) -> DataFrame:
    """The rows of ``docs``, all columns, whose score lies in the range. ``score`` gets texts as bytes and gives an array."""

    def run(batches):
        for batch in batches:
            for some in slices(batch, "text", 1 << 20):
                v = score(raw_bytes(some.column(some.schema.get_field_index("text"))))
                keep = np.ones(len(v), bool)
                if below is not None:
                    keep &= v < below
                if at_least is not None:
                    keep &= v >= at_least
                yield some.filter(pa.array(keep))

    return docs.mapInArrow(run, docs.schema)


def lower_az(text: Column) -> Column:
    """Lower-cases A-Z and nothing else."""
    return F.translate(text, UPPER, LOWER)


def held_out(doc_id: Column) -> Column:
    """True for rows whose labels no model may learn from: crc32 of the id as text, mod 5, is 0. Null ids: false."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % 5 == 0, F.lit(False))


def raw_bytes(column: pa.Array | pa.ChunkedArray) -> list[bytes]:
    """The UTF-8 bytes of a text column; null becomes empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    kind = pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()
    if column.null_count:
        column = column.fill_null("")
    return column.cast(kind).to_pylist()


def slices(batch: pa.RecordBatch, text: str, most_bytes: int = 4 << 20):
    """Cuts a batch where the text in it exceeds ``most_bytes``, so that memory follows bytes and not rows."""
    column = batch.column(batch.schema.get_field_index(text))
    sizes = np.asarray(pc.fill_null(pc.binary_length(column), 0), dtype=np.int64)
    group = np.cumsum(sizes) // most_bytes
    cuts = [0, *(np.flatnonzero(np.diff(group)) + 1).tolist(), len(sizes)]
    for a, b in zip(cuts, cuts[1:], strict=False):
        if b > a:
            yield batch.slice(a, b - a)
