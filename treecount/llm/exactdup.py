"""Exact deduplication against immutable snapshots, screened by static filters."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .binfuse import BinaryFuse
from .common import commit, discard, lower_az, ready

KEYS_PER_FILTER = 250_000


def digests(docs: DataFrame, snapshot: str) -> DataFrame:
    """doc_id, snapshot (null: the incoming batch) and text_sha256 of each row; null text counts as empty."""
    text = lower_az(F.coalesce(F.col("text").cast("string"), F.lit("")))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.expr(snapshot).cast("int").alias("snapshot"), F.sha2(text, 256).alias("text_sha256"))


def build_filters(stored: DataFrame, shards: int) -> DataFrame:
    """One filter for each snapshot and shard of the digest space: (snapshot, shards, shard, filter)."""

    def build(key: tuple, part: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"snapshot": [key[0]], "shards": [shards], "shard": [key[1]], "filter": [BinaryFuse.build(part["key"].to_numpy()).to_bytes()]})

    return sharded(stored, shards).select("snapshot", "shard", "key").groupBy("snapshot", "shard").applyInPandas(build, "snapshot int, shards int, shard int, filter binary")


def sharded(rows: DataFrame, shards: int) -> DataFrame:
    key = F.xxhash64("text_sha256")
    return rows.withColumn("key", key).withColumn("shard", F.pmod(F.shiftright(key, 20), F.lit(shards)).cast("int"))


def screen(incoming: DataFrame, filters: DataFrame, shards: int) -> DataFrame:
    """The digests (distinct, with their other columns dropped) that some snapshot's filter may hold."""

    def probe(_: tuple, part: pd.DataFrame, found: pd.DataFrame) -> pd.DataFrame:
        hit, keys = np.zeros(len(part), bool), part["key"].to_numpy(np.int64)
        for raw in found["filter"]:
            hit |= BinaryFuse.from_bytes(raw).contains(keys)
        return pd.DataFrame({"text_sha256": part["text_sha256"][hit]})

    return sharded(incoming.select("text_sha256"), shards).groupBy("shard").cogroup(filters.select("shard", "filter").groupBy("shard")).applyInPandas(probe, "text_sha256 string")


def snapshot_filters(docs: DataFrame, snapshot: str) -> DataFrame:
    """The filters of the snapshots in ``docs``, to be written beside them and given to :func:`dedup` from then on."""
    stored = digests(docs, snapshot).where("snapshot is not null").select("text_sha256", "snapshot").distinct()
    return build_filters(stored, shards_for(stored))


def shards_for(rows: DataFrame) -> int:
    return max(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-rows.count() // KEYS_PER_FILTER))


def dedup(docs: DataFrame, snapshot: str, filters: DataFrame | None = None) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256.

    snapshot is an SQL expression over ``docs``: the number of the immutable snapshot that a row is
    stored in, or null for the incoming batch. filters are those of :func:`snapshot_filters` for snapshots that have them;
    only others are built. Digests of the batch are grouped among themselves
    first, so a filter sees each once; those that a filter may hold meet the exact store by digest,
    and the texts behind both are compared byte by byte. A batch group whose bytes differ from the
    stored text of the same digest stays a group of its own.

    Texts are equal when identical after lower-casing A-Z. Of equal texts the largest doc_id stays;
    null ids rank below all others. A row that repeats both id and text is kept as often as it
    occurs. An empty table gives no rows.
    """
    rows = commit(digests(docs, snapshot), "digests")
    grouped = commit(rows.groupBy("text_sha256", "snapshot").agg(F.max("doc_id").alias("top"), F.count("*").alias("n")), "digest-groups")
    stored, incoming = grouped.where("snapshot is not null"), grouped.where("snapshot is null")
    kept = filters.select("snapshot", "shards").distinct().limit(1).first() if filters is not None else None
    shards = kept.shards if kept else shards_for(grouped)
    if kept:
        filters = filters.union(build_filters(stored.join(filters.select("snapshot").distinct(), "snapshot", "left_anti"), shards))
    else:
        filters = build_filters(stored, shards)
    filters = commit(filters, "filters")
    positive = screen(incoming, filters, shards)
    store = stored.groupBy("text_sha256").agg(F.max("top").alias("top"), F.sum("n").alias("n"))
    matched = commit(incoming.join(positive, "text_sha256", "left_semi").select("text_sha256", F.col("top").alias("new")).join(store.select("text_sha256", F.col("top").alias("old")), "text_sha256"), "matches")
    differing = commit(compare(docs, matched), "differing")
    odd = F.lit(0)
    batch, members = incoming.select("text_sha256", "top", "n"), rows
    if differing.limit(1).count():
        flag = differing.select("text_sha256", F.lit(1).alias("odd"))
        batch, members, odd = batch.join(flag, "text_sha256", "left"), rows.join(flag, "text_sha256", "left"), F.coalesce("odd", F.lit(0))
    whole = store.select("text_sha256", F.lit(0).alias("own"), "top", "n").union(batch.select("text_sha256", odd.alias("own"), "top", "n"))
    groups = commit(whole.groupBy("text_sha256", "own").agg(F.max("top").alias("keep_id"), F.sum("n").cast("long").alias("group_size")), "groups")
    discard(grouped, filters, matched)
    members = members.withColumn("own", F.when(F.col("snapshot").isNull(), odd).otherwise(F.lit(0)))
    out = members.join(groups, ["text_sha256", "own"])
    return out.select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256")


def compare(docs: DataFrame, matched: DataFrame) -> DataFrame:
    """Digests of ``matched`` (text_sha256, new, old) for which the texts of documents new and old differ in some byte."""
    wanted = matched.select("text_sha256", F.explode(F.array("new", "old")).alias("doc_id")).distinct()
    # One plan at every size: sent to all tasks, the ids would have to be bounded.
    wanted = wanted.hint("merge")
    text = lower_az(F.coalesce(F.col("text").cast("string"), F.lit("")))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text")).join(wanted, "doc_id").select("text_sha256", text.alias("text"))
    # Ids may repeat with other texts: only those that the digest stands for count.
    texts = texts.where(F.sha2("text", 256) == F.col("text_sha256"))
    return texts.groupBy("text_sha256").agg(F.min("text").alias("a"), F.max("text").alias("b")).where("a <> b").select("text_sha256")


def keep_one(docs: DataFrame, snapshot: str) -> DataFrame:
    """The documents, with all their columns, that stay; of rows that repeat id and text one stays."""
    kept = dedup(docs, snapshot).where("kept").select(F.col("doc_id").alias("kept_id"), F.col("text_sha256").alias("kept_sha"))
    kept = commit(kept.groupBy("kept_id", "kept_sha").agg(F.count("*").alias("rows")), "kept")
    sha = F.sha2(lower_az(F.coalesce(docs["text"].cast("string"), F.lit(""))), 256)
    out = docs.join(kept.select("kept_id", "kept_sha"), docs["doc_id"].cast("long").eqNullSafe(F.col("kept_id")) & (sha == F.col("kept_sha")), "left_semi")
    return out.dropDuplicates(["doc_id", "text"]) if kept.where("rows > 1").limit(1).count() else out


def halves(docs: DataFrame) -> str:
    """Rows up to the first and second quartile of doc_id are snapshots 0 and 1, all later ones the incoming batch."""
    q = docs.agg(F.percentile_approx(F.col("doc_id").cast("long"), [0.25, 0.5], 1000).alias("q")).first().q
    return f"case when doc_id <= {q[0]} then 0 when doc_id <= {q[1]} then 1 end" if q else "null"


def op4(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """Every document, against the snapshots of :func:`halves`; see :func:`dedup`."""
    ready(spark)
    return dedup(docs, halves(docs))


ORACLE = """
with d as (select doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) as text_sha256 from documents),
g as (select text_sha256, max(doc_id) as keep_id, count(*)::bigint as group_size from d group by 1)
select doc_id, keep_id, group_size, doc_id is not distinct from keep_id as kept, text_sha256 from d join g using (text_sha256)"""
