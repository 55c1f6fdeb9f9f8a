"""From raw documents to packed training sequences: five stages, each written as Parquet and read again by the next."""

from __future__ import annotations

import uuid

from treecount.llm import exactdup, minhash, packing, quality, toxicity
from treecount.llm.common import documents, labels, ready, shared_dir


def drop_toxic(spark, docs, sf_dir):
    ready(spark)
    s = toxicity.Settings()
    return toxicity.drop_toxic(docs, toxicity.fit(docs, labels(spark, sf_dir), s), s)


def keep_good(spark, docs, sf_dir):
    ready(spark)
    s = quality.Settings()
    table = quality.tables(docs, s)
    return quality.keep_good(docs, quality.fit(docs, labels(spark, sf_dir), table, s), table, s)


def drop_copies(spark, docs, sf_dir):
    ready(spark)
    return exactdup.keep_one(docs, exactdup.halves(docs))


def drop_near_copies(spark, docs, sf_dir):
    ready(spark)
    return minhash.keep_one(docs)


def pack(spark, docs, sf_dir):
    return packing.op10(spark, docs)


STAGES = [("toxicity", drop_toxic), ("quality", keep_good), ("exact_dedup", drop_copies), ("near_dedup", drop_near_copies), ("packing", pack)]

#: The first two stages apply trained models, which SQL doesn't express; tests compare the rest with brute force.
ORACLE_SQL = None


def run(spark, sf_dir):
    docs = documents(spark, sf_dir)
    folder = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.mode("overwrite").parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
