"""The registered queries of this subpackage and their SQL."""

from __future__ import annotations

from . import bpe, exactdup, minhash, packing, quality, tokencounts, tokenfile, toxicity, urlrules, vecdup
from .common import documents, labels, ready


def queries() -> dict:
    return {
        "op1_quality": lambda spark, d: quality.op1(spark, documents(spark, d), labels(spark, d)),
        "op2_toxicity": lambda spark, d: toxicity.op2(spark, documents(spark, d), labels(spark, d)),
        "op3_url_rules": lambda spark, d: urlrules.op3(spark, ready(spark).read.parquet(f"{d}/pages.parquet")),
        "op4_exact_dedup": lambda spark, d: exactdup.op4(spark, documents(spark, d)),
        "op5_token_files": lambda spark, d: tokenfile.op5(spark, documents(spark, d)),
        "op6_minhash_dedup": lambda spark, d: minhash.op6(spark, documents(spark, d)),
        "op7_token_counts": lambda spark, d: tokencounts.op7(spark, documents(spark, d)),
        "op8_bpe_round_trip": lambda spark, d: bpe.op8(spark, documents(spark, d)),
        "op9_embedding_dedup": lambda spark, d: vecdup.op9(spark, ready(spark).read.parquet(f"{d}/embeddings.parquet")),
        "op10_packing": lambda spark, d: packing.op10(spark, documents(spark, d)),
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op3_url_rules": urlrules.oracle(),
        "op4_exact_dedup": exactdup.ORACLE,
        "op6_minhash_dedup": minhash.ORACLE,
        "op9_embedding_dedup": vecdup.ORACLE,
    }
