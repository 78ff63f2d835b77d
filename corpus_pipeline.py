"""A corpus pipeline of five stages over ``documents``: each stage works on all that its predecessor kept.

Toxic documents go; of near-duplicates the first document stays; passages that an earlier document holds are cut; live secrets
are replaced; what is left is packed into token sequences. All stages but the last return the columns of ``documents``.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from couponspark.llm.common import mark, stage, sweep
from couponspark.llm.packing import pack_documents
from couponspark.llm.secret_scan import remove_live
from couponspark.llm.set_join import drop_near_duplicates
from couponspark.llm.suffix_dedup import suffix_dedup
from couponspark.llm.toxicity import fit, keep_clean


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the recurrent scorer, trained on the labels, does not predict to be toxic."""
    return keep_clean(docs, fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates."""
    return drop_near_duplicates(docs)


def cut_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the passages of 50 bytes or more that a document with a smaller id holds."""
    return suffix_dedup(docs, mode="text")


def hide_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts with live secrets replaced. Owners are counted in all of ``documents``: earlier stages drop the copies that tell an
    example from a secret."""
    return remove_live(docs, corpus=spark.read.parquet(f"{sf_dir}/documents.parquet"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of token sequences of 4096."""
    return pack_documents(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [("toxicity", drop_toxic), ("minhash_near_dedup", drop_copies), ("suffix_array_dedup", cut_passages), ("secret_scan", hide_secrets), ("packing", pack)]

ORACLE_SQL = None  # a trained network and sequence packing are not SQL; tests compare with a brute-force version


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Apply all stages to ``documents``; each result is written and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    since = mark()
    for i, (name, step) in enumerate(STAGES):
        docs = step(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = stage(docs, f"pipeline-{name}")
            sweep(spark, since, docs)
    return docs
