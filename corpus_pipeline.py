"""Documents to tokens in five stages; each takes (spark, docs, sf_dir) and gives the next one's documents."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from pathframe.llm import decontaminate, minhash, private, quality, transducer
from pathframe.llm.common import removed, stored, table, writing


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that fail the base test or meet a learned rule go."""
    return quality.keep_good(docs, quality.learn_from(docs, table(spark, sf_dir, "labels")))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays: that of the smallest id."""
    return minhash.keep_one(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with enough words of benchmark items go."""
    return decontaminate.clean_documents(docs, table(spark, sf_dir, "benchmark"))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Spans of personal data give way to their kind; every document stays."""
    return private.redact(docs, private.fit(docs))


def bpe_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, lang, source, n_tokens, ids_sha256, decoded_sha256 and the ids themselves. The workers stay beside the
    JVM of the stages before and, idle, of the next run, so they work in smaller slices and remember less than op5's."""
    return transducer.encode_texts(docs, with_ids=True, carry=("lang", "source"), slice_bytes=1 << 20, transitions=100_000)


STAGES = [
    ("quality_rules", quality_rules),
    ("near_dedup", near_dedup),
    ("decontamination", decontamination),
    ("personal_data", personal_data),
    ("bpe_tokens", bpe_tokens),
]

#: A learned list, EM and a transducer are no SQL; tests compare with a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of the last stage over `documents`. Each stage's table is removed when the next one's is written, with the
    tables that the stage wrote on its way; what the last stage reads stays until the shared folder is cleared."""
    docs, before = table(spark, sf_dir, "documents"), []
    for name, stage in STAGES[:-1]:
        with writing() as made:
            docs = stored(stage(spark, docs, sf_dir), name)
        removed(spark, [*before, *made[:-1]])
        before = made[-1:]
    return STAGES[-1][1](spark, docs, sf_dir)
