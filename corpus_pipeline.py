"""From raw documents to packed sequences: quality rules, near copies, leaked benchmarks, personal data, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tracegraph.llm.common import materialise, table
from tracegraph.llm.decontamination import clean
from tracegraph.llm.packing_nnls import pack
from tracegraph.llm.pii_disclosure import sanitise
from tracegraph.llm.quality_mcd import keep_quality
from tracegraph.llm.token_groups import keep_one

#: Vocabulary file and window of the packed sequences.
TOKENIZER, WINDOW = "byte_bpe_50k.json", 2048


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return keep_quality(docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return keep_one(docs, words=5, percent=80)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return clean(docs, table(spark, sf_dir, "benchmark"))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return sanitise(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack(docs, public_tokenizers.path(TOKENIZER), WINDOW)


STAGES = [
    ("quality_mcd", quality),
    ("token_group_join", near_copies),
    ("decontamination", decontaminate),
    ("pii_disclosure", personal_data),
    ("nnls_packing", packing),
]

#: The stages estimate, cluster and tokenise: SQL can't express them; tests hold them against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
