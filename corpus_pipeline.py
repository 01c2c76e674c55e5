"""The training-data pipeline: each stage works on all that the one before kept."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from treepack.llm import stages
from treepack.llm.common import stage, table
from treepack.llm.packing import pack_documents


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack_documents(docs, public_tokenizers.path("word_bpe_49k.json"))


Stage = Callable[[SparkSession, DataFrame, str], DataFrame]
STAGES: list[tuple[str, Stage]] = [
    ("language_id", lambda spark, docs, sf_dir: stages.keep_known_languages(docs)),
    ("exact_dedup", lambda spark, docs, sf_dir: stages.keep_one_of_equal(docs)),
    ("simhash_near_dedup", lambda spark, docs, sf_dir: stages.keep_one_of_similar(docs)),
    ("personal_data", lambda spark, docs, sf_dir: stages.mask_personal_data(docs)),
    ("packing", packing),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each result written and read again before the next."""
    docs = table(spark, sf_dir, "documents")
    for k, (name, step) in enumerate(STAGES):
        docs = step(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = stage(docs, f"pipeline-{name}")
    return docs


#: SQL can't express trained models and fingerprints; tests hold the stages against brute force.
ORACLE_SQL = None
