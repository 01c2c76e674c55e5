"""One query per operator, with production parameters, over its whole table."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treepack.llm import byte_cnn, pu_quality
from treepack.llm.byte_bpe import byte_bpe_digest
from treepack.llm.common import table
from treepack.llm.exact_dedup import exact_dedup
from treepack.llm.html_text import extract_text
from treepack.llm.matroska import from_media, to_media
from treepack.llm.packing import pack_documents
from treepack.llm.pii import personal_data
from treepack.llm.simhash import simhash_dedup
from treepack.llm.suffix_dedup import suffix_dedup


def op6_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup(table(spark, sf_dir, "documents"))


def op4_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash_dedup(table(spark, sf_dir, "documents"))


def op2_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return byte_bpe_digest(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


def op1_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


def op3_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup(table(spark, sf_dir, "documents"))


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held = F.coalesce(byte_cnn.fold("doc_id", 3) == 1, F.lit(False))
    net = byte_cnn.train(docs.where(~held))
    return byte_cnn.language_id(docs, net).withColumn("held_out", held)


def op7_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    held = F.coalesce(byte_cnn.fold("doc_id", 5) == 0, F.lit(False))
    net = pu_quality.train(docs.where(~held), labels.where(~held))
    return pu_quality.quality_scores(docs, net).withColumn("held_out", held)


def op8_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_text(table(spark, sf_dir, "pages"))


def op9_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return from_media(to_media(table(spark, sf_dir, "documents")))


def op10_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return personal_data(table(spark, sf_dir, "documents"))


QUERIES = {"op10_personal_data": op10_personal_data, "op8_html_extraction": op8_html_extraction, "op9_media_columns": op9_media_columns, "op7_quality_classifier": op7_quality_classifier, "op5_language_id": op5_language_id, "op3_suffix_array_dedup": op3_suffix_array_dedup, "op1_best_fit_packing": op1_best_fit_packing, "op2_byte_bpe": op2_byte_bpe, "op4_simhash_near_dedup": op4_simhash_near_dedup, "op6_exact_dedup": op6_exact_dedup}

ORACLE_SQL = {
    "op6_exact_dedup": r"""
WITH n AS (SELECT doc_id, length(coalesce(text, '')) AS pts, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g') AS t FROM documents),
g AS (SELECT *, count(*) OVER (PARTITION BY t) AS group_size, first_value(doc_id) OVER (PARTITION BY t ORDER BY pts DESC, doc_id) AS keep_id FROM n)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, sha256(t) AS text_sha256 FROM g""",
}
