"""Operators as pipeline stages: documents in, documents out, all columns kept.

A stage holds a row's columns in one struct while it works, so names that it
uses can't clash with theirs. Texts of any length pass whole; an empty table
stays empty.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from treepack.llm import byte_cnn, pii
from treepack.llm.common import SPACE, bounded_batches, give_back, maybe_broadcast, scratch, stage
from treepack.llm.exact_dedup import exact_dedup
from treepack.llm.simhash import similar_dedup


def keep_known_languages(docs: DataFrame) -> DataFrame:
    """Rejects texts that are null, have no letter, or are in no learnt language.

    The network learns from all labelled rows but one fold, and the score under
    which a text is rejected comes from all rows of that fold. If no row has
    a label, nothing can be rejected but texts without letters. Repeated rows
    stay.
    """
    bounded_batches(docs.sparkSession)
    net, least = byte_cnn.train_with_limit(docs)

    @F.pandas_udf("boolean")
    def known(text: pd.Series) -> pd.Series:
        out = np.zeros(len(text), bool)
        for at in range(0, len(text), 256):
            part = [None if t is None else t.encode() for t in text.iloc[at : at + 256]]
            if net:
                got = byte_cnn.predict_texts(net, part)
                out[at : at + len(part)] = [p != "und" and s >= least for p, s in got]
            else:
                out[at : at + len(part)] = [t is not None and byte_cnn.has_letter(t) for t in part]
        give_back()
        return pd.Series(out)

    return docs.where(known("text"))


def _one_of_each(docs: DataFrame, kept: DataFrame, keys: dict[str, Column]) -> DataFrame:
    """The rows of docs whose keys are in kept(keys..), one for each: of rows that agree in them the one with the longest text.

    Only rows whose keys stand on several of them are shuffled, and of those
    each task passes on one.
    """
    rows = docs.select(F.struct("*").alias("row"), *(c.alias(k) for k, c in keys.items()), F.col("text").alias("text"))
    rows = rows.join(maybe_broadcast(kept, 500_000), list(keys), "left_semi")
    repeats = rows.groupBy(*keys).agg(F.count("*").alias("n")).where("n > 1").select(*keys)
    repeats = stage(repeats, "stage-repeats")
    if repeats.isEmpty():
        return rows.select("row.*")
    several = rows.join(maybe_broadcast(repeats, 500_000), list(keys), "left_semi")
    one = several.groupBy(*keys).agg(F.max_by("row", F.struct(F.length("text"), F.xxhash64("text"))).alias("row"))
    return rows.join(maybe_broadcast(repeats, 500_000), list(keys), "left_anti").select("row.*").unionByName(one.select("row.*"))


def _id() -> Column:
    return F.coalesce(F.col("doc_id").cast("long"), F.lit(-1))


def keep_one_of_equal(docs: DataFrame) -> DataFrame:
    """Of documents that are equal without white space (null: empty), the one that exact_dedup keeps: most code points, then least id. A null id sorts last."""
    with scratch(docs.sparkSession) as keep:
        found = exact_dedup(docs).where("kept")
        kept = keep(stage(found.select(F.coalesce("doc_id", F.lit(-1)).alias("id"), F.col("text_sha256").alias("sha")).distinct(), "stage-exact"))
    bare = F.translate(F.coalesce("text", F.lit("")), SPACE.decode(), "")
    return _one_of_each(docs, kept, {"id": _id(), "sha": F.sha2(bare, 256)})


def keep_one_of_similar(docs: DataFrame, shingle: int = 5, similarity: float = 0.8) -> DataFrame:
    """Of documents in one component of links, the one with the smallest id (of rows with that id, one). Null and wordless texts are one component; a null id sorts first."""
    with scratch(docs.sparkSession) as keep:
        found = similar_dedup(docs, shingle=shingle, similarity=similarity).where("kept")
        kept = keep(stage(found.select(F.coalesce("doc_id", F.lit(-1)).alias("id"), F.col("text_key").alias("key")).distinct(), "stage-similar"))
    return _one_of_each(docs, kept, {"id": _id(), "key": F.xxhash64("text")})


def mask_personal_data(docs: DataFrame) -> DataFrame:
    """All documents, with personal data in their texts replaced by its kind; null texts stay null, repeated rows stay."""
    return pii.mask(docs)
