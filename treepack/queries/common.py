"""What several areas' queries share."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treepack.operators import stats
from treepack.operators.blocks import decode_blocks, encode_blocks
from treepack.plans.selective import Gates
from treepack.sources.streams import build_streams, from_blocks, to_blocks


def hist_of(spark: SparkSession, d: str, names) -> DataFrame:
    return stats.byte_histogram(build_streams(spark, d, names))


def books_of(spark: SparkSession, d: str, names, **how) -> DataFrame:
    return stats.codebooks(hist_of(spark, d, names), **how)


def codes_of(books: DataFrame) -> DataFrame:
    return stats.canonical_codes(stats.code_lengths(books))


def encoded(spark: SparkSession, d: str, names, *, shape: str = "flat_opt", gates: Gates | None = None, block_size: int = 8192, with_hist: bool = False, **how) -> DataFrame:
    values = build_streams(spark, d, names)
    hist = stats.byte_histogram(values)
    return encode_blocks(to_blocks(values, block_size), stats.codebooks(hist), shape=shape, gates=gates, hist=hist if with_hist else None, **how)


def digests(decoded: DataFrame) -> DataFrame:
    """(stream_id, value_id, n_bytes, digest) of values put together from decoded blocks."""
    return from_blocks(decoded.select("stream_id", "value_id", "block_no", "raw")).select("stream_id", "value_id", F.octet_length("raw").cast("long").alias("n_bytes"), F.md5("raw").alias("digest"))


def roundtrip(spark: SparkSession, d: str, names, *, decoder: str = "bottomup", shape: str = "flat_opt", gates: Gates | None = None, block_size: int = 8192, with_hist: bool = False, **how) -> DataFrame:
    enc = encoded(spark, d, names, shape=shape, gates=gates, block_size=block_size, with_hist=with_hist)
    return digests(decode_blocks(enc, shape=shape, decoder=decoder, gates=gates, **how))


def sizes(enc: DataFrame) -> DataFrame:
    """(stream_id, raw_bytes, enc_bytes, ratio): the length table of each codebook counts too."""
    per_book = enc.groupBy("stream_id", "codebook_id").agg(F.sum("n").cast("long").alias("raw"), F.sum(F.octet_length("payload")).cast("long").alias("enc"))
    total = per_book.groupBy("stream_id").agg(F.sum("raw").alias("raw_bytes"), (F.sum("enc") + F.lit(128) * F.count("*")).alias("enc_bytes"))
    return total.withColumn("ratio", F.round(F.col("raw_bytes") / F.col("enc_bytes"), 6))
