"""Tables, staged tables in the shared folder, and size-checked broadcasts."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch(spark: SparkSession) -> str:
    """A new folder under spark.checkpoint.dir; under the warehouse only where that is unset."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/treepack-shared"
    return f"{base}/treepack-{uuid.uuid4().hex}"


def staged(df: DataFrame) -> DataFrame:
    """df written once and read again: what follows never recomputes it."""
    path = scratch(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def small(df: DataFrame, rows: int = 100_000) -> DataFrame:
    """df marked for broadcast if it has no more than `rows` rows, else as it is."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def write_blocks(enc: DataFrame, path: str, mode: str = "errorifexists") -> None:
    """The block sink: a folder per stream, blocks in order, so that both prune."""
    enc.sortWithinPartitions("stream_id", "block_no").write.mode(mode).partitionBy("stream_id").parquet(path)
