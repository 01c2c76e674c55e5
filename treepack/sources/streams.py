"""Byte streams from table columns.

A stream is values (stream_id, value_id, raw). A text is a value; narrow columns
are gathered into pages of neighbouring keys, so a page never depends on the
order or number of partitions. Values are cut into blocks where they are.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from treepack.operators.codec import BLOCK_SIZE, check_block_size
from treepack.sources.tables import load

PAGE = 1024  # rows of a page of 8-byte values: one block


def values(df: DataFrame, stream: str, key: Column | str, raw: Column) -> DataFrame:
    return df.select(F.lit(stream).alias("stream_id"), (F.col(key) if isinstance(key, str) else key).cast("long").alias("value_id"), raw.cast("binary").alias("raw"))


def paged(df: DataFrame, stream: str, page: Column, order: list[str], value: Column, dtype: str, *, delta: bool = False, clip: int | None = None, header: bytes = b"") -> DataFrame:
    """Values of the rows of a page, in order, as little-endian numbers of dtype. delta: gaps to the row before, first 0."""
    rows = df.select(page.cast("long").alias("value_id"), F.struct(*order, value.alias("_v")).alias("r"))
    arrays = rows.groupBy("value_id").agg(F.array_sort(F.collect_list("r")).alias("rs")).select("value_id", F.transform("rs", lambda x: x["_v"]).alias("v"))

    def run(batches):
        for b in batches:
            raws = []
            for v in b.column("v"):
                a = v.values.to_numpy(zero_copy_only=False)
                if delta:
                    a = np.diff(a, prepend=a[:1])
                if clip is not None:
                    a = np.clip(a, 0, clip)
                raws.append(header + a.astype(dtype).tobytes())
            yield pa.RecordBatch.from_arrays([pa.array([stream] * b.num_rows, pa.string()), b.column("value_id"), pa.array(raws, pa.binary())], names=["stream_id", "value_id", "raw"])

    return arrays.mapInArrow(run, "stream_id string, value_id long, raw binary")


def joined(df: DataFrame, stream: str, page: Column, order: list[str], text: Column) -> DataFrame:
    """Texts of the rows of a page joined by newlines."""
    rows = df.select(page.cast("long").alias("p"), F.struct(*order, text.alias("_t")).alias("r"))
    pages = rows.groupBy("p").agg(F.array_sort(F.collect_list("r")).alias("rs"))
    return values(pages, stream, "p", F.array_join(F.transform("rs", lambda x: x["_t"]), "\n"))


def _docs(lang: str) -> Callable:
    return lambda spark, d: values(load(spark, d, "documents").where(F.col("lang") == lang), f"doc_{lang}", "doc_id", F.col("text"))


def _letters(spark, d):
    text = F.regexp_replace(F.lower("text"), "[^a-z .,\n]", "")
    return values(load(spark, d, "documents").where("lang = 'en'"), "letters", "doc_id", text)


def _geom(spark, d):
    """2**20 symbols of which each next one is a fifth as frequent."""
    u = (F.expr("(id * 2654435761) % 4294967296") / 4294967296.0).alias("u")
    rows = spark.range(1 << 20).select("id", u).select("id", F.least(F.lit(5), F.floor(F.ln(1 - F.col("u")) / F.ln(F.lit(0.2)))).cast("int").alias("s"))
    return paged(rows, "geom80", F.expr("id div 8192"), ["id"], F.col("s"), "u1")


def _userid(spark, d):
    return paged(load(spark, d, "events"), "userid_le8", F.expr(f"event_id div {PAGE}"), ["event_id"], F.col("user_id"), "<i8")


def _custkey_gaps(spark, d):
    return paged(load(spark, d, "orders"), "mixskew", F.expr(f"1000000000 + o_custkey div 200"), ["o_custkey", "o_orderkey"], F.col("o_custkey"), "<u4", delta=True)


_LINE = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"]


def _line(stream: str, value: str, dtype: str, **how) -> Callable:
    return lambda spark, d: paged(load(spark, d, "lineitem"), stream, F.expr("l_orderkey div 1024"), _LINE, F.expr(value), dtype, **how)


def _acgt(spark, d):
    base = F.ascii(F.expr("substring('ACGT', cast(l_suppkey % 4 as int) + 1, 1)"))
    plain = paged(load(spark, d, "lineitem"), "acgt", F.expr("l_orderkey div 2048"), _LINE, base, "u1")

    def wrap(batches):
        for b in batches:
            raws = []
            for r, k in zip(b.column("raw").to_pylist(), b.column("value_id").to_pylist(), strict=True):
                raws.append((b">page %d synthetic\n" % k) + b"\n".join(r[i : i + 70] for i in range(0, len(r), 70)) + b"\n")
            yield pa.RecordBatch.from_arrays([b.column("stream_id"), b.column("value_id"), pa.array(raws, pa.binary())], names=b.schema.names)

    return plain.mapInArrow(wrap, plain.schema)


def _embeddings(spark, d):
    rows = load(spark, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("k", "x"))
    return paged(rows, "emb_f4", F.expr("vec_id div 32"), ["vec_id", "k"], F.col("x"), "<f4")


def _conversations(spark, d):
    c = load(spark, d, "conversations")
    return joined(c, "convjson", F.expr("conv_id div 8"), ["conv_id", "turn", "role", "text"], F.to_json(F.struct(*c.columns)))


def _evjson(spark, d):
    e = load(spark, d, "events")
    return joined(e, "evjson", F.expr("event_id div 64"), ["event_id"], F.to_json(F.struct(*e.columns)))


STREAMS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "geom80": _geom,
    "okdelta": lambda spark, d: paged(load(spark, d, "lineitem"), "okdelta", F.expr("l_orderkey div 2048"), _LINE, F.col("l_orderkey"), "u1", delta=True, clip=255),
    "userid_le8": _userid,
    "acgt": _acgt,
    "letters": _letters,
    "doc_en": _docs("en"), "doc_de": _docs("de"), "doc_fr": _docs("fr"), "doc_es": _docs("es"),
    "html": lambda spark, d: values(load(spark, d, "pages"), "html", "page_id", F.col("html")),
    "evjson": _evjson,
    "convjson": _conversations,
    "props": lambda spark, d: joined(load(spark, d, "events"), "props", F.expr(f"event_id div {PAGE}"), ["event_id"], F.col("props")),
    "emb_f4": _embeddings,
    "mixskew": lambda spark, d: _userid(spark, d).withColumn("stream_id", F.lit("mixskew")).unionByName(_custkey_gaps(spark, d)),
    "ok_le8": _line("ok_le8", "l_orderkey", "<i8"),
    "lq_f8": _line("lq_f8", "l_quantity", "<f8"),
    "linenumber_i4": _line("linenumber_i4", "l_linenumber", "<i4"),
    "disc100": _line("disc100", "cast(round(l_discount * 100) as int)", "u1"),
    "tsdelta8": lambda spark, d: paged(load(spark, d, "events"), "tsdelta8", F.expr(f"event_id div {PAGE}"), ["event_id"], F.unix_micros(F.col("ts").cast("timestamp")), "<i8", delta=True),
}
TEXT_STREAMS = ("doc_en", "doc_de", "doc_fr", "doc_es", "html")


def build_stream(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(stream_id, value_id, raw) of a named stream; null values are left out."""
    if name not in STREAMS:
        raise ValueError(f"unknown stream {name!r}; one of {', '.join(STREAMS)}")
    return STREAMS[name](spark, sf_dir).where(F.col("raw").isNotNull())


def build_streams(spark: SparkSession, sf_dir: str, names) -> DataFrame:
    first, *rest = [build_stream(spark, sf_dir, n) for n in names]
    for r in rest:
        first = first.unionByName(r)
    return first


def to_blocks(stream: DataFrame, block_size: int = BLOCK_SIZE) -> DataFrame:
    """(stream_id, value_id, block_no, n, raw): each value cut into blocks, by a map over values alone. An empty value has one empty block."""
    check_block_size(block_size)

    def run(batches):
        for b in batches:
            rows = [
                (s, v, k, raw[at : at + block_size])
                for s, v, raw in zip(b.column("stream_id").to_pylist(), b.column("value_id").to_pylist(), b.column("raw").to_pylist(), strict=True)
                for k, at in enumerate(range(0, max(1, len(raw)), block_size))
            ]
            for at in range(0, len(rows), 1024):
                s, v, k, raw = zip(*rows[at : at + 1024], strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(s, pa.string()), pa.array(v, pa.int64()), pa.array(k, pa.int64()), pa.array(map(len, raw), pa.int32()), pa.array(raw, pa.binary())], names=["stream_id", "value_id", "block_no", "n", "raw"])

    return stream.mapInArrow(run, "stream_id string, value_id long, block_no long, n int, raw binary")


def from_blocks(blocks: DataFrame) -> DataFrame:
    """Values back from their blocks; only values of several blocks are more than one row to gather."""
    return blocks.groupBy("stream_id", "value_id").agg(F.array_sort(F.collect_list(F.struct("block_no", "raw"))).alias("b")).select("stream_id", "value_id", F.expr("aggregate(b, X'', (a, x) -> concat(a, x.raw))").alias("raw"))
