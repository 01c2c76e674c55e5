"""Typed columns through the codec: a byte stream per column, page by page."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treepack.operators import stats
from treepack.operators.blocks import decode_blocks, encode_blocks
from treepack.sources.streams import from_blocks, to_blocks
from treepack.sources.tables import staged


def encode_columns(df: DataFrame, key: str, columns: dict[str, str], page: int = 1024) -> DataFrame:
    """Encoded blocks of fixed-width columns (name -> numpy type), a stream per column; nulls have a validity stream of their own.

    Rows are gathered into pages of neighbouring keys; (page, key) order is kept in a key stream.
    """
    rows = df.select(F.expr(f"{key} div {page}").cast("long").alias("value_id"), F.struct(F.col(key).cast("long").alias("_k"), *columns).alias("r"))
    pages = rows.groupBy("value_id").agg(F.array_sort(F.collect_list("r")).alias("rs"))
    wide = pages.select("value_id", F.transform("rs", _field("_k")).alias("_k"), *(F.transform("rs", _field(c)).alias(c) for c in columns))
    kinds = {"_k": "<i8", **columns}

    def run(batches):
        for b in batches:
            out = []
            for i, v in enumerate(b.column("value_id").to_pylist()):
                for c, kind in kinds.items():
                    cell = b.column(c)[i].values
                    valid = np.array(cell.is_valid())
                    a = np.asarray(cell.fill_null(0).to_numpy(zero_copy_only=False)).astype(kind)
                    out.append((c, v, a.tobytes()))
                    if not valid.all():
                        out.append((f"{c}/valid", v, valid.astype(np.uint8).tobytes()))
            s, v, raw = zip(*out, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(s, pa.string()), pa.array(v, pa.int64()), pa.array(raw, pa.binary())], names=["stream_id", "value_id", "raw"])

    values = staged(wide.mapInArrow(run, "stream_id string, value_id long, raw binary"))
    return encode_blocks(to_blocks(values), stats.codebooks(stats.byte_histogram(values)))


def _field(c: str):
    return lambda x: x[c]


def decode_columns(enc: DataFrame, columns: dict[str, str], types: dict[str, str]) -> DataFrame:
    """(_k, columns..) rows back from encoded columns."""
    values = from_blocks(decode_blocks(enc).select("stream_id", "value_id", "block_no", "raw"))
    names = ["_k", *columns]
    wide = values.groupBy("value_id").pivot("stream_id", [*names, *(f"{c}/valid" for c in names)]).agg(F.first("raw"))
    kinds = {"_k": "<i8", **columns}

    def run(batches):
        for b in batches:
            for i in range(b.num_rows):
                arrays = []
                for c, kind in kinds.items():
                    a = np.frombuffer(b.column(c)[i].as_py(), kind)
                    valid = b.column(f"{c}/valid")[i].as_py()
                    mask = None if valid is None else np.frombuffer(valid, np.uint8) == 0
                    arrays.append(pa.array(a, mask=mask))
                yield pa.RecordBatch.from_arrays(arrays, names=names)

    return wide.mapInArrow(run, ", ".join(["_k long", *(f"`{c}` {types[c]}" for c in columns)]))
