"""The codec as SQL functions: Arrow-batched scalar functions, a grouped aggregate, table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from treepack.operators import codec
from treepack.plans import codebook as cb
from treepack.plans import shape as sh


@F.pandas_udf(T.BinaryType())
def nbh_encode(raw: pd.Series, lengths: pd.Series) -> pd.Series:
    """Payload of a value of up to 65535 bytes under a length table; n stands in its first four bytes. Null in, null out."""
    return _per_book(raw, lengths, lambda r, b: [len(x).to_bytes(4, "little") + p for x, p in zip(r, codec.encode_batch(r, b), strict=True)])


@F.pandas_udf(T.BinaryType())
def nbh_decode(payload: pd.Series, lengths: pd.Series) -> pd.Series:
    return _per_book(payload, lengths, lambda p, b: codec.decode_batch([x[4:] for x in p], [int.from_bytes(x[:4], "little") for x in p], b))


def _per_book(data: pd.Series, lengths: pd.Series, fn) -> pd.Series:
    out = pd.Series([None] * len(data), dtype=object)
    groups: dict[bytes, list[int]] = {}
    for i, (x, b) in enumerate(zip(data, lengths, strict=True)):
        if x is not None and b is not None:
            groups.setdefault(bytes(b), []).append(i)
    for b, rows in groups.items():
        for i, got in zip(rows, fn([bytes(data.iloc[k]) for k in rows], b), strict=True):
            out.iat[i] = got
    return out


@F.pandas_udf(T.BinaryType())
def huff_lengths(counts: pd.Series) -> pd.Series:
    """Length table of an array of 256 counts."""
    return counts.map(lambda c: None if c is None else cb.pack_lengths(cb.fit_lengths(np.asarray(c, np.int64))))


@F.pandas_udf(T.DoubleType())
def byte_entropy(raw: pd.Series) -> pd.Series:
    """Bits per byte of a value's own distribution; 0 for an empty one."""

    def one(x):
        if x is None:
            return None
        p = np.bincount(np.frombuffer(bytes(x), np.uint8), minlength=256) / max(1, len(x))
        p = p[p > 0]
        return float(-(p * np.log2(p)).sum()) + 0.0

    return raw.map(one)


@F.pandas_udf(T.ArrayType(T.LongType()))
def byte_hist_agg(raw: pd.Series) -> list:
    """256 counts over a group's values; for groups of bounded size (byte_histogram counts any)."""
    out = np.zeros(256, np.int64)
    for x in raw:
        if x is not None:
            out += np.bincount(np.frombuffer(bytes(x), np.uint8), minlength=256)
    return out.tolist()


def _fields(**kinds: T.DataType) -> T.StructType:
    return T.StructType([T.StructField(k, v) for k, v in kinds.items()])


@F.udtf(returnType=_fields(prefix=T.StringType(), n=T.LongType(), n_right=T.LongType(), marker=T.IntegerType(), body=T.IntegerType()))
class nbh_nodes:
    """The inner nodes of one encoded value: what the container holds of each."""

    def eval(self, raw: bytes, lengths: bytes):
        marks: list = []
        codec.encode_batch([bytes(raw)], bytes(lengths), "naive", fallback=False, markers=marks)
        for _, prefix, n, right, marker, body in marks:
            yield prefix, n, right, marker, body


@F.udtf(returnType=_fields(pos=T.IntegerType(), sym=T.IntegerType()))
class symbols:
    """A row per byte."""

    def eval(self, raw: bytes):
        if raw is not None:
            for k, b in enumerate(bytes(raw)):
                yield k, b


@F.udtf(returnType=_fields(node_id=T.IntegerType(), depth=T.IntegerType(), prefix=T.StringType(), op=T.StringType(), d=T.IntegerType()))
class shape_plan:
    """The plan that a length table stands for."""

    def eval(self, lengths: bytes):
        for k, depth, prefix, op, _, _, d, _ in sh.plan_rows(sh.shape_of(bytes(lengths))):
            yield k, depth, prefix, op, d


def register(spark: SparkSession) -> None:
    """Makes all of them callable from SQL in this session."""
    for f in (nbh_encode, nbh_decode, huff_lengths, byte_entropy, byte_hist_agg):
        spark.udf.register(f.__name__ if hasattr(f, "__name__") else f.func.__name__, f)
    for name, f in (("nbh_nodes", nbh_nodes), ("symbols", symbols), ("shape_plan", shape_plan)):
        spark.udtf.register(name, f)
