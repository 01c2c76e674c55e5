"""Encoding and decoding of block tables: map-only, by a length table that each worker turns into a plan."""

from __future__ import annotations

import zlib
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treepack.operators import codec
from treepack.plans.selective import Gates
from treepack.sources.tables import small

#: How many bytes of blocks go through the kernels together.
BATCH_BYTES = 4 << 20


def _by_book(batch: pa.RecordBatch, column: str = "lengths"):
    """Row numbers of the batch per length table, cut to BATCH_BYTES."""
    groups: dict[bytes, list[int]] = {}
    for i, b in enumerate(batch.column(column).to_pylist()):
        groups.setdefault(b, []).append(i)
    n = batch.column("n").to_pylist()
    for book, rows in groups.items():
        part, size = [], 0
        for i in rows:
            part.append(i)
            size += n[i]
            if size >= BATCH_BYTES:
                yield book, part
                part, size = [], 0
        if part:
            yield book, part


def encode_blocks(blocks: DataFrame, books: DataFrame, on: tuple[str, ...] = ("stream_id",), *, shape: str = "flat_opt", gates: Gates | None = None, encoder: Callable | None = None, hist: DataFrame | None = None) -> DataFrame:
    """blocks with raw replaced by codebook_id, lengths, payload and crc. No shuffle: books are broadcast while small.

    encoder(raws, lengths) -> payloads replaces node bitmaps by a baseline's format.
    hist: stream counts, needed for gates of stream scope.
    """
    keys = [c for c in blocks.columns if c != "raw"]
    joined = _with_books(blocks, books, list(on))
    extra = []
    if hist is not None:
        joined, extra = _with_books(joined, _counts(hist), ["stream_id"], "left"), ["_syms", "_cnts"]

    def run(batches):
        for b in batches:
            raws = b.column("raw").to_pylist()
            ids = b.column("stream_id").to_pylist() if extra else [None] * len(raws)
            payload: list = [None] * len(raws)
            for book, part in _by_book(b):
                for sid in dict.fromkeys(ids[i] for i in part):
                    rows = [i for i in part if ids[i] == sid]
                    some = [raws[i] for i in rows]
                    if encoder:
                        got = encoder(some, book)
                    else:
                        got = codec.encode_batch(some, book, shape, gates, _array(b, rows[0]) if extra else None)
                    for i, p in zip(rows, got, strict=True):
                        payload[i] = p
            crc = pa.array([zlib.crc32(r) for r in raws], pa.int64())
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in keys), b.column("codebook_id"), b.column("lengths"), pa.array(payload, pa.binary()), crc], names=[*keys, "codebook_id", "lengths", "payload", "crc"])

    ddl = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in blocks.select(*keys).schema.fields), "codebook_id long, lengths binary, payload binary, crc long"])
    return joined.select(*keys, "codebook_id", "lengths", "raw", *extra).mapInArrow(run, ddl)


#: Parts that the blocks of one key are dealt to where the other side is too large to broadcast.
SALTS = 64


def _with_books(blocks: DataFrame, books: DataFrame, on: list[str], how: str = "inner") -> DataFrame:
    """blocks joined with a row per key: broadcast while small, else by salted keys, so no key's blocks meet in one task."""
    side = small(books)
    if side is not books:
        return blocks.join(side, on, how)
    salted = blocks.withColumn("_salt", F.pmod(F.xxhash64("value_id", "block_no"), F.lit(SALTS)))
    dealt = books.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    return salted.join(dealt, [*on, "_salt"], how).drop("_salt")


def _counts(hist: DataFrame) -> DataFrame:
    """(stream_id, _syms, _cnts): at most 256 of each stream in one row."""
    rows = hist.groupBy("stream_id").agg(F.array_sort(F.collect_list(F.struct("sym", F.col("cnt").cast("long").alias("cnt")))).alias("r"))
    return rows.select("stream_id", F.transform("r", lambda x: x["sym"].cast("int")).alias("_syms"), F.transform("r", lambda x: x["cnt"]).alias("_cnts"))


def _array(batch: pa.RecordBatch, row: int) -> np.ndarray | None:
    syms, cnts = batch.column("_syms")[row].as_py(), batch.column("_cnts")[row].as_py()
    if syms is None:
        return None
    out = np.zeros(256, np.int64)
    out[syms] = cnts
    return out


def decode_blocks(enc: DataFrame, *, shape: str = "flat_opt", decoder: str = "bottomup", gates: Gates | None = None, decode: Callable | None = None, mode: str = "FAILFAST", **how) -> DataFrame:
    """enc with payload replaced by raw. FAILFAST raises on a broken block; PERMISSIVE gives a null raw and says why in _corrupt."""
    keys = [c for c in enc.columns if c not in ("payload", "crc", "lengths")]
    decode = decode or (lambda payloads, n, lengths: codec.decode_batch(payloads, n, lengths, shape, decoder, gates, **how))
    checked = "crc" in enc.columns
    permissive = mode.upper() == "PERMISSIVE"

    def one(payload, n, book, crc):
        try:
            (raw,) = decode([payload], [n], book)
            if crc is not None and zlib.crc32(raw) != crc:
                raise codec.CorruptBlock("the checksum differs")
            return raw, None
        except Exception as e:  # whatever broken bytes lead to
            return None, f"{type(e).__name__}: {e}"

    def run(batches):
        for b in batches:
            payload, n = b.column("payload").to_pylist(), b.column("n").to_pylist()
            crc = b.column("crc").to_pylist() if checked else [None] * len(n)
            raw, why = [None] * len(n), [None] * len(n)
            for book, rows in _by_book(b):
                try:
                    got = decode([payload[i] for i in rows], [n[i] for i in rows], book)
                    bad = [i for i, g in zip(rows, got, strict=True) if crc[i] is not None and zlib.crc32(g) != crc[i]]
                    if bad:
                        raise codec.CorruptBlock(f"the checksum of row {bad[0]} differs")
                    for i, g in zip(rows, got, strict=True):
                        raw[i] = g
                except Exception:
                    if not permissive:
                        raise
                    for i in rows:
                        raw[i], why[i] = one(payload[i], n[i], book, crc[i])
            arrays = [*(b.column(k) for k in keys), pa.array(raw, pa.binary())]
            yield pa.RecordBatch.from_arrays([*arrays, pa.array(why, pa.string())] if permissive else arrays, names=[*keys, "raw"] + ["_corrupt"] * permissive)

    ddl = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in enc.select(*keys).schema.fields), "raw binary"] + ["_corrupt string"] * permissive)
    return enc.mapInArrow(run, ddl)


def chunk_encode(blocks: DataFrame, *, shape: str = "flat_opt", gates: Gates | None = None, max_len: int = 11) -> DataFrame:
    """One pass: each Arrow batch gets a code of its own, fitted where it is, so no count has to meet another."""
    from treepack.plans import codebook as cb

    keys = [c for c in blocks.columns if c != "raw"]

    def run(batches):
        for b in batches:
            raws = b.column("raw").to_pylist()
            counts = np.bincount(np.frombuffer(b"".join(raws), np.uint8), minlength=256)
            lengths = cb.pack_lengths(cb.fit_lengths(counts, max_len))
            payload = codec.encode_batch(raws, lengths, shape, gates, counts)
            arrays = [*(b.column(k) for k in keys), pa.array([lengths] * len(raws), pa.binary()), pa.array(payload, pa.binary()), pa.array([zlib.crc32(r) for r in raws], pa.int64())]
            yield pa.RecordBatch.from_arrays(arrays, names=[*keys, "lengths", "payload", "crc"])

    ddl = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in blocks.select(*keys).schema.fields), "lengths binary, payload binary, crc long"])
    return blocks.mapInArrow(run, ddl).withColumn("codebook_id", F.xxhash64("lengths"))
