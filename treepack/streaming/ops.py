"""Blocks as the unit of a stream: encoding micro-batches, windowed counts, block building, changing codebooks."""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from treepack.operators.blocks import encode_blocks
from treepack.plans import codebook as cb
from treepack.sources.streams import to_blocks


def encode_stream(values: DataFrame, books: DataFrame, **how) -> DataFrame:
    """Stateless: (stream_id, value_id, raw) rows of a stream encoded by a code that was made before."""
    return encode_blocks(to_blocks(values), books, **how)


def byte_counts(events: DataFrame, column: str) -> DataFrame:
    """A row per byte value of a text column, with its count; stateless."""
    bytes_ = F.explode(F.transform(F.sequence(F.lit(1), F.octet_length(column)), lambda i: F.conv(F.substring(F.hex(column), 2 * i - 1, 2), 16, 10).cast("int")))
    return events.where(F.octet_length(column) > 0).select("*", bytes_.alias("sym"))


def window_histogram(events: DataFrame, ts: str, column: str, size: str, slide: str | None = None, watermark: str = "1 hour", by: tuple[str, ...] = ()) -> DataFrame:
    """(start, by.., sym, cnt) over tumbling or sliding windows."""
    w = F.window(ts, size, slide) if slide else F.window(ts, size)
    return byte_counts(events.withWatermark(ts, watermark), column).groupBy(w.alias("w"), *by, "sym").agg(F.count("*").alias("cnt")).select(F.col("w.start").alias("start"), *by, "sym", "cnt")


def session_bytes(events: DataFrame, ts: str, column: str, gap: str, key: str, watermark: str = "1 hour") -> DataFrame:
    """(key, start, n, n_bytes) per session."""
    s = events.withWatermark(ts, watermark).groupBy(F.session_window(ts, gap).alias("w"), key).agg(F.count("*").alias("n"), F.sum(F.octet_length(column)).alias("n_bytes"))
    return s.select(key, F.col("w.start").alias("start"), "n", "n_bytes")


def block_builder(events: DataFrame, key: str, column: str, block_size: int = 8192, timeout_ms: int | None = None) -> DataFrame:
    """(key, block_no, n, raw): bytes of a key gathered until they fill a block; with timeout_ms what is left goes out when the key stays
    silent so long (a stream with timers runs until it is stopped).

    State: at most a block's bytes per key, with its number.
    """

    def build(k: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held, number = state.get if state.exists else (b"", 0)
        rows = []
        if state.hasTimedOut:
            rows = [(k[0], number, len(held), bytes(held))] if held else []
            state.remove()
        else:
            for pdf in frames:
                held = bytes(held) + b"".join(v.encode() for v in pdf[column] if v is not None)
            while len(held) >= block_size:
                rows.append((k[0], number, block_size, held[:block_size]))
                held, number = held[block_size:], number + 1
            state.update((held, number))
            if timeout_ms is not None:
                state.setTimeoutDuration(timeout_ms)
        yield pd.DataFrame(rows, columns=[key, "block_no", "n", "raw"])

    kind = dict(events.dtypes)[key]
    return events.select(key, column).groupBy(key).applyInPandasWithState(build, f"`{key}` {kind}, block_no long, n int, raw binary", "held binary, number long", "append", GroupStateTimeout.NoTimeout if timeout_ms is None else GroupStateTimeout.ProcessingTimeTimeout)


def adaptive_codebook(events: DataFrame, key: str, column: str, tau: float = 0.05) -> DataFrame:
    """(key, version, n, drift, lengths): a new code when the bytes seen since the last one diverge from what it was made for by over tau bits.

    State: two histograms of 256 counts per key, and the version.
    """

    def adapt(k: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        base, now, version = (json.loads(state.get[0]), json.loads(state.get[1]), state.get[2]) if state.exists else ([0] * 256, [0] * 256, 0)
        base, now = np.array(base, np.int64), np.array(now, np.int64)
        for pdf in frames:
            data = b"".join(v.encode() for v in pdf[column] if v is not None)
            now += np.bincount(np.frombuffer(data, np.uint8), minlength=256)
        drift = divergence(now, base)
        rows = []
        if now.sum() and (version == 0 or drift > tau):
            version += 1
            rows.append((k[0], version, int(now.sum()), float(drift), cb.pack_lengths(cb.fit_lengths(cb.smoothed(now)))))
            base, now = now, np.zeros(256, np.int64)
        state.update((json.dumps(base.tolist()), json.dumps(now.tolist()), version))
        yield pd.DataFrame(rows, columns=[key, "version", "n", "drift", "lengths"])

    kind = dict(events.dtypes)[key]
    return events.select(key, column).groupBy(key).applyInPandasWithState(adapt, f"`{key}` {kind}, version int, n long, drift double, lengths binary", "base string, now string, version int", "append", GroupStateTimeout.NoTimeout)


def divergence(now: np.ndarray, base: np.ndarray) -> float:
    """Extra bits per byte of coding `now` by a code for `base`, both smoothed."""
    p, q = (now + 1) / (now.sum() + 256), (base + 1) / (base.sum() + 256)
    return float((p * np.log2(p / q)).sum())


def idempotent_writer(path: str, sink: str = "parquet"):
    """A foreachBatch function that overwrites the folder of its batch: a batch that runs again leaves the same rows."""

    def write(df: DataFrame, batch_id: int) -> None:
        df.write.mode("overwrite").format(sink).save(f"{path}/batch={batch_id}")

    return write
