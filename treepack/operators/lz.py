"""Greedy LZ77 within a value, as four streams: literals, literal runs, match lengths, offsets."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame

MIN_MATCH = 4
WINDOW = 65535
STREAMS = ("lz/lit", "lz/ll", "lz/ml", "lz/off")


def parse(data: bytes, min_match: int = MIN_MATCH, window: int = WINDOW) -> tuple[bytes, list[int], list[int], list[int]]:
    """Each step: a run of literals, then the latest match of the next min_match bytes, as long as it goes; the last run has no match."""
    lit, runs, lens, offs = bytearray(), [], [], []
    seen: dict[bytes, int] = {}
    at, start, n = 0, 0, len(data)
    while at + min_match <= n:
        key = data[at : at + min_match]
        was = seen.get(key)
        seen[key] = at
        if was is None or at - was > window:
            at += 1
            continue
        size = min_match
        while at + size < n and data[was + size] == data[at + size]:
            size += 1
        lit += data[start:at]
        runs.append(at - start)
        lens.append(size)
        offs.append(at - was)
        for k in range(at + 1, min(at + size, n - min_match + 1), 4):
            seen[data[k : k + min_match]] = k
        at += size
        start = at
    lit += data[start:]
    runs.append(n - start)
    return bytes(lit), runs, lens, offs


def rebuild(lit: bytes, runs: list[int], lens: list[int], offs: list[int]) -> bytes:
    out, at = bytearray(), 0
    for k, run in enumerate(runs):
        out += lit[at : at + run]
        at += run
        if k < len(lens):
            size, off = lens[k], offs[k]
            begin = len(out) - off
            if off >= size:
                out += out[begin : begin + size]
            else:
                for i in range(size):
                    out.append(out[begin + i])
    return bytes(out)


def varbytes(numbers: list[int]) -> bytes:
    """255 as often as it fits, then the rest."""
    return b"".join(b"\xff" * (v // 255) + bytes([v % 255]) for v in numbers)


def unvarbytes(data: bytes) -> list[int]:
    out, v = [], 0
    for b in data:
        v += b
        if b != 255:
            out.append(v)
            v = 0
    return out


def pack_offsets(offs: list[int]) -> bytes:
    return b"".join(v.to_bytes(2, "little") for v in offs)


def substreams(values: DataFrame) -> DataFrame:
    """(stream_id, value_id, raw): four streams of every value; a map, value by value."""

    def run(batches):
        for b in batches:
            rows = []
            for v, raw in zip(b.column("value_id").to_pylist(), b.column("raw").to_pylist(), strict=True):
                lit, runs, lens, offs = parse(raw)
                rows += zip(STREAMS, [v] * 4, (lit, varbytes(runs), varbytes(lens), pack_offsets(offs)), strict=True)
            s, v, raw = zip(*rows, strict=True) if rows else ((), (), ())
            yield pa.RecordBatch.from_arrays([pa.array(s, pa.string()), pa.array(v, pa.int64()), pa.array(raw, pa.binary())], names=["stream_id", "value_id", "raw"])

    return values.select("value_id", "raw").mapInArrow(run, "stream_id string, value_id long, raw binary")


def join_substreams(streams: DataFrame) -> DataFrame:
    """(value_id, raw) back from the four streams."""
    import pandas as pd

    wide = streams.groupBy("value_id").pivot("stream_id", list(STREAMS)).agg({"raw": "first"})

    def run(frames):
        for pdf in frames:
            raws = [
                rebuild(bytes(a), unvarbytes(bytes(b)), unvarbytes(bytes(c)), [int.from_bytes(bytes(d)[i : i + 2], "little") for i in range(0, len(d), 2)])
                for a, b, c, d in zip(*(pdf[s] for s in STREAMS), strict=True)
            ]
            yield pd.DataFrame({"value_id": pdf["value_id"], "raw": raws})

    return wide.mapInPandas(run, "value_id long, raw binary")
