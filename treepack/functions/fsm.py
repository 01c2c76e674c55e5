"""Tabled asymmetric numeral systems, run in lockstep over many streams and several cursors per stream.

A stream is the cursors' first states, then the bits of each step, cursor after
cursor. How many bits a cursor reads depends on its state alone, so all cursors
of a step read at once from places that a running sum gives. Streams of a batch
may use different tables.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache

import numpy as np

TABLE_LOG = 12
CURSORS = 8


@dataclass(frozen=True)
class Tables:
    """One row per table: for decoding symbol, bits and base of each state; for encoding frequencies, first slots and next states."""

    log: int
    symbol: np.ndarray
    bits: np.ndarray
    base: np.ndarray
    freq: np.ndarray
    first: np.ndarray
    after: np.ndarray


def normalise(weights: np.ndarray, log: int = TABLE_LOG, everything: bool = True) -> np.ndarray:
    """Frequencies that sum to 2**log, at least one for each symbol with weight (with `everything`, for each symbol)."""
    w, size = np.asarray(weights, np.float64), 1 << log
    used = np.ones(len(w), bool) if everything else w > 0
    if used.sum() > size:
        raise ValueError("more symbols than states")
    share = w / w.sum() * size if w.sum() else np.full(len(w), size / len(w))
    out = np.where(used, np.maximum(1, np.floor(share)), 0).astype(np.int64)
    while (gap := size - int(out.sum())) != 0:  # one state at a time, where the expected length gains most or loses least
        if gap > 0:
            out[np.argmax(np.where(used, share * np.log2((out + 1) / np.maximum(out, 1)), -1))] += 1
        else:
            out[np.argmin(np.where(out > 1, share * np.log2(np.maximum(out, 1) / np.maximum(out - 1, 1)), np.inf))] -= 1
    return out


def build(freqs: list[np.ndarray], log: int = TABLE_LOG) -> Tables:
    """Decode and encode tables from frequencies."""
    size, n = 1 << log, len(freqs)
    symbol, bits, base = np.zeros((n, size), np.uint8), np.zeros((n, size), np.int64), np.zeros((n, size), np.int64)
    first, after = np.zeros((n, 256), np.int64), np.zeros((n, size), np.int64)
    step = (size >> 1) + (size >> 3) + 3
    place = (np.arange(size) * step) & (size - 1)
    for t, f in enumerate(freqs):
        spread = np.empty(size, np.uint8)
        spread[place] = np.repeat(np.arange(256, dtype=np.uint8), f)
        order = np.argsort(spread, kind="stable")  # states of each symbol, ascending
        start = np.concatenate(([0], np.cumsum(f)[:-1]))
        rank = np.arange(size) - np.repeat(start, f)
        x = np.repeat(f, f) + rank
        nb = log - (np.frexp(x.astype(np.float64))[1] - 1)
        symbol[t], first[t], after[t] = spread, start, order
        bits[t, order], base[t, order] = nb, (x << nb) - size
    return Tables(log, symbol, bits, base, np.stack(freqs), first, after)


@lru_cache(maxsize=4)
def static_tables(log: int = TABLE_LOG) -> Tables:
    """Fifty tables for bitmaps of which 50, 51 .. 99 per cent of the bits are zero, over bytes of independent bits."""
    ones = np.bitwise_count(np.arange(256, dtype=np.uint8)).astype(np.float64)
    return build([normalise((p / 100) ** (8 - ones) * (1 - p / 100) ** ones, log) for p in range(50, 100)], log)


@lru_cache(maxsize=4)
def bit_costs(log: int = TABLE_LOG) -> np.ndarray:
    """Expected bits per bitmap bit of each static table on data it is built for."""
    ones = np.bitwise_count(np.arange(256, dtype=np.uint8)).astype(np.float64)
    f = static_tables(log).freq
    return np.array([((p / 100) ** (8 - ones) * (1 - p / 100) ** ones * (log - np.log2(f[k]))).sum() / 8 for k, p in enumerate(range(50, 100))])


def encode(data: np.ndarray, sizes: np.ndarray, table: np.ndarray, tables: Tables, cursors: int = CURSORS) -> list[bytes]:
    """Streams of bytes, end to end in data, each with its table's number."""
    sizes, table = np.asarray(sizes, np.int64), np.asarray(table, np.int64)
    begins, n, size, log = np.cumsum(sizes) - sizes, len(sizes), 1 << tables.log, tables.log
    steps, whole = (int(-(-sizes.max() // cursors)), int(sizes.min()) // cursors) if n else (0, 0)
    room = steps * cursors
    at = np.arange(room)[None, :]
    # what does not depend on the state is looked up for all steps at once
    key = (table[:, None] * 256 + data[np.minimum(begins[:, None] + at, max(0, len(data) - 1))]).reshape(n, steps, cursors).transpose(1, 0, 2) if room else np.zeros((0, n, cursors), np.int64)
    f = tables.freq.ravel()
    most = log + 1 - np.frexp(np.maximum(f, 1).astype(np.float64))[1]  # largest with 2 size - 1 >> most >= f; one less for states under f << most
    bound, to = (f << most).astype(np.int32)[key], (np.repeat(np.arange(len(tables.freq)), 256) * size + tables.first.ravel() - f).astype(np.int32)[key]
    most, after = most.astype(np.int32)[key], tables.after.ravel().astype(np.int32) + size
    state = np.full((n, cursors), size, np.int32)  # from size to 2 size - 1
    w, v = np.zeros((n, steps + 1, cursors), np.uint8), np.zeros((n, steps + 1, cursors), np.uint16 if log <= 16 else np.uint32)
    lane = np.arange(cursors)
    for t in range(steps - 1, -1, -1):
        nb = most[t] - (state < bound[t])
        if t < whole:
            w[:, t + 1], v[:, t + 1] = nb, state & ((1 << nb) - 1)
            state = after[to[t] + (state >> nb)]
        else:
            live = t * cursors + lane < sizes[:, None]
            w[:, t + 1], v[:, t + 1] = np.where(live, nb, 0), np.where(live, state & ((1 << nb) - 1), 0)
            state = np.where(live, after[np.clip(to[t] + (state >> nb), 0, len(after) - 1)], state)
    w[:, 0], v[:, 0] = log, state - size
    w, v = w.reshape(n, -1), v.reshape(n, -1)
    total = w.sum(axis=1, dtype=np.int64)
    nbytes = (total + 7) // 8
    begin = (np.cumsum(nbytes) - nbytes) * 8
    place = begin[:, None] + np.cumsum(w, axis=1, dtype=np.int64) - w
    room = np.zeros(int(nbytes.sum()) * 8, np.uint8)
    for k in range(log):
        m = w > k
        room[place[m] + k] = v[m] >> k & 1
    raw, ends = np.packbits(room, bitorder="little").tobytes(), np.cumsum(nbytes)
    return [raw[e - b : e] for b, e in zip(nbytes.tolist(), ends.tolist(), strict=True)]


def decode_steps(streams: list[bytes], sizes: np.ndarray, table: np.ndarray, tables: Tables, cursors: int = CURSORS, unroll: int = 1):
    """Yields (streams x bytes) parts of all streams in step, in order; what lies past the end of a stream means nothing."""
    sizes, table = np.asarray(sizes, np.int64), np.asarray(table, np.int64)
    n, size, log = len(sizes), 1 << tables.log, tables.log
    lens = np.array([len(s) for s in streams], np.int64)
    data = np.frombuffer(b"".join(streams) + b"\0\0\0\0", np.uint8).astype(np.int64)
    word = data[:-3] | data[1:-2] << 8 | data[2:-1] << 16
    pos = (np.cumsum(lens) - lens) * 8
    flat_symbol, flat_bits, flat_base = tables.symbol.ravel(), tables.bits.ravel(), tables.base.ravel()
    lane = np.arange(cursors)
    at = pos[:, None] + lane * log
    state = (word[np.minimum(at >> 3, len(word) - 1)] >> (at & 7)) & (size - 1)
    pos = pos + cursors * log
    steps, row = int(-(-sizes.max() // cursors)), table[:, None] * size
    whole = int(sizes.min()) // cursors  # as long as all lanes live, nothing needs a mask
    for t0 in range(0, steps, unroll):
        part = []
        for t in range(t0, min(t0 + unroll, steps)):
            k = row + state
            part.append(flat_symbol[k])
            nb = flat_bits[k]
            if t >= whole:
                nb = np.where(t * cursors + lane < sizes[:, None], nb, 0)
            ends = np.cumsum(nb, axis=1)
            at = pos[:, None] + ends - nb
            state = flat_base[k] + ((word[np.minimum(at >> 3, len(word) - 1)] >> (at & 7)) & ((1 << nb) - 1))
            state &= size - 1
            pos = pos + ends[:, -1]
        yield np.stack(part, axis=1).astype(np.uint8).reshape(n, -1)


def decode(streams: list[bytes], sizes: np.ndarray, table: np.ndarray, tables: Tables, cursors: int = CURSORS, unroll: int = 1) -> np.ndarray:
    """The bytes of all streams, end to end. unroll: steps whose symbols are stored together."""
    sizes = np.asarray(sizes, np.int64)
    if not sizes.sum():
        return np.zeros(0, np.uint8)
    kept = np.concatenate(list(decode_steps(streams, sizes, table, tables, cursors, unroll)), axis=1)
    return kept[np.arange(kept.shape[1])[None, :] < sizes[:, None]]
