"""Code lengths and canonical codes from symbol counts; everything else follows from the lengths."""

from __future__ import annotations

import heapq
from functools import lru_cache

import numpy as np

MAX_LEN = 11
MAX_FIELD = 15  # what a 4-bit field holds


def huffman_lengths(counts: dict[int, int] | np.ndarray) -> np.ndarray:
    """Optimal lengths without a limit. Of equal counts the subtree with the smaller least symbol merges first.

    No symbol: all zero. One symbol: length zero too, since nothing needs to be told apart.
    """
    pairs = sorted(counts.items()) if isinstance(counts, dict) else [(s, int(c)) for s, c in enumerate(counts)]
    heap = [(c, s, [s]) for s, c in pairs if c > 0]
    out = np.zeros(256, np.int64)
    heapq.heapify(heap)
    while len(heap) > 1:
        a, b = heapq.heappop(heap), heapq.heappop(heap)
        for s in a[2] + b[2]:
            out[s] += 1
        heapq.heappush(heap, (a[0] + b[0], min(a[1], b[1]), a[2] + b[2]))
    return out


def limited_lengths(counts: np.ndarray, max_len: int = MAX_LEN) -> np.ndarray:
    """Least-cost lengths of at most max_len: at each of max_len levels, coins of one denomination are
    paired and merged with the coins of the next; the 2 (n - 1) cheapest at the end tell the lengths."""
    counts = np.asarray(counts, np.int64)
    plain = huffman_lengths(counts)
    if plain.max() <= max_len:
        return plain
    symbols = [int(s) for s in np.flatnonzero(counts)]
    if len(symbols) > 1 << max_len:
        raise ValueError(f"{len(symbols)} symbols do not fit codes of {max_len} bits")
    coins = sorted((int(counts[s]), s, (s,)) for s in symbols)
    row = coins
    for _ in range(max_len - 1):
        packages = [(a[0] + b[0], min(a[1], b[1]), a[2] + b[2]) for a, b in zip(row[::2], row[1::2])]
        row = sorted(coins + packages, key=lambda x: (x[0], x[1], len(x[2])))
    out = np.zeros(256, np.int64)
    for _, _, members in row[: 2 * (len(symbols) - 1)]:
        for s in members:
            out[s] += 1
    return out


def fit_lengths(counts: np.ndarray, max_len: int = MAX_LEN) -> np.ndarray:
    """What a codebook stores: limited lengths; a lone symbol gets length one so that the table names it."""
    out = limited_lengths(counts, max_len)
    if not out.any() and np.any(counts):
        out[int(np.argmax(counts))] = 1
    return out


def repaired_lengths(counts: np.ndarray, max_len: int = MAX_LEN) -> np.ndarray:
    """The quick way to a limit: clip, then lengthen the rarest codes until the code fits; near the optimum, not always at it."""
    counts = np.asarray(counts, np.int64)
    out = np.minimum(huffman_lengths(counts), max_len)
    used = [int(s) for s in sorted(np.flatnonzero(out), key=lambda s: (counts[s], s))]
    kraft, one = sum(1 << max_len - int(out[s]) for s in used), 1 << max_len
    while kraft > one:
        s = next(s for s in used if out[s] < max_len)
        kraft -= 1 << max_len - int(out[s]) - 1
        out[s] += 1
    for s in reversed(used):
        while out[s] > 1 and kraft + (1 << max_len - int(out[s])) <= one:
            kraft += 1 << max_len - int(out[s])
            out[s] -= 1
    return out


def canonical(lengths: np.ndarray) -> dict[int, tuple[int, int]]:
    """symbol -> (length, code): codes count up in order of (length, symbol)."""
    out, code, last = {}, 0, 0
    for n, s in sorted((int(n), s) for s, n in enumerate(lengths) if n):
        code <<= n - last
        out[s] = (n, code)
        code, last = code + 1, n
    return out


def pack_lengths(lengths: np.ndarray) -> bytes:
    """256 four-bit fields, even symbols in the low half."""
    a = np.asarray(lengths, np.uint8)
    if a.max(initial=0) > MAX_FIELD:
        raise ValueError("a code length does not fit four bits")
    return (a[0::2] | a[1::2] << 4).tobytes()


def unpack_lengths(packed: bytes) -> np.ndarray:
    a = np.frombuffer(packed, np.uint8)
    out = np.empty(256, np.int64)
    out[0::2], out[1::2] = a & 15, a >> 4
    return out


def smoothed(counts: np.ndarray) -> np.ndarray:
    """Counts of a sample with every symbol possible, so that a code from a sample can take any block."""
    return np.asarray(counts, np.int64) + 1


@lru_cache(maxsize=512)
def codes_of(packed: bytes) -> dict[int, tuple[int, int]]:
    return canonical(unpack_lengths(packed))
