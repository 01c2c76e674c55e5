"""Pivoted unary codes: bit j of all values that reach j form one bitmap; decoding folds the bitmaps from the last to the first."""

from __future__ import annotations

from functools import lru_cache

import numpy as np

from treepack.functions import kernels

MAX_VALUE = 254


def encode(values: np.ndarray, k: int = 0) -> tuple[list[np.ndarray], np.ndarray | None]:
    """(bitmaps as booleans, low k bits): value v goes on, clear, in bitmaps 0 .. v - 1 and ends, set, in bitmap v."""
    values = np.asarray(values, np.int64)
    rest = values & ((1 << k) - 1) if k else None
    values = values >> k
    if len(values) and (values.min() < 0 or values.max() > MAX_VALUE):
        raise ValueError(f"a unary part lies outside 0 .. {MAX_VALUE}; take more low bits")
    out, j = [], 0
    while len(values):
        ends = values == j
        out.append(ends)
        values, j = values[~ends], j + 1
    return out, rest


def decode(bitmaps: list[np.ndarray], rest: np.ndarray | None = None, k: int = 0) -> np.ndarray:
    child = np.zeros(0, np.uint8)
    for bits in reversed(bitmaps):
        child = kernels.merge_vec_cst_plus1(bits, child)
    out = child.astype(np.int64)
    return out << k | rest if rest is not None else out


def to_bytes(values: np.ndarray, k: int = 0) -> bytes:
    """4-byte count, bitmap count, bitmaps with their sizes following from one another, low bits."""
    bitmaps, rest = encode(values, k)
    body = b"".join(np.packbits(b, bitorder="little").tobytes() for b in bitmaps)
    low = kernels.pack_codes(rest.astype(np.uint8), k, np.array([len(values)]))[0].tobytes() if k else b""
    return len(values).to_bytes(4, "little") + bytes([len(bitmaps)]) + body + low


def from_bytes(data: bytes, k: int = 0) -> np.ndarray:
    n, m, at = int.from_bytes(data[:4], "little"), data[4], 5
    bitmaps, left = [], n
    for _ in range(m):
        size = (left + 7) // 8
        bits = np.unpackbits(np.frombuffer(data[at : at + size], np.uint8), bitorder="little", count=left).view(bool)
        bitmaps.append(bits)
        left, at = left - int(bits.sum()), at + size
    rest = kernels.unpack_codes(np.frombuffer(data[at:], np.uint8), k, np.array([n])).astype(np.int64) if k else None
    return decode(bitmaps, rest, k)


# --- the row-wise code that the baselines read ------------------------------------


def plain_bits(values: np.ndarray) -> bytes:
    """v zeros, then a one, value after value."""
    values = np.asarray(values, np.int64)
    ends = np.cumsum(values + 1) - 1
    room = np.zeros(int(ends[-1]) + 1 if len(ends) else 0, np.uint8)
    room[ends] = 1
    return np.packbits(room, bitorder="little").tobytes()


def decode_naive(data: bytes, n: int) -> np.ndarray:
    out, v, at = [], 0, 0
    while len(out) < n:
        if data[at >> 3] >> (at & 7) & 1:
            out.append(v)
            v = 0
        else:
            v += 1
        at += 1
    return np.array(out, np.int64)


@lru_cache(maxsize=1)
def byte_table() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """By byte: the up to eight values that end in it (the first without what came before), how many, zeros left at its end."""
    bits = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little")
    values, many, left = np.zeros((256, 8), np.int64), bits.sum(axis=1).astype(np.int64), np.zeros(256, np.int64)
    for b in range(256):
        at = np.flatnonzero(bits[b])
        gaps = np.diff(np.concatenate(([-1], at))) - 1
        values[b, : len(gaps)] = gaps
        left[b] = 7 - at[-1] if len(at) else 8
    return values, many, left


def decode_bytetable(data: bytes, n: int, branch_free: bool = False) -> np.ndarray:
    """A byte at a time by a table of up to eight values. branch_free: all eight are stored, only the place moves on."""
    values, many, left = byte_table()
    out, at, carry = np.zeros(n + 16, np.int64), 0, 0
    for b in data:
        m = int(many[b])
        if branch_free:
            out[at : at + 8] = values[b][: len(out) - at]
            out[at] += carry
            at += m
            carry = int(left[b]) + carry * (m == 0)
        elif m == 0:
            carry += 8
        else:
            out[at : at + m] = values[b, :m][: len(out) - at]
            out[at] += carry
            at, carry = at + m, int(left[b])
        if at >= n:
            break
    return out[:n]
