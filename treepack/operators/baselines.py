"""The codecs that node bitmaps are compared with: code-after-code Huffman with bit-by-bit, table and
multi-cursor decoders, and whole-stream tabled ANS."""

from __future__ import annotations

from functools import lru_cache

import numpy as np

from treepack.functions import fsm
from treepack.functions.kernels import offsets
from treepack.operators.codec import RAW, CorruptBlock
from treepack.plans.codebook import codes_of, unpack_lengths

TABLE_BITS = 11


@lru_cache(maxsize=256)
def _code_arrays(lengths: bytes) -> tuple[np.ndarray, np.ndarray]:
    """(length, code with its first bit lowest) of each symbol."""
    size, code = np.zeros(256, np.int64), np.zeros(256, np.int64)
    for s, (n, c) in codes_of(lengths).items():
        size[s], code[s] = n, int(format(c, f"0{n}b")[::-1], 2) if n else 0
    return size, code


def encode_classic(raws: list[bytes], lengths: bytes, cursors: int = 1) -> list[bytes]:
    """4-byte size, then per cursor its symbols' codes one after another; with several cursors, 2-byte lengths of all but the last come first.

    Cursor c has the c-th of `cursors` equal stretches of the block. A block that would not get smaller is stored as it is.
    """
    size, code = _code_arrays(lengths)
    out = []
    for raw in raws:
        a = np.frombuffer(raw, np.uint8)
        if (unpack_lengths(lengths) > 0).sum() <= 1:
            out.append((0).to_bytes(4, "little"))
            continue
        parts = [_bits_of(p, size, code) for p in stretches(a, cursors)]
        body = b"".join(len(p).to_bytes(2, "little") for p in parts[:-1]) + b"".join(parts)
        out.append((len(raw) | RAW).to_bytes(4, "little") + raw if len(body) >= len(raw) else len(body).to_bytes(4, "little") + body)
    return out


def stretches(a: np.ndarray, cursors: int) -> list[np.ndarray]:
    step = -(-len(a) // cursors) if len(a) else 0
    return [a[c * step : (c + 1) * step] for c in range(cursors)]


def _bits_of(a: np.ndarray, size: np.ndarray, code: np.ndarray) -> bytes:
    n, c = size[a], code[a]
    at = np.cumsum(n) - n
    room = np.zeros(int(n.sum()), np.uint8)
    for k in range(int(n.max(initial=0))):
        m = n > k
        room[at[m] + k] = c[m] >> k & 1
    return np.packbits(room, bitorder="little").tobytes()


def _split(payloads: list[bytes], sizes: list[int], lengths: bytes, cursors: int):
    """Blocks already known, and (block, cursor stream, symbols) of the rest."""
    done: dict[int, bytes] = {}
    lanes: list[tuple[int, bytes, int]] = []
    for k, (p, n) in enumerate(zip(payloads, sizes, strict=True)):
        size = int.from_bytes(p[:4], "little")
        if len(p) - 4 != size & ~RAW:
            raise CorruptBlock("a block's size differs from what it says")
        if size & RAW:
            done[k] = p[4:]
        elif (unpack_lengths(lengths) > 0).sum() <= 1:
            done[k] = bytes([int(np.argmax(unpack_lengths(lengths)))]) * n
        else:
            head = 2 * (cursors - 1)
            lens = [int.from_bytes(p[4 + 2 * c : 6 + 2 * c], "little") for c in range(cursors - 1)]
            at = 4 + head
            step = -(-n // cursors) if n else 0
            for c in range(cursors):
                end = at + lens[c] if c < cursors - 1 else len(p)
                lanes.append((k, p[at:end], max(0, min(step, n - c * step))))
                at = end
    return done, lanes


def decode_bitwise(payloads: list[bytes], sizes: list[int], lengths: bytes) -> list[bytes]:
    """From the root, a bit at a time, to each symbol: what every other decoder is measured against."""
    tree: dict = {}
    for s, (n, c) in codes_of(lengths).items():
        at = tree
        for bit in format(c, f"0{n}b")[:-1]:
            at = at.setdefault(bit == "1", {})
        at[format(c, f"0{n}b")[-1] == "1"] = s
    done, lanes = _split(payloads, sizes, lengths, 1)
    for k, stream, n in lanes:
        out, at = bytearray(), 0
        for _ in range(n):
            node = tree
            while isinstance(node, dict):
                node = node[bool(stream[at >> 3] >> (at & 7) & 1)]
                at += 1
            out.append(node)
        done[k] = bytes(out)
    return [done[k] for k in range(len(payloads))]


@lru_cache(maxsize=256)
def _table(lengths: bytes, log: int, pairs: bool) -> tuple[np.ndarray, ...]:
    """By the next `log` bits: symbol, bits used; with pairs also a second symbol (if both codes fit), how many, bits in all."""
    size, code = _code_arrays(lengths)
    if size.max() > log:
        raise ValueError(f"codes of {size.max()} bits need a larger table than {log}")
    sym, bits = np.zeros(1 << log, np.uint8), np.ones(1 << log, np.int64)
    for s in np.flatnonzero(size):
        at = code[s] + (np.arange(1 << log - size[s]) << size[s])
        sym[at], bits[at] = s, size[s]
    if not pairs:
        return sym, bits
    rest = np.arange(1 << log) >> bits
    second, two = sym[rest], bits[rest]
    fits = bits + two <= log
    return sym, bits, np.where(fits, second, 0).astype(np.uint8), np.where(fits, 2, 1), np.where(fits, bits + two, bits)


def decode_table(payloads: list[bytes], sizes: list[int], lengths: bytes, log: int = TABLE_BITS, cursors: int = 1, symbols_per_step: int = 1) -> list[bytes]:
    """Peek, look up, skip: all blocks' cursors take each step together."""
    done, lanes = _split(payloads, sizes, lengths, cursors)
    n = np.array([x for _, _, x in lanes], np.int64)
    if len(n) and n.max():
        data = np.frombuffer(b"".join(s for _, s, _ in lanes) + b"\0\0\0\0", np.uint8).astype(np.int64)
        word = data[:-3] | data[1:-2] << 8 | data[2:-1] << 16
        lens = np.array([len(s) for _, s, _ in lanes], np.int64)
        pos, limit = (np.cumsum(lens) - lens) * 8, len(word) - 1
        out = np.zeros((len(n), int(n.max()) + 1), np.uint8)
        mask = (1 << log) - 1
        if symbols_per_step == 1:
            sym, bits = _table(lengths, log, False)
            for t in range(int(n.max())):
                k = word[np.minimum(pos >> 3, limit)] >> (pos & 7) & mask
                out[:, t] = sym[k]
                pos += bits[k]
        else:
            sym, bits, second, many, both = _table(lengths, log, True)
            at, row = np.zeros(len(n), np.int64), np.arange(len(n))
            while (live := at < n).any():
                k = word[np.minimum(pos >> 3, limit)] >> (pos & 7) & mask
                out[row[live], at[live]] = sym[k[live]]
                two = live & (many[k] == 2) & (at + 1 < n)
                out[row[two], at[two] + 1] = second[k[two]]
                pos += np.where(live, np.where(two, both[k], bits[k]), 0)
                at += live.astype(np.int64) + two
        parts: dict[int, list[bytes]] = {}
        for (k, _, m), line in zip(lanes, out, strict=True):
            parts.setdefault(k, []).append(line[:m].tobytes())
        done |= {k: b"".join(v) for k, v in parts.items()}
    else:
        done |= {k: b"" for k, _, _ in lanes}
    return [done[k] for k in range(len(payloads))]


# --- whole streams by tabled ANS -------------------------------------------------


def encode_tans(raws: list[bytes], lengths: bytes = b"", cursors: int = 2, log: int = fsm.TABLE_LOG) -> list[bytes]:
    """Each value with a table of its own, made from its bytes: 4-byte size, used symbols, frequencies, stream. Raw if not smaller."""
    freqs, heads = [], []
    for raw in raws:
        f = fsm.normalise(np.bincount(np.frombuffer(raw, np.uint8), minlength=256), log, everything=False) if raw else np.zeros(256, np.int64)
        used = np.flatnonzero(f)
        freqs.append(f)
        heads.append(bytes([len(used) - 1]) + used.astype(np.uint8).tobytes() + (f[used] - 1).astype("<u2").tobytes() if raw else b"")
    streams = [b""] * len(raws)
    many = sorted((k for k, f in enumerate(freqs) if np.count_nonzero(f) > 1), key=lambda k: len(raws[k]))  # equal lengths step together
    for at in range(0, len(many), 256):  # tables take room
        part = many[at : at + 256]
        data, sizes = np.frombuffer(b"".join(raws[k] for k in part), np.uint8), np.array([len(raws[k]) for k in part])
        for k, s in zip(part, fsm.encode(data, sizes, np.arange(len(part)), fsm.build([freqs[k] for k in part], log), cursors), strict=True):
            streams[k] = s
    out = []
    for raw, head, stream in zip(raws, heads, streams, strict=True):
        body = head + stream
        out.append((len(raw) | RAW).to_bytes(4, "little") + raw if len(body) >= len(raw) else len(body).to_bytes(4, "little") + body)
    return out


def decode_tans(payloads: list[bytes], sizes: list[int], lengths: bytes = b"", cursors: int = 2, log: int = fsm.TABLE_LOG, unroll: int = 2) -> list[bytes]:
    """All values of the batch in lockstep, each with its table."""
    done: dict[int, bytes] = {}
    freqs, streams, which = [], [], []
    for k, (p, n) in enumerate(zip(payloads, sizes, strict=True)):
        size = int.from_bytes(p[:4], "little")
        if size & RAW or not n:
            done[k] = p[4:]
            continue
        m = p[4] + 1
        symbols = np.frombuffer(p[5 : 5 + m], np.uint8)
        if m == 1:
            done[k] = symbols.tobytes() * n
            continue
        f = np.zeros(256, np.int64)
        f[symbols] = np.frombuffer(p[5 + m : 5 + 3 * m], "<u2").astype(np.int64) + 1
        freqs.append(f)
        streams.append(p[5 + 3 * m :])
        which.append(k)
    for a in range(0, len(which), 64):  # tables take room
        part = which[a : a + 64]
        n = np.array([sizes[k] for k in part], np.int64)
        flat = fsm.decode(streams[a : a + 64], n, np.arange(len(part)), fsm.build(freqs[a : a + 64], log), cursors, unroll).tobytes()
        done |= {k: flat[b : b + m] for k, b, m in zip(part, offsets(n).tolist(), n.tolist(), strict=True)}
    return [done[k] for k in range(len(payloads))]
