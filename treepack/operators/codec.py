"""Node-bitmap Huffman blocks: encoding, and the two ways to decode, for whole batches of blocks at once.

A block is its size (4 bytes), then its nodes in pre-order. Inner nodes have the
number of right symbols (2 bytes, only if both children hold data), a marker
(0: plain bitmap; else table id, top bit set if bits are complemented), and the
bitmap or a 2-byte length and coded bytes. Flat nodes are D-bit codes. A node
that no symbol of the block reaches holds nothing. A block that would not get
smaller is stored as it is, with the top bit of its size set.
"""

from __future__ import annotations

import zlib

import numpy as np

from treepack.functions import fsm, kernels
from treepack.functions.kernels import block_sums, offsets, spread
from treepack.plans.codebook import unpack_lengths
from treepack.plans.selective import Gates, choose_table, passes, stream_choice
from treepack.plans.shape import Node, paths, shape_of

BLOCK_SIZE = 8192
MAX_BLOCK = 65535  # right counts and coded lengths are 2-byte fields
RAW = 1 << 31


class CorruptBlock(ValueError):
    """A payload that its own fields contradict."""


def check_block_size(n: int) -> int:
    if not 0 < n <= MAX_BLOCK:
        raise ValueError(f"a block holds 1 to {MAX_BLOCK} symbols, not {n}")
    return n


# --- encoding ----------------------------------------------------------------


def encode_batch(raws: list[bytes], lengths: bytes, shape: str = "flat_opt", gates: Gates | None = None, counts: np.ndarray | None = None, block_size: int = BLOCK_SIZE, fallback: bool = True, markers: list | None = None) -> list[bytes]:
    """Payloads of blocks under one code. gates: entropy-code skewed bitmaps. counts: the stream's, for gates of stream scope.
    markers: gets (block, prefix, bits, right, marker, body bytes) of every inner node."""
    root = shape_of(lengths, shape)
    n = np.array([len(r) for r in raws], np.int64)
    if (n > MAX_BLOCK).any():
        check_block_size(int(n.max()))
    data = np.frombuffer(b"".join(raws), np.uint8)
    known = unpack_lengths(lengths) > 0
    if len(data) and not known[data].all():
        raise ValueError(f"symbol {int(data[~known[data]][0])} has no code")
    if root is None:
        return [(0).to_bytes(4, "little") for _ in raws]
    chosen = stream_choice(root, counts, gates, block_size) if gates and gates.scope == "stream" and counts is not None else None
    sections: list[tuple[np.ndarray, np.ndarray]] = []
    # a symbol's path through the tree, from the top bit of 16 down; a flat node's own bits follow those that lead to it
    code = np.zeros(256, np.uint16)
    for s, (prefix, i, d) in paths(root).items():
        code[s] = (int(prefix or "0", 2) << d | i) << (16 - len(prefix) - d)

    def go(node: Node, codes: np.ndarray, count: np.ndarray) -> None:
        if node.leaf or not len(codes):
            return
        depth = len(node.prefix)
        if node.flat:
            own = (codes >> np.uint16(16 - depth - node.d) & np.uint16((1 << node.d) - 1)).astype(np.uint8)
            sections.append(kernels.pack_codes(own, node.d, count))
            return
        keep = "none" if node.two_leaves else "right" if node.left.leaf else "left" if node.right.leaf else "full"
        bits, left, rest = kernels.enc_partition(codes, 15 - depth, keep)
        right = block_sums(bits, count)
        sections.extend(_inner_sections(node, bits, count, right, gates, chosen, markers))
        if left is not None:
            go(node.left, left, count - right)
        if rest is not None:
            go(node.right, rest, right)

    go(root, code.take(data), n)
    body = sum((size for _, size in sections), np.zeros(len(raws), np.int64))
    begin = offsets(body)
    out, at = np.empty(int(body.sum()), np.uint8), begin.copy()
    for section, size in sections:
        out[spread(size, at)] = section
        at += size
    flat = out.tobytes()
    result = []
    for raw, b, size in zip(raws, begin.tolist(), body.tolist(), strict=True):
        if fallback and size >= len(raw):
            result.append((len(raw) | RAW).to_bytes(4, "little") + raw)
        else:
            result.append(size.to_bytes(4, "little") + flat[b : b + size])
    return result


def _inner_sections(node: Node, bits, count, right, gates, chosen, markers):
    used = count > 0
    if node.counted:
        yield right[used].astype("<u2").view(np.uint8), np.where(used, 2, 0)
    plain, size = kernels.pack_bits(bits, count)
    marker = np.zeros(len(count), np.uint8)
    coded: dict[int, bytes] = {}
    if gates:
        which = _selected(node, count, right, gates, chosen)
        ids, flip = choose_table(*_spanned(count, right, gates.span))
        if chosen is not None and node.prefix in chosen:
            ids, flip = np.full_like(ids, abs(chosen[node.prefix])), np.full_like(flip, chosen[node.prefix] < 0)
        if len(which):
            coded = _code(plain, size, which, ids, flip, gates)
            for b in coded:
                marker[b] = ids[b] | (0x80 if flip[b] else 0)
    if markers is not None:
        for b in np.flatnonzero(used).tolist():
            markers.append((b, node.prefix, int(count[b]), int(right[b]), int(marker[b]), len(coded[b]) + 2 if b in coded else int(size[b])))
    yield marker[used], used.astype(np.int64)
    if not coded:
        yield plain, size
        return
    begin = offsets(size)
    parts, sizes = [], size.copy()
    for b in range(len(count)):
        if b in coded:
            parts.append(len(coded[b]).to_bytes(2, "little") + coded[b])
            sizes[b] = len(parts[-1])
        else:
            parts.append(plain[begin[b] : begin[b] + size[b]].tobytes())
    yield np.frombuffer(b"".join(parts), np.uint8), sizes


def _spanned(count: np.ndarray, right: np.ndarray, span: int) -> tuple[np.ndarray, np.ndarray]:
    """Counts over the `span` neighbouring blocks that share a table."""
    if span == 1:
        return count, right
    group = np.arange(len(count)) // span
    return np.bincount(group, count).astype(np.int64)[group], np.bincount(group, right).astype(np.int64)[group]


def _selected(node: Node, count, right, gates: Gates, chosen) -> np.ndarray:
    if chosen is not None:
        return np.flatnonzero(count > 0) if node.prefix in chosen else np.zeros(0, np.int64)
    a, b = _spanned(count, right, gates.span)
    return np.flatnonzero(passes(a, b, node.depth, gates, count))


def _code(plain, size, which, ids, flip, gates: Gates) -> dict[int, bytes]:
    """Coded bitmaps that come out smaller than plain ones."""
    begin = offsets(size)
    parts = [plain[begin[b] : begin[b] + size[b]] for b in which.tolist()]
    parts = [~p if flip[b] else p for p, b in zip(parts, which.tolist(), strict=True)]
    if gates.coder == "tans":
        streams = fsm.encode(np.concatenate(parts), size[which], ids[which] - 1, fsm.static_tables(gates.table_log), gates.cursors)
    elif gates.coder == "custom_tans":
        streams = [custom_encode(p, gates) for p in parts]
    elif gates.coder == "zlib":
        streams = [zlib.compress(p.tobytes(), 9) for p in parts]
    elif gates.coder == "rle":
        streams = [run_lengths(p) for p in parts]
    else:
        raise ValueError(f"unknown bitmap coder {gates.coder!r}")
    return {b: s for b, s, p in zip(which.tolist(), streams, parts, strict=True) if len(s) + 2 < len(p)}


def custom_encode(p: np.ndarray, gates: Gates) -> bytes:
    """A table from the bytes themselves, written ahead of the stream: used symbols and their counts."""
    counts = np.bincount(p, minlength=256)
    f = fsm.normalise(counts, gates.table_log, everything=False)
    used = np.flatnonzero(f)
    head = bytes([len(used) - 1]) + used.astype(np.uint8).tobytes() + f[used].astype("<u2").tobytes()
    return head + fsm.encode(p, np.array([len(p)]), np.array([0]), fsm.build([f], gates.table_log), gates.cursors)[0]


def custom_decode(s: bytes, n: int, gates: Gates) -> np.ndarray:
    k = s[0] + 1
    f = np.zeros(256, np.int64)
    f[np.frombuffer(s[1 : 1 + k], np.uint8)] = np.frombuffer(s[1 + k : 1 + 3 * k], "<u2")
    return fsm.decode([s[1 + 3 * k :]], np.array([n]), np.array([0]), fsm.build([f], gates.table_log), gates.cursors)


def run_lengths(p: np.ndarray) -> bytes:
    """(byte, run of up to 255) pairs."""
    cut = np.flatnonzero(np.diff(p)) + 1
    begin = np.concatenate(([0], cut))
    out = []
    for v, n in zip(p[begin].tolist(), np.diff(np.concatenate((begin, [len(p)]))).tolist(), strict=True):
        while n:
            out += [v, min(n, 255)]
            n -= min(n, 255)
    return bytes(out)


# --- reading -----------------------------------------------------------------


def read_nodes(payloads: list[bytes], n: np.ndarray, root: Node, gates: Gates | None = None, fuse: bool = False) -> dict[str, tuple]:
    """prefix -> (bits or codes of all blocks, count per block), walking all blocks' nodes in step.

    fuse: bitmaps that are coded stay so (CodedBits), where the walk needs no bits to go on.
    """
    buffer = np.frombuffer(b"".join(payloads) + b"\0\0\0\0", np.uint8)
    lens = np.array([len(p) for p in payloads], np.int64)
    end = np.cumsum(lens)
    at = end - lens + 4
    out: dict[str, tuple[np.ndarray, np.ndarray]] = {}
    gates = gates or Gates()

    def take(size: np.ndarray) -> np.ndarray:
        nonlocal at
        if (at + size > end).any():
            raise CorruptBlock("a node runs past the end of its block")
        got = buffer[spread(size, at)]
        at = at + size
        return got

    def go(node: Node, count: np.ndarray) -> None:
        if node.leaf or not count.any():
            return
        used = count > 0
        if node.flat:
            out[node.prefix] = kernels.unpack_codes(take((count * node.d + 7) // 8), node.d, count), count
            return
        right = np.zeros(len(count), np.int64)
        if node.counted:
            right[used] = take(np.where(used, 2, 0)).view("<u2")
        marker = np.zeros(len(count), np.int64)
        marker[used] = take(used.astype(np.int64))
        size = (count + 7) // 8
        if marker.any() and fuse and gates.coder == "tans" and (node.counted or node.two_leaves):
            out[node.prefix] = _still_coded(take, size, marker, gates, count, right), count
            go(node.left, count - right)
            go(node.right, right)
            return
        plain = _uncode(take, size, marker, gates) if marker.any() else take(size)
        bits = kernels.unpack_bits(plain, count)
        out[node.prefix] = bits, count
        if not node.counted:
            right = block_sums(bits, count)
        if (right > count).any():
            raise CorruptBlock("more right symbols than symbols")
        go(node.left, count - right)
        go(node.right, right)

    go(root, n)
    if (at != end).any():
        raise CorruptBlock("bytes are left over after the last node")
    return out


def _coded_parts(take, size: np.ndarray, marker: np.ndarray) -> tuple[np.ndarray, list[bytes], np.ndarray, np.ndarray]:
    """(blocks whose bitmap is coded, their streams, the others, their bytes end to end)."""
    coded = marker > 0
    if ((marker & 0x7F)[coded] > 50).any() or ((marker & 0x7F)[coded] == 0).any():
        raise CorruptBlock("unknown table")
    length = np.zeros(len(size), np.int64)
    length[coded] = take(np.where(coded, 2, 0)).view("<u2")
    length = np.where(coded, length, size)
    got, begin = take(length), offsets(length)
    which, plain = np.flatnonzero(coded), np.flatnonzero(~coded)
    streams = [got[begin[b] : begin[b] + length[b]].tobytes() for b in which.tolist()]
    return which, streams, plain, got[spread(size[plain], begin[plain])]


def _uncode(take, size: np.ndarray, marker: np.ndarray, gates: Gates) -> np.ndarray:
    which, streams, plain, rest = _coded_parts(take, size, marker)
    if gates.coder == "tans":
        data = fsm.decode(streams, size[which], (marker[which] & 0x7F) - 1, fsm.static_tables(gates.table_log), gates.cursors)
    elif gates.coder == "custom_tans":
        data = np.concatenate([custom_decode(s, k, gates) for s, k in zip(streams, size[which].tolist(), strict=True)])
    elif gates.coder == "zlib":
        data = np.frombuffer(b"".join(zlib.decompress(s) for s in streams), np.uint8)
    else:
        data = np.concatenate([np.repeat(np.frombuffer(s, np.uint8)[::2], np.frombuffer(s, np.uint8)[1::2]) for s in streams])
    flip = np.repeat((marker[which] & 0x80) > 0, size[which])
    data = np.where(flip, ~data, data)
    out = np.empty(int(size.sum()), np.uint8)
    out[spread(size[which], offsets(size)[which])] = data
    out[spread(size[plain], offsets(size)[plain])] = rest
    return out


class CodedBits:
    """A node's bitmaps of which some are still coded: merging decodes them a few bytes of every block at a time and never holds them whole."""

    def __init__(self, which, streams, plain, rest, size, marker, gates: Gates, count, right):
        self.which, self.streams, self.plain, self.rest, self.size, self.marker, self.gates, self.count, self.right = which, streams, plain, rest, size, marker, gates, count, right

    def merge(self, left: np.ndarray | int, right: np.ndarray | int) -> np.ndarray:
        """The children's symbols (an array, or a constant) in the order of the bits."""
        out, begin = np.empty(int(self.count.sum()), np.uint8), offsets(self.count)
        from_left, from_right = (None if np.isscalar(x) else offsets(n) for x, n in ((left, self.count - self.right), (right, self.right)))
        if len(self.plain):
            n = self.count[self.plain]
            bits = kernels.unpack_bits(self.rest, n)
            sides = [x if np.isscalar(x) else x[spread(k[self.plain], at[self.plain])] for x, k, at in ((left, self.count - self.right, from_left), (right, self.right, from_right))]
            out[spread(n, begin[self.plain])] = _merged(bits, *sides)
        if len(self.which):
            n, at = self.count[self.which], begin[self.which].copy()
            end = at + n
            taken = [None if x is None else x[self.which].copy() for x in (from_left, from_right)]
            flip = np.where((self.marker[self.which] & 0x80) > 0, 0xFF, 0).astype(np.uint8)[:, None]
            tables = fsm.static_tables(self.gates.table_log)
            for part in fsm.decode_steps(self.streams, self.size[self.which], (self.marker[self.which] & 0x7F) - 1, tables, self.gates.cursors, 8):
                bits = np.unpackbits(part ^ flip, axis=1, bitorder="little").view(bool)
                live = at[:, None] + np.arange(bits.shape[1]) < end[:, None]
                sides = []
                for value, where, on in ((left, taken[0], ~bits & live), (right, taken[1], bits & live)):
                    if where is None:
                        sides.append(np.uint8(value))
                        continue
                    step = np.cumsum(on, axis=1)
                    index = where[:, None] + step - 1
                    if len(value) == 0 or (on & (index >= len(value))).any():
                        raise CorruptBlock("a bitmap takes more symbols than there are")
                    sides.append(value[np.clip(index, 0, len(value) - 1)])
                    where += step[:, -1]
                merged = np.where(bits, sides[1], sides[0])
                out[(at[:, None] + np.arange(bits.shape[1]))[live]] = merged[live]
                at += bits.shape[1]
        return out


def _still_coded(take, size, marker, gates: Gates, count, right) -> CodedBits:
    return CodedBits(*_coded_parts(take, size, marker), size, marker, gates, count, right)


def _merged(bits: np.ndarray, left: np.ndarray | int, right: np.ndarray | int) -> np.ndarray:
    if np.isscalar(left):
        return kernels.merge_cst_cst(bits, left, right) if np.isscalar(right) else kernels.merge_cst_vec(bits, left, right)
    return kernels.merge_vec_cst(bits, left, right) if np.isscalar(right) else kernels.merge_vec_vec(bits, left, right)


def decode_batch(payloads: list[bytes], sizes: list[int], lengths: bytes, shape: str = "flat_opt", decoder: str = "bottomup", gates: Gates | None = None, **how) -> list[bytes]:
    """The blocks' symbols. decoder: bottomup (merges), bottomup_fused (merges take coded bitmaps as they are decoded),
    topdown (partitions and scatters) or topdown_interleaved (of two halves of the blocks in turn)."""
    out: list[bytes | None] = [None] * len(payloads)
    root, todo = shape_of(lengths, shape), []
    for k, p in enumerate(payloads):
        if len(p) < 4:
            raise CorruptBlock("a block without its size")
        size = int.from_bytes(p[:4], "little")
        if len(p) - 4 != size & ~RAW:
            raise CorruptBlock(f"a block of {len(p) - 4} bytes says {size & ~RAW}")
        if size & RAW:
            out[k] = p[4:]
        elif root is None:
            out[k] = bytes([int(np.argmax(unpack_lengths(lengths)))]) * sizes[k]
        else:
            todo.append(k)
    if todo:
        n = np.array([sizes[k] for k in todo], np.int64)
        if decoder == "topdown_interleaved":
            half = len(todo) // 2
            parts = [(read_nodes([payloads[k] for k in some], m, root, gates), m) for some, m in ((todo[:half], n[:half]), (todo[half:], n[half:])) if some]
            flat = b"".join(x.tobytes() for x in decode_interleaved(root, parts, lengths, **how))
        else:
            nodes = read_nodes([payloads[k] for k in todo], n, root, gates, fuse=decoder == "bottomup_fused")
            flat = (decode_topdown(root, nodes, n, lengths, **how) if decoder == "topdown" else decode_bottomup(root, nodes, n)).tobytes()
        for k, b, size in zip(todo, offsets(n).tolist(), n.tolist(), strict=True):
            out[k] = flat[b : b + size]
    for k, (o, size) in enumerate(zip(out, sizes, strict=True)):
        if len(o) != size:
            raise CorruptBlock(f"block {k} holds {len(o)} symbols, not {size}")
    return out


def decode_bottomup(root: Node, nodes: dict, n: np.ndarray) -> np.ndarray:
    """Dense lists of symbols flow up: each node merges its children's lists by its bits; leaves are constants."""

    def up(node: Node) -> np.ndarray | int:
        if node.leaf:
            return node.symbols[0]
        if node.prefix not in nodes:
            return np.zeros(0, np.uint8)
        bits, _ = nodes[node.prefix]
        if node.flat:
            return kernels.merge_flat(bits, np.array(node.symbols, np.uint8))
        left, right = up(node.left), up(node.right)
        return bits.merge(left, right) if isinstance(bits, CodedBits) else _merged(bits, left, right)

    return up(root)


def decode_topdown(root: Node, nodes: dict, n: np.ndarray, lengths: bytes, **how) -> np.ndarray:
    """Lists of output positions flow down: inner nodes partition them, leaves scatter their symbol to them."""
    out = np.empty(int(n.sum()), np.uint8)
    for _ in topdown_steps(root, nodes, out, lengths, **how):
        pass
    return out


def decode_interleaved(root: Node, parts: list[tuple[dict, np.ndarray]], lengths: bytes, **how) -> list[np.ndarray]:
    """Top-down decoding of several groups of blocks, a kernel of each in turn, so that one's scatters run between another's partitions."""
    outs = [np.empty(int(n.sum()), np.uint8) for _, n in parts]
    going = []
    for (nodes, _), out in zip(parts, outs, strict=True):
        going.append(topdown_steps(root, nodes, out, lengths, **how))
        going = [g for g in going if next(g, None) is not None]  # those that began before are one kernel ahead
    while going:
        going = [g for g in going if next(g, None) is not None]
    return outs


def topdown_steps(root: Node, nodes: dict, out: np.ndarray, lengths: bytes, prefill: bool = True, fuse: bool = True, impl: str = "vector", root_levels: bool = False):
    """Fills out, and yields the kind of each kernel once it has run.

    prefill: the most frequent leaf is a constant written first. fuse: one
    scatter for a node of two leaves. root_levels: all levels above the first
    leaf are decoded at once, by a split into as many lists as they have paths.
    """
    from treepack.plans.shape import most_frequent_leaf

    total = len(out)
    free = most_frequent_leaf(root, unpack_lengths(lengths)) if prefill else None
    out[:] = next((x.symbols[0] for x in root.walk() if x.prefix == free and x.leaf), 0)
    yield "fill"

    def down(node: Node, idx: np.ndarray | None):
        if node.leaf:
            if node.prefix != free:
                kernels.scatter_one(out, np.arange(total) if idx is None else idx, node.symbols[0])
                yield "scatter"
            return
        if node.prefix not in nodes:
            return
        bits, _ = nodes[node.prefix]
        if node.flat:
            kernels.scatter_flat(out, np.arange(total) if idx is None else idx, bits, np.array(node.symbols, np.uint8))
            yield "scatter"
        elif fuse and node.two_leaves:
            kernels.scatter_two(out, np.arange(total) if idx is None else idx, bits, node.left.symbols[0], node.right.symbols[0])
            yield "scatter"
        elif node.left.prefix == free or node.right.prefix == free:
            side = node.left.prefix == free
            part = np.flatnonzero(bits if side else bits == 0) if idx is None else kernels.partition_half(bits, idx, side)
            yield "partition"
            yield from down(node.right if side else node.left, part)
        else:
            left, right = kernels.partition_root(bits) if idx is None else kernels.partition(bits, idx, impl)
            yield "partition"
            yield from down(node.left, left)
            yield from down(node.right, right)

    levels = min(len(x.prefix) for x in root.walk() if not x.inner) if root_levels else 0
    if not levels:
        yield from down(root, None)
        return
    below = [root]
    for _ in range(levels):
        below = [child for node in below for child in (node.left, node.right)]
    lists = kernels.split_ways(_ways(root, nodes, levels), len(below))
    yield "split"
    for node, idx in zip(below, lists, strict=True):
        yield from down(node, idx)


def _ways(node: Node, nodes: dict, levels: int) -> np.ndarray:
    """The next `levels` bits of every symbol of a node as one number, from the bitmaps of those levels."""
    if node.prefix not in nodes:
        return np.zeros(0, np.uint16)
    bits, _ = nodes[node.prefix]
    if levels == 1:
        return bits.astype(np.uint16)
    out = np.empty(len(bits), np.uint16)
    out[np.flatnonzero(~bits)] = _ways(node.left, nodes, levels - 1)
    out[np.flatnonzero(bits)] = _ways(node.right, nodes, levels - 1) | np.uint16(1 << (levels - 1))
    return out
