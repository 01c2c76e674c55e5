"""Questions answered on encoded blocks without decoding them: a symbol's path through the tree is all that is read."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from treepack.functions.kernels import block_sums, offsets
from treepack.operators import codec
from treepack.operators.blocks import _by_book
from treepack.plans.shape import Node, paths, shape_of


def _scan(enc: DataFrame, ddl: str, names: list[str], one, shape: str) -> DataFrame:
    """one(nodes or None, root, blocks' raw or None, n) -> for each block a list of tuples."""
    keys = ["stream_id", "value_id", "block_no"]

    def run(batches):
        for b in batches:
            payload, n = b.column("payload").to_pylist(), b.column("n").to_pylist()
            ident = list(zip(*(b.column(k).to_pylist() for k in keys), strict=True))
            rows = []
            for book, part in _by_book(b):
                root = shape_of(book, shape)
                plain = [i for i in part if root is None or int.from_bytes(payload[i][:4], "little") & codec.RAW]
                as_is = set(plain)
                coded = [i for i in part if i not in as_is]
                if coded:
                    size = np.array([n[i] for i in coded], np.int64)
                    for i, got in zip(coded, one(codec.read_nodes([payload[i] for i in coded], size, root), root, size, None), strict=True):
                        rows += [(*ident[i], *g) for g in got]
                for i, raw in zip(plain, codec.decode_batch([payload[i] for i in plain], [n[i] for i in plain], book, shape) if plain else [], strict=True):
                    rows += [(*ident[i], *g) for g in one(None, root, None, np.frombuffer(raw, np.uint8))]
            if rows:
                cols = list(zip(*rows, strict=True))
                kinds = [pa.string(), pa.int64(), pa.int64()] + [pa.int64()] * (len(cols) - 3)
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=[*keys, *names])

    return enc.select(*keys, "n", "lengths", "payload").mapInArrow(run, "stream_id string, value_id long, block_no long, " + ddl)


def _step(root: Node, prefix: str):
    """(inner node, side) on the way to a node."""
    at = root
    for bit in prefix:
        yield at, bit == "1"
        at = at.right if bit == "1" else at.left


def _reach(nodes: dict, root: Node, symbol: int, size: np.ndarray) -> np.ndarray:
    """How many of the symbol each block has: counts along one path."""
    where = paths(root).get(symbol)
    if where is None:
        return np.zeros(len(size), np.int64)
    prefix, index, d = where
    count = size
    for node, side in _step(root, prefix):
        if node.prefix not in nodes:
            return np.zeros(len(size), np.int64)
        right = block_sums(nodes[node.prefix][0], count)
        count = right if side else count - right
    if d:
        return block_sums(nodes[prefix][0] == index, count) if prefix in nodes else np.zeros(len(size), np.int64)
    return count


def count_symbol(enc: DataFrame, symbol: int, shape: str = "flat_opt") -> DataFrame:
    """(.., found): occurrences per block."""

    def one(nodes, root, size, raw):
        return [(int((raw == symbol).sum()),)] if nodes is None else [[(c,)] for c in _reach(nodes, root, symbol, size).tolist()]

    return _scan(enc, "found long", ["found"], one, shape)


def line_count(enc: DataFrame, shape: str = "flat_opt") -> DataFrame:
    return count_symbol(enc, 10, shape)


def histogram(enc: DataFrame, shape: str = "flat_opt") -> DataFrame:
    """(.., sym, cnt) from popcounts alone."""

    def one(nodes, root, size, raw):
        if nodes is None:
            c = np.bincount(raw, minlength=256)
            return [(int(s), int(c[s])) for s in np.flatnonzero(c)]
        out: list[list] = [[] for _ in size]

        def go(node: Node, count: np.ndarray) -> None:
            if node.leaf:
                for b in np.flatnonzero(count).tolist():
                    out[b].append((node.symbols[0], int(count[b])))
            elif node.prefix in nodes:
                data, c = nodes[node.prefix]
                if node.flat:
                    for i, s in enumerate(node.symbols):
                        got = block_sums(data == i, c)
                        for b in np.flatnonzero(got).tolist():
                            out[b].append((s, int(got[b])))
                else:
                    right = block_sums(data, c)
                    go(node.left, c - right)
                    go(node.right, right)

        go(root, size)
        return out

    return _scan(enc, "sym long, cnt long", ["sym", "cnt"], one, shape)


def positions(enc: DataFrame, symbols: set[int] | int, shape: str = "flat_opt", limit: int | None = None) -> DataFrame:
    """(.., pos) of the symbols in each block, in order; only subtrees that hold one are followed. limit: the first so many of a block."""
    wanted = {symbols} if isinstance(symbols, int) else set(symbols)

    def one(nodes, root, size, raw):
        if nodes is None:
            return [(int(p),) for p in np.flatnonzero(np.isin(raw, list(wanted)))[:limit]]
        begin, total = offsets(size), int(size.sum())
        parts: list[np.ndarray] = []

        def holds(node: Node) -> bool:
            return any(wanted.intersection(x.symbols) for x in node.walk() if not x.inner)

        def go(node: Node, idx: np.ndarray) -> None:
            if not len(idx) or not holds(node):
                return
            if node.leaf:
                parts.append(idx)
            elif node.flat:
                parts.append(idx[np.isin(nodes[node.prefix][0], [i for i, s in enumerate(node.symbols) if s in wanted])])
            else:
                bits = nodes[node.prefix][0]
                go(node.left, idx[~bits])
                go(node.right, idx[bits])

        go(root, np.arange(total))
        found = np.sort(np.concatenate(parts)) if parts else np.zeros(0, np.int64)
        of = np.searchsorted(begin, found, side="right") - 1
        out: list[list] = [[] for _ in size]
        for b, p in zip(of.tolist(), (found - begin[of]).tolist(), strict=True):
            if limit is None or len(out[b]) < limit:
                out[b].append((p,))
        return out

    return _scan(enc, "pos long", ["pos"], one, shape)


def access(enc: DataFrame, at: int, shape: str = "flat_opt") -> DataFrame:
    """(.., sym) at a position of each block that is long enough: one bit per level, by rank."""

    def one(nodes, root, size, raw):
        if nodes is None:
            return [(int(raw[at]),)] if at < len(raw) else []
        out = []
        for b, n in enumerate(size.tolist()):
            out.append([(_walk(nodes, root, b, at),)] if at < n else [])
        return out

    return _scan(enc, "sym long", ["sym"], one, shape)


def _walk(nodes: dict, root: Node, block: int, i: int) -> int:
    node = root
    while not node.leaf:
        data, count = nodes[node.prefix]
        begin = int(offsets(count)[block])
        if node.flat:
            return node.symbols[int(data[begin + i])]
        ones = int(data[begin : begin + i].sum())
        node, i = (node.right, ones) if data[begin + i] else (node.left, i - ones)
    return node.symbols[0]


def rank(enc: DataFrame, symbol: int, at: int, shape: str = "flat_opt") -> DataFrame:
    """(.., found): occurrences of the symbol before position `at`."""

    def one(nodes, root, size, raw):
        if nodes is None:
            return [(int((raw[:at] == symbol).sum()),)]
        where = paths(root).get(symbol)
        out = []
        for b, n in enumerate(size.tolist()):
            i = min(at, n) if where else 0
            for node, side in _step(root, where[0]) if where else ():
                if i == 0 or node.prefix not in nodes:
                    i = 0
                    break
                data, count = nodes[node.prefix]
                begin = int(offsets(count)[b])
                ones = int(data[begin : begin + i].sum())
                i = ones if side else i - ones
            if where and where[2] and i:
                data, count = nodes[where[0]]
                begin = int(offsets(count)[b])
                i = int((data[begin : begin + i] == where[1]).sum())
            out.append([(i,)])
        return out

    return _scan(enc, "found long", ["found"], one, shape)


def select(enc: DataFrame, symbol: int, k: int, shape: str = "flat_opt") -> DataFrame:
    """(.., pos) of the k-th occurrence (from 0) in each block that has one."""
    from pyspark.sql import Window
    from pyspark.sql import functions as F

    w = Window.partitionBy("stream_id", "value_id", "block_no").orderBy("pos")
    return positions(enc, symbol, shape, limit=k + 1).withColumn("nth", F.row_number().over(w) - 1).where(F.col("nth") == k).drop("nth")


