"""Decoding strategies: the code tree with an operation at each node, from code lengths alone.

A plan starts as the binary tree of the canonical code and is rewritten by rules,
each of which leaves the decoded output as it is:

* flatten: a subtree whose leaves are all D levels down becomes one D-bit lookup,
* regroup: symbols of one length are first put into runs of powers of two, each
  a virtual leaf D levels up, so that as much as possible flattens,
* fuse (top-down only): two sibling leaves become one two-way scatter,
* prefill (top-down only): the most frequent symbol is written beforehand.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np

from treepack.plans.codebook import unpack_lengths

MODES = ("naive", "flat", "flat_opt")
TOPDOWN = ("naive", "fused", "prefill", "flat", "flat_opt")


@dataclass
class Node:
    """leaf: symbols has one; flat: 2**d symbols by index; inner: two children."""

    prefix: str
    symbols: list[int] = field(default_factory=list)
    d: int = 0
    left: Node | None = None
    right: Node | None = None

    @property
    def leaf(self) -> bool:
        return self.left is None and self.d == 0

    @property
    def flat(self) -> bool:
        return self.d > 0

    @property
    def inner(self) -> bool:
        return self.left is not None

    @property
    def depth(self) -> int:
        return len(self.prefix)

    @property
    def two_leaves(self) -> bool:
        return self.inner and self.left.leaf and self.right.leaf

    @property
    def counted(self) -> bool:
        """Whether the container holds the number of right symbols: only if both children hold data."""
        return self.inner and not self.left.leaf and not self.right.leaf

    def walk(self):
        """Pre-order; the order of nodes in a block."""
        todo = [self]
        while todo:
            n = todo.pop()
            yield n
            if n.inner:
                todo += [n.right, n.left]


def _units(lengths: np.ndarray, mode: str, min_flat: int) -> list[tuple[int, list[int], int]]:
    """(depth, symbols, d) of the leaves, virtual ones too."""
    groups: dict[int, list[int]] = {}
    for s, n in enumerate(lengths):
        if n:
            groups.setdefault(int(n), []).append(s)
    out = []
    for n, symbols in groups.items():
        if mode != "flat_opt":
            out += [(n, [s], 0) for s in symbols]
            continue
        at = 0
        while at < len(symbols):
            d = (len(symbols) - at).bit_length() - 1
            out.append((n - d, symbols[at : at + (1 << d)], d))
            at += 1 << d
    return sorted(out, key=lambda u: (u[0], u[1][0], u[2]))


@lru_cache(maxsize=1024)
def shape_of(packed: bytes, mode: str = "flat_opt", min_flat: int = 2) -> Node | None:
    return build_shape(unpack_lengths(packed), mode, min_flat)


def build_shape(lengths: np.ndarray, mode: str = "flat_opt", min_flat: int = 2) -> Node | None:
    """The plan for bottom-up decoding and for encoding; None where no bit is needed (at most one symbol)."""
    if mode not in MODES:
        raise ValueError(f"unknown shape {mode!r}; one of {', '.join(MODES)}")
    units = _units(np.asarray(lengths), mode, min_flat)
    if len(units) < 2 and (not units or units[0][2] == 0):
        return None
    root = Node("")
    code, last = 0, 0
    for depth, symbols, d in units:
        code <<= depth - last
        _insert(root, format(code, f"0{depth}b") if depth else "", symbols, d)
        code, last = code + 1, depth
    if mode == "flat":
        root = flatten(root, min_flat)
    return _pairs(root, min_flat)


def _insert(root: Node, path: str, symbols: list[int], d: int) -> None:
    at = root
    for k, bit in enumerate(path):
        if at.left is None:
            at.left, at.right = Node(at.prefix + "0"), Node(at.prefix + "1")
        at = at.right if bit == "1" else at.left
    at.symbols, at.d = symbols, d


def _pairs(node: Node, min_flat: int) -> Node:
    """Flat nodes under min_flat bits become binary again: a pair of symbols stays a node that can be entropy coded."""
    if node.inner:
        node.left, node.right = _pairs(node.left, min_flat), _pairs(node.right, min_flat)
    elif node.flat and node.d < min_flat:
        half = len(node.symbols) // 2
        parts = [Node(node.prefix + b, node.symbols[k * half : (k + 1) * half], node.d - 1) for k, b in enumerate("01")]
        return _pairs(Node(node.prefix, left=parts[0], right=parts[1]), min_flat)
    return node


def flatten(node: Node, min_flat: int = 2) -> Node:
    """Subtrees whose leaves are all equally deep become one lookup."""
    if not node.inner:
        return node
    node.left, node.right = flatten(node.left, 1), flatten(node.right, 1)
    d = node.left.d
    if not node.left.inner and not node.right.inner and node.right.d == d:
        return Node(node.prefix, node.left.symbols + node.right.symbols, d + 1)
    return node


def paths(root: Node) -> dict[int, tuple[str, int, int]]:
    """symbol -> (prefix of its leaf or flat node, index in it, bits of that index)."""
    return {s: (n.prefix, i, n.d) for n in root.walk() if not n.inner for i, s in enumerate(n.symbols)}


def plan_rows(root: Node | None) -> list[tuple]:
    """(node_id, depth, prefix, op, left, right, d, symbols) in pre-order."""
    if root is None:
        return []
    nodes = list(root.walk())
    ids = {id(n): k for k, n in enumerate(nodes)}
    return [(k, n.depth, n.prefix, operation(n), ids[id(n.left)] if n.inner else None, ids[id(n.right)] if n.inner else None, n.d, [int(s) for s in n.symbols]) for k, n in enumerate(nodes)]


def operation(n: Node) -> str:
    if n.leaf:
        return "leaf"
    if n.flat:
        return f"flat_{n.d}"
    return "merge_" + "_".join("cst" if c.leaf else "vec" for c in (n.left, n.right))


# --- cost --------------------------------------------------------------------


def weights(root: Node, counts: np.ndarray) -> dict[str, int]:
    """How many symbols reach each node, by prefix."""
    out: dict[str, int] = {}

    def of(n: Node) -> int:
        out[n.prefix] = sum(int(counts[s]) for s in n.symbols) if not n.inner else of(n.left) + of(n.right)
        return out[n.prefix]

    of(root)
    return out


def ops_bottomup(root: Node | None, counts: np.ndarray) -> tuple[int, int]:
    """(nodes with work, operations on symbols in all): a leaf costs nothing, a flat node one operation."""
    if root is None:
        return 0, 0
    w = weights(root, counts)
    busy = [n for n in root.walk() if not n.leaf]
    return len(busy), sum(w[n.prefix] for n in busy)


def ops_topdown(lengths: np.ndarray, counts: np.ndarray, mode: str) -> int:
    """Operations on symbols of a top-down decode: a partition per inner node, a scatter per leaf, less what the mode saves."""
    if mode not in TOPDOWN:
        raise ValueError(f"unknown mode {mode!r}; one of {', '.join(TOPDOWN)}")
    root = build_shape(lengths, {"flat": "flat", "flat_opt": "flat_opt"}.get(mode, "naive"))
    if root is None:
        return 0
    w = weights(root, counts)
    free = most_frequent_leaf(root, lengths) if mode in ("prefill", "flat", "flat_opt") else None
    total = 0
    for n in root.walk():
        if not n.leaf:
            total += w[n.prefix]
        elif n.prefix != free and not (mode != "naive" and _paired(root, n)):
            total += w[n.prefix]
    return total


def most_frequent_leaf(root: Node, lengths: np.ndarray) -> str | None:
    """Prefix of the leaf to prefill: the shortest code, if it is a leaf of its own."""
    leaves = [n for n in root.walk() if n.leaf]
    best = min(leaves, key=lambda n: (n.depth, n.symbols[0]), default=None)
    shortest = min((int(x) for x in lengths if x), default=0)
    return best.prefix if best is not None and best.depth == shortest else None


def _paired(root: Node, leaf: Node) -> bool:
    at = root
    for bit in leaf.prefix[:-1]:
        at = at.right if bit == "1" else at.left
    return at.two_leaves
