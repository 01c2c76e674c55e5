"""Which node bitmaps to entropy-code: gates on size, skew and gain, from counts alone, and the choice of a static table."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treepack.functions import fsm
from treepack.plans.shape import Node, weights


@dataclass(frozen=True)
class Gates:
    """min_bitmap_bytes, min_skew and max_cost_ratio are the three gates; scope 'stream' decides once per node for
    all blocks from the stream's counts, 'block' from each block's own popcount; span: blocks that share a table."""

    min_bitmap_bytes: int = 32
    min_skew: float = 0.625
    max_cost_ratio: float = 0.95
    scope: str = "block"
    span: int = 1
    cursors: int = fsm.CURSORS
    table_log: int = fsm.TABLE_LOG
    coder: str = "tans"  # or rle, zlib, custom_tans

    def __post_init__(self):
        if self.scope not in ("stream", "block"):
            raise ValueError(f"gate scope is 'stream' or 'block', not {self.scope!r}")


def entropy_of_bit(p):
    p = np.clip(np.asarray(p, np.float64), 1e-12, 1 - 1e-12)
    return -(p * np.log2(p) + (1 - p) * np.log2(1 - p))


def choose_table(n: np.ndarray, n_right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(table id from 1, whether bits are complemented): the tables are built for mostly zero bits."""
    n, n_right = np.asarray(n, np.int64), np.asarray(n_right, np.int64)
    flip = n_right * 2 > n
    percent = 100 * np.where(flip, n_right, n - n_right) / np.maximum(n, 1)  # one division, so that a half is a half
    return np.clip(np.floor(percent + 0.5).astype(np.int64), 50, 99) - 49, flip


def passes(n: np.ndarray, n_right: np.ndarray, depth: int, gates: Gates, sized: np.ndarray | None = None) -> np.ndarray:
    """Whether bitmaps of n bits, n_right of them set, at this depth are worth coding. sized: bits of a block, where n is a whole stream's."""
    n = np.asarray(n, np.int64)
    ids, _ = choose_table(n, n_right)
    major = np.maximum(n_right, n - n_right) / np.maximum(n, 1)
    cost = fsm.bit_costs(gates.table_log)[ids - 1]
    bits = n if sized is None else np.asarray(sized)
    return (bits >= 8 * gates.min_bitmap_bytes) & (major > gates.min_skew) & ((depth + cost) / (depth + 1) < gates.max_cost_ratio)


def stream_choice(root: Node, counts: np.ndarray, gates: Gates, block_size: int) -> dict[str, int]:
    """prefix -> table id (negative: complemented) of the nodes that pass on the whole stream's counts."""
    w, out = weights(root, counts), {}
    total = max(1, w[""])
    for n in root.walk():
        if n.inner:
            all_, right = np.array([w[n.prefix]]), np.array([w[n.right.prefix]])
            if passes(all_, right, n.depth, gates, all_ * block_size // total)[0]:
                ids, flip = choose_table(all_, right)
                out[n.prefix] = int(-ids[0] if flip[0] else ids[0])
    return out


def skew_report(hist: DataFrame, codes: DataFrame) -> DataFrame:
    """(stream_id, prefix, depth, n, n_right, skew, h, saving) of every binary node, from
    hist(stream_id, sym, cnt) and codes(stream_id, sym, len, code) with code as a bit string: no pass over the data."""
    each = hist.join(codes, ["stream_id", "sym"]).select("stream_id", "cnt", "code", F.explode(F.sequence(F.lit(0), F.col("len") - 1)).alias("depth"))
    node = each.groupBy("stream_id", F.expr("substring(code, 1, depth)").alias("prefix"), "depth").agg(
        F.sum("cnt").alias("n"), F.sum(F.when(F.expr("substring(code, depth + 1, 1)") == "1", F.col("cnt")).otherwise(0)).alias("n_right")
    )
    total = hist.groupBy("stream_id").agg(F.sum("cnt").alias("total"))
    p = F.col("n_right") / F.col("n")
    h = F.when((p <= 0) | (p >= 1), 0.0).otherwise(-(p * F.log2(p) + (1 - p) * F.log2(1 - p)))
    out = node.join(total, "stream_id").withColumn("skew", F.greatest(p, 1 - p)).withColumn("h", h)
    return out.select("stream_id", "prefix", "depth", "n", "n_right", "skew", "h", (F.col("n") / F.col("total") * (1 - F.col("h"))).alias("saving"))


def gate_nodes(nodes: DataFrame, block_size: int = 8192, gates: Gates = Gates()) -> DataFrame:
    """skew_report rows with gated: the three gates on stream statistics, the entropy standing in for a table's cost."""
    total = nodes.where("depth = 0").select("stream_id", F.col("n").alias("_total"))
    share = F.floor(F.col("n") * block_size / F.col("_total"))
    ok = (share >= 8 * gates.min_bitmap_bytes) & (F.col("skew") > gates.min_skew) & ((F.col("depth") + F.col("h")) / (F.col("depth") + 1) < gates.max_cost_ratio)
    return nodes.join(total, "stream_id").withColumn("gated", ok).drop("_total")
