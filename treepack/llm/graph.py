"""Connected components over DataFrames of edges, by alternating star contraction."""

from __future__ import annotations

from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treepack.llm.common import scratch, stage


def connected_components(edges: DataFrame, name: str = "components") -> DataFrame:
    """edges(a long, b long) -> (node long, root long), root the smallest node reachable.

    Every round joins each node to the least of its neighbours, once seen from
    the larger side and once from the smaller. Each row is an edge; no node's
    neighbours are gathered into one row, minima are pre-aggregated before the
    shuffle, and skewed joins are left to adaptive execution. Self loops and
    repeated edges are ignored; an empty input gives an empty result.
    """
    spark = edges.sparkSession
    with scratch(spark) as keep:
        now = stage(_ordered(edges.select("a", "b")), f"{name}-0")
        # ends: a round that changes an edge moves it to a smaller node, which can't go on for ever
        for k in count(1):
            if _settled(now):
                break
            with scratch(spark) as keep_round:
                now = keep_round(stage(_small(_large(now)), f"{name}-{k}"))
        keep(now)
    # all edges now are (node, root)
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).union(now.select(F.col("b"), F.col("b")).distinct())


def _ordered(e: DataFrame) -> DataFrame:
    """Edges from the larger to the smaller node, each once."""
    return e.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def _large(e: DataFrame) -> DataFrame:
    both = e.union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
    return both.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()


def _small(e: DataFrame) -> DataFrame:
    """Of distinct edges from larger to smaller nodes, as _large gives them."""
    least = e.groupBy("a").agg(F.min("b").alias("m"))
    moved = e.join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return moved.union(least.select("a", F.col("m").alias("b"))).where("a <> b").distinct()


def _settled(e: DataFrame) -> bool:
    """Whether the edges are stars: each node has one edge to a smaller one, or none and is the root of others."""
    ends = e.select(F.col("a").alias("node"), F.lit(1).alias("up"), F.lit(0).alias("down")).union(e.select("b", F.lit(0), F.lit(1)))
    of_node = ends.groupBy("node").agg(F.sum("up").alias("up"), F.max("down").alias("down"))
    return of_node.where("up > 1 or up + down > 1").agg(F.count("*")).first()[0] == 0
