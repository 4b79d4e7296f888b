"""Connected components of a graph given as a table of links."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialize


def _large_star(edges: DataFrame) -> DataFrame:
    """Links every larger neighbour of a node to the least of the node and its neighbours."""
    both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
    return both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """Links a node and its smaller neighbours to the least of them."""
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = down.groupBy("a").agg(F.min("b").alias("m"))
    low = down.join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return low.union(least.select("a", F.col("m").alias("b"))).where("a <> b").distinct()


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, label) for every node of the links (a, b); label is the least node of the component.

    Alternates the two star steps, each a pair of shuffles on narrow rows, until the links no longer change; then each
    node hangs from its label. The links of each round are written to the shared folder, so lineage stays short and no
    link reaches the driver. Self-links are dropped, so a node with no other link is not returned. Repeated links count
    once.
    """
    edges = materialize(edges.where("a <> b").select("a", "b").distinct(), "links")
    mark = None
    for _ in range(max_rounds):
        before, edges = edges, materialize(_small_star(_large_star(edges)), "links")
        discard(before)
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == mark:
            nodes = edges.select(F.col("a").alias("node"), F.col("b").alias("label"))
            return nodes.union(edges.select(F.col("b").alias("node"), F.col("b").alias("label")).distinct())
        mark = now
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
