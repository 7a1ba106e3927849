"""Connected components by alternating star contraction (Kiveris et al., 2014)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .stages import cut, drop


def _large_star(edges: DataFrame) -> DataFrame:
    """Each larger neighbour of a node is tied to the node's smallest neighbour (or itself)."""
    both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    return both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _small_star(edges: DataFrame) -> DataFrame:
    """Each node's smaller neighbours and itself are tied to the smallest of them."""
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    moved = down.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(least.select("u", F.col("m").alias("v")))


def connected_components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """``edges(u, v)`` of ordered ids -> ``(node, root)`` for every node with an edge.

    ``root`` is the smallest node of the component. Minima are pre-aggregated, and a
    node with very many edges meets them in a join that AQE can split; state between
    rounds is a table in the shared folder.
    """
    now = cut(edges.where("u <> v").select("u", "v").distinct(), "edges")
    was = None
    for _ in range(rounds):
        large = _large_star(now).where("u <> v").distinct()
        new = cut(_small_star(large).where("u <> v").distinct(), "edges")
        state = new.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        drop(now)
        now = new
        if state == was:
            break
        was = state
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    least = now.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return least.union(least.select(F.col("root").alias("node"), "root").distinct())
