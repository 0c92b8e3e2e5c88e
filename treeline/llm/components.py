"""Connected components by alternating large-star and small-star rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored


def _directed(edges: DataFrame) -> DataFrame:
    return edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))


def large_star(edges: DataFrame) -> DataFrame:
    """Links every larger neighbour of a node to the least of the node and its neighbours. edges: a, b."""
    both = _directed(edges)
    least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
    return both.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()


def small_star(edges: DataFrame) -> DataFrame:
    """Links a node and its smaller neighbours to the least of them. edges: a, b."""
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = down.groupBy("a").agg(F.min("b").alias("m"))
    joined = down.join(least, "a")
    return (
        joined.select(F.col("b").alias("a"), F.col("m").alias("b"))
        .union(least.select("a", F.col("m").alias("b")))
        .where("a <> b")
        .distinct()
    )


def components(edges: DataFrame, rounds: int = 40) -> DataFrame:
    """node, root (the least node it reaches) for every node of edges (a, b, of one orderable type, a <> b, no nulls).

    Stars shrink to a fixed point in O(log n) rounds; a node's neighbours are only ever counted and joined, never
    gathered. Only the number of changed links comes to the driver. Repeated links and both directions are fine.
    """
    now = stored(edges.select("a", "b").where("a <> b").distinct(), "links")
    for _ in range(rounds):
        after = stored(small_star(large_star(now)), "links")
        ends = after.select(F.col("a").alias("v"), F.lit(1).alias("up"), F.lit(0).alias("down")).union(after.select("b", F.lit(0), F.lit(1)))
        ends = ends.groupBy("v").agg(F.sum("up").alias("up"), F.max("down").alias("down"))
        # at the fixed point every link leads from a node to its root, and no root has a root
        if ends.where("up > 1 or (up = 1 and down = 1)").isEmpty():
            now = after
            break
        now = after
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).union(
        now.select(F.col("b").alias("node"), F.col("b").alias("root"))
    ).distinct()
