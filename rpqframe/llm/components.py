"""Connected components by alternating star operations, without collecting anything."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rpqframe.llm.common import checkpoint


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
    return both.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = down.groupBy("a").agg(F.min("b").alias("m"))
    joined = down.join(least, "a")
    moved = joined.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return moved.union(least.select("a", F.col("m").alias("b"))).where("a <> b").distinct()


def connected_components(links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, component) for each node with a link; component is its smallest node.

    ``links`` has columns a and b. Each round alternates a large and a small star; the edge
    set has converged when two rounds agree in count and in an order-free hash. Raises when
    ``max_rounds`` do not suffice (a round at least halves the depth of every tree).
    """
    edges = checkpoint(links.select("a", "b").where("a <> b").distinct())
    seen = None
    for _ in range(max_rounds):
        edges = checkpoint(_small_star(_large_star(edges)))
        state = edges.agg(F.count("*"), F.expr("bit_xor(xxhash64(a, b))"), F.expr("bit_xor(xxhash64(b))")).first()
        if state == seen:
            low = edges.select(F.col("a").alias("node"), F.col("b").alias("component"))
            return low.union(edges.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
        seen = state
    raise RuntimeError(f"components did not converge in {max_rounds} rounds")
