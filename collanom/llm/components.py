"""Connected components of a link table by alternating star contraction, on DataFrames only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, join_by_hot_key, stored


def _both(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(edges.select(F.col("b").alias("u"), F.col("a").alias("v")))


def _large_star(edges: DataFrame, n: int) -> DataFrame:
    """Each larger neighbour of a node is tied to the least node around it."""
    sides = _both(edges)
    least = sides.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"), F.count("*").alias("n"))
    tied = join_by_hot_key(sides, least, "u", 2 * n).where("v > u and v <> m")
    return tied.select(F.col("m").alias("a"), F.col("v").alias("b")).distinct()


def _small_star(edges: DataFrame, n: int) -> DataFrame:
    """Each smaller neighbour of a node, and the node, are tied to the least of them."""
    sides = edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
    least = sides.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n"))
    tied = join_by_hot_key(sides, least, "u", n).where("v <> m").select(F.col("m").alias("a"), F.col("v").alias("b"))
    return tied.unionByName(least.select(F.col("m").alias("a"), F.col("u").alias("b"))).distinct()


def _state(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root) for every node of the links (a, b); root is the least node of the component.

    Every round is written to the shared folder, so a lost executor costs one round at most. The driver
    sees two numbers a round. A node with very many links (a hub) is spread over the tasks.
    """
    now = stored(edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())
    state = _state(now)
    for _ in range(max_rounds if state[0] else 0):
        larger = stored(_large_star(now, state[0]))
        last, now = now, stored(_small_star(larger, state[0]))
        discard(larger, last)
        before, state = state, _state(now)
        if state == before:
            break
    else:
        if state[0]:
            raise RuntimeError(f"no fixed point after {max_rounds} rounds")
    stars = now.select(F.col("b").alias("node"), F.col("a").alias("root"))
    return stars.unionByName(now.select(F.col("a").alias("node"), F.col("a").alias("root")).distinct())
