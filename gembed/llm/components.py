"""Connected components of an edge table: alternating large and small stars, each a join and an aggregate.

A step keeps the components and pulls every node nearer to its component's smallest id; it ends when
each node has one edge and that leads to a root. Nothing is collected but two counts a round. A hub
with many neighbours is one side of an equi-join, which adaptive execution splits.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import forget, stored


def _toward_min(pairs: DataFrame, edges: DataFrame) -> DataFrame:
    """For each node u of pairs (u, v): every v of ``edges`` joined to the least of u and its v's."""
    least = pairs.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
    return edges.join(least, "u")


def _large(edges: DataFrame) -> DataFrame:
    both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    return _toward_min(both, both.where("v > u")).select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()


def _small(edges: DataFrame) -> DataFrame:
    """edges (u, v) with v < u: u and its smaller neighbours all point to the least of them."""
    hung = _toward_min(edges, edges)
    return hung.select(F.col("v").alias("u"), F.col("m").alias("v")).union(hung.select("u", F.col("m").alias("v"))).where("u != v").distinct()


def is_star(edges: DataFrame) -> bool:
    """Whether every u has one v and no v is itself a u."""
    once = edges.groupBy("u").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n").alias("n")).first()["n"]
    return (once or 1) == 1 and edges.join(edges.select(F.col("u").alias("v")), "v", "left_semi").isEmpty()


def components(edges: DataFrame, a: str, b: str, rounds: int = 60) -> DataFrame:
    """(node, root) of every node but the roots; root is the smallest id of the component."""
    now = stored(edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u != v").distinct(), "links")
    for _ in range(rounds):
        if is_star(now):
            return now.select(F.col("u").alias("node"), F.col("v").alias("root"))
        large = stored(_large(now), "large-star")
        forget(now)
        now = stored(_small(large), "small-star")
        forget(large)
    raise RuntimeError(f"components did not settle in {rounds} rounds")
