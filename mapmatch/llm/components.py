"""Connected components of an edge table, by alternating large-star and small-star rounds.

Every round rewrites the edges so that each node hangs from the smallest node it can see: first the larger
neighbours of a node move to its smallest neighbour, then the smaller ones do. The edges end as stars around the
smallest node of each component. A round is two aggregations with partial sums and two joins on node ids. The smallest
neighbours are written down before they are joined: only then do both sides of the join come from exchanges of their own,
so that the engine can split a node with very many neighbours over tasks. No node is gathered in one task's memory.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_stored, stored


def _large_star(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = stored(both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m")), "least")
    return both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct(), least


def _small_star(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = stored(down.groupBy("a").agg(F.min("b").alias("m")), "least")
    moved = down.join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return moved.unionByName(least.select("a", F.col("m").alias("b"))).where("a <> b").distinct(), least


def connected(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """node, root (the smallest node of its component) for every node of edges (columns a, b, both long).

    Nodes with a loop alone do not appear. Rounds go on until the edges stop changing.
    """
    now = stored(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    mark = None
    for _ in range(most_rounds):
        large, first = _large_star(now)
        middle = stored(large, "edges")
        small, second = _small_star(middle)
        new = stored(small, "edges")
        for done in (now, first, middle, second):
            drop_stored(done)
        now = new
        seen = now.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if seen == mark:
            return now.select(F.col("a").alias("node"), F.col("b").alias("root"))
        mark = seen
    raise RuntimeError("components did not settle")
