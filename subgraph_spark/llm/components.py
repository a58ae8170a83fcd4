"""Connected components of a graph too large for one machine, by alternating star contractions.

Edges are pairs of 64-bit nodes. A large-star step links every larger neighbour of a node to the smallest node it sees;
a small-star step does so for the node and its smaller neighbours. Each halves what lies between a node and its
component's smallest one, so a few rounds end in stars. A hub's edges are spread over tasks: minima are combined before the
shuffle, and the join that hands them out is one whose uneven sides Spark splits.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop, stage


def _to_smallest(edges: DataFrame, all_neighbours: bool) -> DataFrame:
    """From edges (a > b): per node n its smallest neighbour m; links (x, m) for the neighbours x on the one side."""
    if all_neighbours:
        sides = edges.select(F.col("a").alias("n"), F.col("b").alias("x")).unionByName(edges.select(F.col("b").alias("n"), F.col("a").alias("x")))
    else:
        sides = edges.select(F.col("a").alias("n"), F.col("b").alias("x"))
    least = sides.groupBy("n").agg(F.least(F.min("x"), F.col("n")).alias("m"))
    if all_neighbours:
        # Links go from the larger neighbours only; these are the edges (a, b) whose b is the node.
        linked = edges.select(F.col("b").alias("n"), F.col("a").alias("x")).join(least, "n").select(F.col("x").alias("a"), F.col("m").alias("b"))
    else:
        linked = sides.join(least, "n").select(F.col("x").alias("a"), F.col("m").alias("b")).unionByName(least.select(F.col("n").alias("a"), F.col("m").alias("b")))
    return linked.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """From edges (a, b) of longs to rows (node, root), root being the smallest node of the component.

    Nodes without an edge to another one don't appear. Self-loops, repeats and both directions are harmless.
    """
    now = stage(edges.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    seen = None
    for _ in range(most_rounds):
        # A round that changes no edge is the last.
        tell = now.agg(F.count("*").alias("n"), F.sum(F.hash("a", "b").cast("long")).alias("s"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("t")).first()
        if seen == tell:
            return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
        seen = tell
        large = stage(_to_smallest(now, True), "large-star")
        before, now = now, stage(_to_smallest(large, False), "small-star")
        drop(before, large)
    raise RuntimeError("the components did not settle")
