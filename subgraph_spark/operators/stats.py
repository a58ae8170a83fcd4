"""Properties of targets, and small graph utilities."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import TargetGraph
from ..session import materialise


def properties(target: TargetGraph) -> DataFrame:
    """One row: vertices, edges, degree (in + out, pairs) mean, deviation and maximum, labels."""
    d = target.degrees().withColumn("deg", F.col("indeg") + F.col("outdeg"))
    row = d.agg(F.count("*").alias("vertices"), F.round(F.avg("deg"), 6).alias("degree_mean"), F.round(F.stddev_pop("deg"), 6).alias("degree_sd"), F.max("deg").alias("degree_max"), F.count_distinct("vlabel").alias("labels"))
    return row.crossJoin(target.edges.agg(F.count("*").alias("edges"))).select(F.lit(target.name).alias("target"), "vertices", "edges", "degree_mean", "degree_sd", "degree_max", "labels")


def collection_table(targets: list[TargetGraph]) -> DataFrame:
    return reduce(DataFrame.unionByName, map(properties, targets))


def label_histogram(target: TargetGraph) -> DataFrame:
    return target.vertices.groupBy("vlabel").agg(F.count("*").alias("n"))


def hubs(target: TargetGraph, k: int = 20) -> DataFrame:
    return target.degrees().select("vid", (F.col("indeg") + F.col("outdeg")).alias("deg")).orderBy(F.desc("deg"), "vid").limit(k)


def k_core(target: TargetGraph, k: int) -> DataFrame:
    """Vertices of the largest part in which everyone has ``k`` neighbours, whatever the direction.

    Rounds go on until none drops a pair: a chain loses its two ends a round.
    """
    both = target.pairs().filter("src <> dst")
    both = materialise(both.union(both.select("dst", "src")).distinct(), "pairs")
    n = both.count()
    while n:
        alive = both.groupBy("src").agg(F.count("*").alias("n")).filter(F.col("n") >= k).select("src")
        both = materialise(both.join(alive, "src", "left_semi").join(alive.withColumnRenamed("src", "dst"), "dst", "left_semi").select("src", "dst"), "core")
        before, n = n, both.count()
        if n == before:
            break
    return both.select(F.col("src").alias("vid")).distinct()


def weak_components(target: TargetGraph, most_rounds: int = 100) -> DataFrame:
    """(vid, component): the smallest vertex reachable, by passing minima on and jumping along them."""
    both = target.pairs()
    both = materialise(both.union(both.select("dst", "src")).filter("src <> dst").distinct(), "pairs")
    now = target.vertices.select("vid", F.col("vid").alias("component"))
    for _ in range(most_rounds):
        heard = both.join(now, both["dst"] == now["vid"]).groupBy("src").agg(F.min("component").alias("least"))
        least = now.join(heard, now["vid"] == heard["src"], "left").select("vid", F.least("component", F.coalesce("least", "component")).alias("component"))
        least = materialise(least, "minima")
        jump = least.select(F.col("vid").alias("component"), F.col("component").alias("further"))
        jumped = materialise(least.join(jump, "component").select("vid", F.col("further").alias("component")), "components")
        moved = jumped.join(now.withColumnRenamed("component", "before"), "vid").filter("component <> before").limit(1).count()
        now = jumped
        if not moved:
            return now
    raise RuntimeError("the components did not settle")


def neighbours(target: TargetGraph) -> DataFrame:
    """(vid, near): neighbours whatever the direction."""
    p = target.pairs()
    return p.select(F.col("src").alias("vid"), F.col("dst").alias("near")).union(p.select("dst", "src")).filter("vid <> near").distinct()


def induced_edges(target: TargetGraph, vertices: DataFrame) -> DataFrame:
    """Edges between the given vertices (vid)."""
    return target.edges.join(vertices.select(F.col("vid").alias("src")), "src", "left_semi").join(vertices.select(F.col("vid").alias("dst")), "dst", "left_semi")


def census3(target: TargetGraph) -> DataFrame:
    """Connected induced subgraphs of three vertices by shape: (code, n). The code packs the six possible arcs, the smallest over orders.

    Pairs are looked up once as a two-bit code; triples come from neighbours of both ends of an edge.
    """
    near = target.pairs().filter("src <> dst")
    both = near.select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b"), F.when(F.col("src") < F.col("dst"), 1).otherwise(2).alias("c"))
    both = materialise(both.groupBy("a", "b").agg(F.sum("c").alias("c")), "codes")
    around = both.select(F.col("a").alias("u"), F.col("b").alias("v")).union(both.select("b", "a"))
    paths = around.join(around.withColumnRenamed("v", "w"), "u").filter("v < w")
    triples = paths.select(F.array_sort(F.array("u", "v", "w")).alias("t")).distinct().select(*[F.col("t")[i].alias(x) for i, x in enumerate("xyz")])
    for p, q in (("x", "y"), ("x", "z"), ("y", "z")):
        triples = triples.join(both.select(F.col("a").alias(p), F.col("b").alias(q), F.col("c").alias(p + q)), [p, q], "left")
    arcs = triples.select(*[F.coalesce(k, F.lit(0)).alias(k) for k in ("xy", "xz", "yz")])
    turn = lambda k: F.when(F.col(k) == 0, 0).when(F.col(k) == 3, 3).otherwise(3 - F.col(k))
    code = lambda a, b, c: a * 16 + b * 4 + c
    f = F.col
    codes = [code(f("xy"), f("xz"), f("yz")), code(f("xz"), f("xy"), turn("yz")), code(turn("xy"), f("yz"), f("xz")), code(f("yz"), turn("xy"), turn("xz")), code(turn("xz"), turn("yz"), f("xy")), code(turn("yz"), turn("xz"), turn("xy"))]
    return arcs.groupBy(F.least(*codes).cast("int").alias("code")).agg(F.count("*").alias("n"))
