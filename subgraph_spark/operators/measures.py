"""Costs and speedups, as aggregates over tables of counts and runs."""

from __future__ import annotations

import contextlib
import resource
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

FUNNEL = "method string, depth int, pairs long, after_unused long, after_label_or_domain long, after_degree long, after_edges long"
RUNS = "instance_id string, collection string, method string, workers int, group_size int, rep int, prep_ms double, match_ms double, total_ms double, pairs long, matches long, steals_ok long, steals_failed long, peak_mem_mb double, timed_out boolean"
LIMIT_MS = 180_000.0
SHORT_MS = 1000.0


@contextlib.contextmanager
def timer(into: dict, name: str):
    """Milliseconds of a phase, added to ``into``."""
    began = time.monotonic()
    try:
        yield
    finally:
        into[name] = into.get(name, 0.0) + (time.monotonic() - began) * 1000


def peak_memory_mb() -> float:
    """The largest resident size that this process has had."""
    return resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024


def funnel(target, pattern, method: str = "ord", rounds: int | str = 1, label_match=None) -> DataFrame:
    """Pairs considered per depth, and those left after each rule."""
    from . import engines, expand

    ready = engines.prepare(target, pattern, method, rounds, label_match=label_match)
    found = [] if ready.infeasible else expand.funnel(target, ready.plan, ready.domains, label_match)
    return target.vertices.sparkSession.createDataFrame([(method, x["depth"], x["pairs"], x["after_unused"], x["after_label_or_domain"], x["after_degree"], x["after_edges"]) for x in found], FUNNEL)


def subtree_sizes(tree: DataFrame) -> DataFrame:
    """(node_id, depth, size): one join and aggregate per depth, from the leaves up."""
    from ..session import materialise

    tree = tree.select("node_id", "parent_id", "depth")
    deepest = tree.agg(F.max("depth")).first()[0]
    done = tree.filter(F.col("depth") == deepest).withColumn("size", F.lit(1).cast("long"))
    for depth in range((deepest or 0) - 1, -1, -1):
        below = done.filter(F.col("depth") == depth + 1).groupBy(F.col("parent_id").alias("node_id")).agg(F.sum("size").alias("below"))
        here = tree.filter(F.col("depth") == depth).join(below, "node_id", "left").withColumn("size", F.coalesce("below", F.lit(0)) + 1).drop("below")
        done = materialise(done.unionByName(here), "subtrees")
    return done.select("node_id", "depth", "size")


def large_branches(tree: DataFrame, share: float = 0.05) -> DataFrame:
    """(depth, branches): nodes whose subtree has ``share`` of all states or more."""
    return subtree_sizes(tree).crossJoin(tree.agg(F.count("*").alias("total"))).groupBy("depth").agg(F.count_if(F.col("size") >= share * F.col("total")).alias("branches"))


def branches_of_search(target, plan, share: float = 0.05) -> DataFrame:
    """``large_branches`` of a search in the order's plain method, whose tree may have any size: a level is a join, a subtree's size a sum over the level below.

    A node is its mapping. The last level's nodes are only counted, by their parents.
    """
    from ..session import materialise
    from . import expand

    info, frontier, levels = materialise(expand.vertex_info(target, plan, None), "vertex-info"), None, []
    keys = [expand.image(i) for i in range(len(plan.steps))]
    for step in plan.steps:
        pairs = expand.generate(frontier, target, plan, step, info, 10**7, label_early=False)
        if step.pos + 1 == len(plan.steps):
            levels.append(materialise(pairs.groupBy(*keys[: step.pos]).agg(F.count("*").alias("below")), "leaves"))
            break
        pairs = materialise(pairs, "pairs")
        levels.append(expand.grown(pairs, step))
        if step.anchor is not None and step.anchor.elabel is not None:
            pairs = expand.with_edge(pairs, target, step.anchor)
        frontier = materialise(expand.grown(expand.step_rules(pairs, target, plan, step, None, False), step), "frontier")
    below = levels.pop()
    leaves = below.agg(F.coalesce(F.sum("below"), F.lit(0))).first()[0]
    total = leaves + sum(x.count() for x in levels)
    spark = target.vertices.sparkSession
    out = spark.createDataFrame([(len(levels), leaves if 1 >= share * total else 0)], "depth int, branches long")
    for depth in range(len(levels) - 1, -1, -1):
        sized = materialise(levels[depth].join(below, keys[: depth + 1], "left").withColumn("size", F.coalesce("below", F.lit(0)) + 1).drop("below"), "subtrees")
        out = out.unionByName(sized.agg(F.lit(depth).alias("depth"), F.count_if(F.col("size") >= share * F.lit(total)).alias("branches")))
        below = sized.groupBy(*keys[:depth]).agg(F.sum("size").alias("below")) if depth else None
    return out


def speedups(base: DataFrame, new: DataFrame, workers: int | None = None) -> DataFrame:
    """Speedup of ``new`` over ``base`` (rows of RUNS, joined by instance): ratio of totals, geometric mean, extremes; all, short, long.

    Only instances that the baseline solves count; a run that timed out in ``new`` counts as the limit. Short is under a second in the baseline.
    """
    both = base.filter(~F.col("timed_out")).select("instance_id", F.col("total_ms").alias("base_ms")).join(new.select("instance_id", F.when(F.col("timed_out"), LIMIT_MS).otherwise(F.col("total_ms")).alias("new_ms")), "instance_id")
    both = both.withColumn("ratio", F.col("base_ms") / F.col("new_ms"))
    classes = F.explode(F.array(F.lit("all"), F.when(F.col("base_ms") < SHORT_MS, "short").otherwise("long"))).alias("class")
    out = both.select("*", classes).groupBy("class").agg(F.count("*").alias("instances"), F.round(F.sum("base_ms") / F.sum("new_ms"), 6).alias("speedup_avg"), F.round(F.exp(F.avg(F.ln("ratio"))), 6).alias("speedup_gmean"), F.round(F.max("ratio"), 6).alias("speedup_max"), F.round(F.min("ratio"), 6).alias("speedup_min"))
    return out if workers is None else out.withColumn("above_workers", F.col("speedup_max") > workers)


def unsolved(runs: DataFrame) -> DataFrame:
    """Instances that timed out, per method and number of workers."""
    return runs.groupBy("method", "workers").agg(F.count_if("timed_out").alias("unsolved"), F.count("*").alias("instances"))


def time_summary(runs: DataFrame) -> DataFrame:
    """Mean, deviation and standard error of times; mean and deviation of pairs; pairs per second."""
    n = F.count("*")
    return runs.groupBy("method", "workers").agg(n.alias("instances"), F.round(F.avg("total_ms"), 6).alias("mean_ms"), F.round(F.stddev_samp("total_ms"), 6).alias("sd_ms"), F.round(F.stddev_samp("total_ms") / F.sqrt(n), 6).alias("se_ms"), F.round(F.avg("pairs"), 6).alias("mean_pairs"), F.round(F.stddev_samp("pairs"), 6).alias("sd_pairs"), F.round(F.sum("pairs") / F.nullif(F.sum("match_ms"), F.lit(0.0)) * 1000, 6).alias("pairs_per_s"))


def time_reduction(base: DataFrame, new: DataFrame) -> DataFrame:
    """Mean total time before and after, its reduction in percent, and the factor."""
    a, b = base.agg(F.avg("total_ms").alias("before")), new.agg(F.avg("total_ms").alias("after"))
    return a.crossJoin(b).select(F.round("before", 6).alias("before_ms"), F.round("after", 6).alias("after_ms"), F.round((1 - F.col("after") / F.col("before")) * 100, 6).alias("reduction_pct"), F.round(F.col("before") / F.col("after"), 6).alias("factor"))


def state_spread(per_worker: DataFrame) -> DataFrame:
    """Deviation of the states per worker (``instance``, ``worker``, ``states``)."""
    return per_worker.groupBy("instance").agg(F.count("*").alias("workers"), F.sum("states").alias("states"), F.round(F.stddev_pop("states"), 6).alias("spread"))


def partition_skew(tagged: DataFrame) -> DataFrame:
    """Pairs per Spark task, from the engine's tagged rows: what is uneven about a search on a cluster."""
    per = tagged.filter("kind = 'stat'").groupBy("part").agg(F.sum("pairs").alias("pairs"))
    return per.agg(F.count("*").alias("tasks"), F.sum("pairs").alias("pairs"), F.max("pairs").alias("most"), F.round(F.stddev_pop("pairs"), 6).alias("spread"))


def runs_table(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, RUNS)
