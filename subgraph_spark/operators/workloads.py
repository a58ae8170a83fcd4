"""The experiments, re-expressed on the given tables.

A collection is a list of targets; an instance is a target and a pattern taken from it, of a size, density and draw. A row per
instance is dealt to tasks, which hold the target's arrays: they extract the pattern, prepare the domains, search, and
simulate stealing there. Nothing but the rows of results leaves a task. Clocks go to the benchmark; what is registered as a query is
counted in pairs and ticks, and so repeats exactly.
"""

from __future__ import annotations

import dataclasses
import json
import time
from collections.abc import Callable, Iterator, Sequence
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import Csr, PatternGraph, TargetGraph
from ..plans import order as orders
from ..plans.search_plan import build
from ..session import materialise
from ..sources import array_files
from . import array_domains, baselines, measures, patterns, steal_sim
from .dfs import Counters, Kernel, task_tree

#: Edges of the pattern sets; the sparse collection stops at 128.
EDGES = (4, 8, 16, 32, 64, 128, 256)
DENSITIES = ("dense", "semi", "sparse")
#: Stand-ins for the collections: dense with many labels, denser with few, sparse with few.
COLLECTIONS = {"dense_many_labels": ("supplier_echo", "part_flow"), "denser_few_labels": ("user_relay",), "sparse": ("commerce", "turn_chain")}
#: Instances with fewer pairs (or ticks) than this, in the baseline, are short where no clock is read.
SHORT_PAIRS = 100_000
SHORT_TICKS = 1_000

#: A draw that falls into too small a part of its target is drawn again, so many times.
TRIES, TRY = 20, 1_000

INSTANCE = "collection string, instance string, edges int, density string, draw int"
SEARCHES = INSTANCE + ", vertices int, method string, prep_ms double, match_ms double, total_ms double, pairs long, matches long, cut boolean, peak_mb double, pattern string"
TREES = INSTANCE + ", method string, whole boolean, roots long, last int, root_at array<long>, depth array<int>, generated array<long>, first array<long>, kids array<long>"
SIMULATED = INSTANCE + ", method string, workers int, group_size int, seed int, stealing boolean, pairs long, makespan long, spread double, steals_ok long, steals_failed long"


def as_text(pattern: PatternGraph) -> str:
    return json.dumps([pattern.labels, pattern.edges])


def prepared(csr: Csr, pattern: PatternGraph, method: str, order: Sequence[int] | None = None) -> Kernel | None:
    """A kernel for one search over the arrays; None if a domain is empty."""
    return next(kernels(csr, pattern, [method], order))[1]


def kernels(csr: Csr, pattern: PatternGraph, methods: Sequence[str], order: Sequence[int] | None = None) -> Iterator[tuple[str, Kernel | None, float]]:
    """A kernel per method, and its milliseconds of preparation. The domains that methods have in common are made once, and count for each; a kernel is used before the next is taken."""
    masks, sizes, shared_ms = None, (), 0.0
    for at, method in enumerate(methods):
        began = time.monotonic()
        if method == "ord":
            kernel = Kernel(csr, build(pattern, "ord", order=order))
            yield method, kernel, (time.monotonic() - began) * 1000
            continue
        if masks is None:
            masks, sizes = array_domains.prepare(csr, pattern, "dom")
            shared_ms = (time.monotonic() - began) * 1000
            began = time.monotonic()
        own, now = masks, sizes
        if method in ("dom_f", "dom_sf") and 0 not in sizes:
            own = masks.copy() if any(m != "ord" for m in methods[at + 1 :]) else masks
            now = array_domains.forward_check(pattern, own, sizes)
        kernel = None if 0 in now else Kernel(dataclasses.replace(csr, masks=own), build(pattern, method, now, order))
        yield method, kernel, shared_ms + (time.monotonic() - began) * 1000
        del kernel, own


def explored(kernel: Kernel, budget: int, time_limit_s: float | None = None) -> tuple[Counters, bool]:
    """A whole search, or the part that the budget of pairs allows; and whether something was left."""
    counters, left = Counters(), False
    end = None if time_limit_s is None else time.monotonic() + time_limit_s
    width = len(kernel.plan.steps)
    block = max(256, min((1 << 19) // width, (1 << 23) // width**2))  # a level of the stack holds a block of whole mappings, and there are as many levels as vertices
    for kind, _ in kernel.run(kernel.seeds(None, counters), counters, budget, end, block=block):
        left = left or kind == "todo"
    return counters, left


def first_edges(spark: SparkSession, arrays: Callable[[], Csr], draws: Sequence[int]) -> dict[int, int]:
    """The edge that each draw's patterns grow from; a task per draw."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            yield pd.DataFrame({"draw": batch["draw"], "key": [patterns.first_edge(arrays(), int(x)) for x in batch["draw"]]})

    rows = spark.createDataFrame([(x,) for x in draws], "draw int").repartition(len(draws))
    return {x.draw: x.key for x in rows.mapInPandas(run, "draw int, key long").collect()}


def on_instances(collection: str, targets: Sequence[TargetGraph], work, schema: str, edges=EDGES, densities=DENSITIES, draws=(1,), parts: Sequence[int] = (0,), max_bytes: int | None = None) -> DataFrame:
    """``work(csr, pattern, part)`` yields tuples, which follow the instance's columns in the rows of ``schema``; a task per instance and part.
    Instances whose target is too small for the size are left out. Arrays of more than ``max_bytes`` are mapped files."""
    out = []
    names = [x.strip().split(" ")[0] for x in schema.split(",")]
    for t in targets:
        spark = t.vertices.sparkSession
        arrays = array_files.opener(t, max_bytes)
        firsts = first_edges(spark, arrays, draws) if array_files.are_mapped(arrays) else {}
        rows = [(collection, t.name, n, d, s, k) for n in edges for d in densities for s in draws for k in parts]
        dealt = spark.createDataFrame(rows, "collection string, target string, edges int, density string, draw int, part int").repartition(len(rows), "edges", "density", "draw", "part")

        def run(batches: Iterator[pd.DataFrame], arrays=arrays, firsts=firsts) -> Iterator[pd.DataFrame]:
            for batch in batches:
                for x in batch.itertuples(index=False):
                    csr = arrays()
                    tries = (patterns.extract(csr, int(x.edges), x.density, int(x.draw) + TRY * k, first=None if k else firsts.get(x.draw)) for k in range(TRIES))
                    pattern = next((p for p in tries if len(p.edges) == x.edges), None)
                    if pattern is not None:
                        key = x.collection, f"{x.target}/{x.density}-{x.edges}-{x.draw}", x.edges, x.density, x.draw
                        yield pd.DataFrame([(*key, *y) for y in work(csr, pattern, int(x.part))], columns=names)

        out.append(dealt.mapInPandas(run, schema))
    return reduce(DataFrame.unionByName, out)


def searches(collection: str, targets: Sequence[TargetGraph], methods: Sequence[str], budget: int = 1_000_000, time_limit_s: float | None = None, **which) -> DataFrame:
    """A row of SEARCHES per instance and method. A search ends after ``budget`` pairs, and then is marked as cut."""

    def work(csr: Csr, pattern: PatternGraph, _: int):
        for method, kernel, prep in kernels(csr, pattern, methods):
            ready = time.monotonic()
            counters, left = (Counters(), False) if kernel is None else explored(kernel, budget, time_limit_s)
            match = (time.monotonic() - ready) * 1000
            yield pattern.size, method, prep, match, prep + match, counters.pairs, counters.matches, left, measures.peak_memory_mb(), as_text(pattern)

    return on_instances(collection, targets, work, SEARCHES, **which)


def classed(found: DataFrame, baseline: str) -> DataFrame:
    """``found`` with each instance's class by the baseline's pairs, and whether any method left it unfinished."""
    base = found.filter(F.col("method") == baseline).select("instance", F.when(F.col("pairs") < SHORT_PAIRS, "short").otherwise("long").alias("class"))
    return found.join(base, "instance").join(found.groupBy("instance").agg(F.max("cut").alias("open")), "instance")


def space_summary(found: DataFrame, baseline: str = "dom") -> DataFrame:
    """Per class and method: instances, those that the method left unfinished, and over those that every method finished their number, matches, and pairs."""
    done = ~F.col("open")
    return classed(found, baseline).groupBy("collection", "class", "method").agg(
        F.count("*").alias("instances"),
        F.count_if("cut").alias("unfinished"),
        F.count_if(done).alias("finished_by_all"),
        F.sum(F.when(done, F.col("matches"))).alias("matches"),
        F.round(F.avg(F.when(done, F.col("pairs"))), 6).alias("mean_pairs"),
        F.round(F.stddev_pop(F.when(done, F.col("pairs"))), 6).alias("sd_pairs"),
    )


def long_sample(found: DataFrame, baseline: str = "dom", n: int = 10) -> DataFrame:
    """Of the ``n`` finished instances with the most pairs in the baseline: each method's pairs, and how they relate to the baseline's."""
    done = classed(found, baseline).filter(~F.col("open"))
    base = done.filter(F.col("method") == baseline).select("instance", F.col("pairs").alias("base_pairs")).orderBy(F.desc("base_pairs"), "instance").limit(n)
    return done.join(base, "instance").groupBy("collection", "method").agg(F.count("*").alias("instances"), F.sum("pairs").alias("pairs"), F.round(F.avg("pairs"), 6).alias("mean_pairs"), F.round(F.sum("pairs") / F.sum("base_pairs"), 6).alias("of_baseline"))


def unfinished(found: DataFrame) -> DataFrame:
    return found.groupBy("collection", "method").agg(F.count_if("cut").alias("unfinished"), F.count("*").alias("instances"))


def simulated(collection: str, targets: Sequence[TargetGraph], methods: Sequence[str] = ("ord",), workers=(1, 2, 4, 8, 16), groups=(4,), seeds=(0,), stealing=(True,), max_nodes: int | None = 30_000, **which) -> DataFrame:
    """A row of SIMULATED per instance, method and setting. Instances whose search tree has more than ``max_nodes`` under a method aren't simulated for it: their pairs are -1. None: all are."""
    fields = [f.name for f in dataclasses.fields(steal_sim.TaskTree)]

    def grow(csr: Csr, pattern: PatternGraph, _: int):
        for method, kernel, _ in kernels(csr, pattern, methods):
            try:
                tree = None if kernel is None else task_tree(kernel, max_nodes)
            except ValueError:
                yield method, False, *[None] * len(fields)
                continue
            yield method, True, *(None if tree is None else getattr(tree, k) for k in fields)

    names = [x.strip().split(" ")[0] for x in SIMULATED.split(",")]
    settings = [(w, g, on) for w in workers for g in (groups if w > 1 else groups[:1]) for on in (stealing if w > 1 else (True,))]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            for x in batch.itertuples(index=False):
                key = x.collection, x.instance, x.edges, x.density, x.draw, x.method
                if not x.whole:
                    out += [(*key, 1, 1, 0, True, -1, None, None, None, None)] if not x.part else []
                    continue
                tree = None if x.depth is None else steal_sim.TaskTree(int(x.roots), int(x.last), *(np.asarray(getattr(x, k)) for k in fields[2:]))
                for w, g, on in settings:
                    if w == 1 and x.part:
                        continue
                    if tree is None:
                        out.append((*key, w, g, seeds[x.part], on, 0, 1, 0.0, 0, 0))
                    else:
                        y = steal_sim.simulate_tasks(tree, w, g, seeds[x.part], on)
                        out.append((*key, w, g, seeds[x.part], on, sum(y.states), y.makespan, y.spread, y.steals_ok, y.steals_failed))
            yield pd.DataFrame(out, columns=names)

    trees = materialise(on_instances(collection, targets, grow, TREES, **which), "trees")
    dealt = trees.withColumn("part", F.explode(F.array(*[F.lit(k) for k in range(len(seeds))])))
    tasks = max(trees.sparkSession.sparkContext.defaultParallelism, trees.count() * len(seeds))
    return dealt.repartition(min(tasks, 1000), "instance", "method", "part").mapInPandas(run, SIMULATED)


def speedup_table(runs: DataFrame, base_method: str | None = None) -> DataFrame:
    """Speedups in ticks over one worker of the same method (or of ``base_method``), by class: ratio of totals, geometric mean, extremes."""
    base = runs.filter("workers = 1 and pairs >= 0").select("collection", "instance", F.col("method").alias("base_method"), F.col("makespan").alias("base"))
    same = F.col("base_method") == (F.col("method") if base_method is None else F.lit(base_method))
    both = runs.filter("pairs >= 0").join(base, ["collection", "instance"]).filter(same).withColumn("ratio", F.col("base") / F.col("makespan"))
    kinds = F.explode(F.array(F.lit("all"), F.when(F.col("base") < SHORT_TICKS, "short").otherwise("long"))).alias("class")
    out = both.select("*", kinds).groupBy("collection", "method", "workers", "class").agg(
        F.count("*").alias("runs"),
        F.round(F.sum("base") / F.sum("makespan"), 6).alias("speedup_avg"),
        F.round(F.exp(F.avg(F.ln("ratio"))), 6).alias("speedup_gmean"),
        F.round(F.max("ratio"), 6).alias("speedup_max"),
        F.round(F.min("ratio"), 6).alias("speedup_min"),
    )
    return out.withColumn("above_workers", F.col("speedup_max") > F.col("workers"))


def group_table(runs: DataFrame) -> DataFrame:
    """Makespan, spread and steals by workers, group size and stealing, over instances and draws."""
    mean = lambda c: F.round(F.avg(c), 6).alias(c)
    return runs.filter("pairs >= 0").groupBy("collection", "workers", "group_size", "stealing").agg(F.count("*").alias("runs"), mean("makespan"), mean("spread"), mean("steals_ok"), mean("steals_failed"))


def order_ablation(target: TargetGraph, pattern: PatternGraph, budget: int) -> DataFrame:
    """Pairs and matches under other orders, and of the state-space matcher; a task each."""
    spark = target.vertices.sparkSession
    shared = spark.sparkContext.broadcast(target.csr())
    made = {"constraint_first": orders.constraint_first(pattern), "by_degree": orders.by_degree(pattern), "identity": orders.identity(pattern), "random": orders.random(pattern, 1), "state_space": None}
    rows = spark.createDataFrame([(k,) for k in made], "`order` string").repartition(len(made), "order")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for name in batch["order"]:
                if name == "state_space":
                    pairs, found = baselines.state_space(shared.value, pattern)
                    row = (name, pairs, len(found), False)
                else:
                    counters, left = explored(Kernel(shared.value, build(pattern, "ord", order=made[name])), budget)
                    row = (name, counters.pairs, counters.matches, left)
                yield pd.DataFrame([row], columns=["order", "pairs", "matches", "cut"])

    return rows.mapInPandas(run, "`order` string, pairs long, matches long, cut boolean")
