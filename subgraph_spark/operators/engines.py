"""Enumeration, counting and existence by any method with any engine.

join    one join per position; targets of any size
dfs     roots dealt over tasks, each of which explores its own over broadcast arrays
hybrid  joins until there are enough mappings to deal, then dfs
rounds  dfs with a budget of pairs per task; what a task has left, shallowest first and in groups of siblings, is dealt
        again in the next round. This takes the place of single steals, which tasks can't make
halves  directed cycles only: both halves of a cycle are made and joined in a task, over arrays that are mapped where they are large
auto    arrays if they fit the allowance, joins if not

Joins of a domain method take the order, with or without the smaller-domain tie-break, that is likely to make fewer pairs,
unless an order is given.
"""

from __future__ import annotations

import re
import time
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..model import Csr, PatternGraph, TargetGraph, TargetTooLarge
from ..plans.search_plan import SearchPlan, build
from ..session import materialise
from . import domains as D
from . import expand, halves
from .balance import worth
from .dfs import Counters, Kernel

TAGGED = "kind string, depth int, m array<bigint>, pairs bigint, part int"


def allowed_bytes(spark: SparkSession) -> int:
    """Bytes of arrays that may be broadcast: every core's Python worker holds them, so a quarter of an executor's memory is shared among its cores; 64 MB at least."""
    conf, local = spark.sparkContext.getConf(), spark.sparkContext.master.startswith("local[")
    size = conf.get("spark.driver.memory" if local else "spark.executor.memory", "1g").strip().lower()
    found = re.fullmatch(r"([0-9]+)([kmgt]?)b?", size)
    memory = int(found[1]) << {"k": 10, "m": 20, "g": 30, "t": 40, "": 20}[found[2]] if found else 1 << 30
    cores = spark.sparkContext.defaultParallelism if local else int(conf.get("spark.executor.cores", "1"))
    return max(64 << 20, memory // 4 // max(1, cores))


@dataclass
class Prepared:
    """A search ready to run: its plan, its domains, and whether an empty domain has ended it."""

    target: TargetGraph
    plan: SearchPlan
    domains: DataFrame | None
    sizes: D.Sizes | None
    infeasible: bool
    prep_ms: float = 0.0
    label_match: dict | None = None
    induced: bool = False
    max_cross: int = 10**7
    ordered: bool = False  # the order was given
    stats: dict = field(default_factory=dict)

    def csr(self, max_bytes: int | None = None) -> Csr:
        return self.target.csr(max_bytes or allowed_bytes(self.target.vertices.sparkSession), self.domains, D.words(self.plan.pattern) if self.plan.uses_domains else 0)


def prepare(target: TargetGraph, pattern: PatternGraph, method: str = "ord", rounds: int | str = 1, induced: bool = False, label_match=None, max_cross: int = 10**7, order=None, reconsistency: bool = False) -> Prepared:
    began = time.monotonic()
    if method == "ord":
        return Prepared(target, build(pattern, method, order=order), None, None, False, (time.monotonic() - began) * 1000, label_match, induced, max_cross, order is not None)
    found, sizes = D.prepare(target, pattern, method, rounds, label_match, reconsistency)
    plan = build(pattern, method, sizes.size, order)
    return Prepared(target, plan, found, sizes, sizes.infeasible, (time.monotonic() - began) * 1000, label_match, induced, max_cross, order is not None)


def _empty(ready: Prepared) -> DataFrame:
    fields = [T.StructField(expand.image(i), T.LongType()) for i in range(len(ready.plan.steps))]
    return ready.target.vertices.sparkSession.createDataFrame([], T.StructType(fields))


def _listed(rows: np.ndarray, group: int, kind: str, part: int) -> Iterator[pa.RecordBatch]:
    """Mappings as tagged rows, ``group`` of them to a row."""
    n, width = rows.shape
    step = max(1, (1 << 16) // max(group, 1)) * group
    for at in range(0, n, step):
        some = rows[at : at + step]
        ends = np.append(np.arange(0, len(some), group), len(some)) * width
        lists = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(some.ravel()))
        k = len(lists)
        yield pa.RecordBatch.from_arrays([pa.array([kind] * k), pa.array(np.full(k, width, np.int32)), lists, pa.nulls(k, pa.int64()), pa.array(np.full(k, part, np.int32))], names=["kind", "depth", "m", "pairs", "part"])


def explore(seeds: DataFrame, csr: Csr, ready: Prepared, budget: int | None = None, group_size: int = 4, time_limit_s: float | None = None, first_only: bool = False, count_only: bool = False, lookahead: bool = False) -> DataFrame:
    """Run the kernel over written or dealt ``seeds`` (depth, m: whole mappings one after another). Returns ``TAGGED`` rows:
    matches, what is left, and one row of counts per task."""
    spark = seeds.sparkSession
    shared = spark.sparkContext.broadcast(csr)  # its size was checked when it was made
    plan, label_match, induced = ready.plan, ready.label_match, ready.induced

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        kernel, counters, part = Kernel(shared.value, plan, label_match, induced, lookahead), Counters(), TaskContext.get().partitionId()
        vids, by_depth, found = shared.value.vids, {}, 0
        for batch in batches:
            for depth, m in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                by_depth.setdefault(depth, []).append(m.values.to_numpy())
        end = None if time_limit_s is None else time.monotonic() + time_limit_s
        left = budget
        for depth in sorted(by_depth, reverse=True):
            rows = np.searchsorted(vids, np.concatenate(by_depth[depth])).reshape(-1, depth)
            before = counters.pairs
            for kind, block in kernel.run(rows, counters, left, end, first_only):
                found += kind == "match"
                if kind == "todo" or not count_only:
                    yield from _listed(vids[block], 1 if kind == "match" else group_size, kind, part)
            if budget is not None:
                left = max(0, left - (counters.pairs - before))
            if first_only and found:
                break
        yield pa.RecordBatch.from_arrays([pa.array(["stat", "count", "late"]), pa.array([0] * 3, pa.int32()), pa.nulls(3, pa.list_(pa.int64())), pa.array([counters.pairs, counters.matches, int(counters.timed_out)], pa.int64()), pa.array([part] * 3, pa.int32())], names=["kind", "depth", "m", "pairs", "part"])

    return seeds.mapInArrow(search, TAGGED)


def _matches(tagged: DataFrame, ready: Prepared) -> DataFrame:
    return tagged.filter("kind = 'match'").select(*[F.element_at("m", i + 1).alias(expand.image(i)) for i in range(len(ready.plan.steps))])


def _seeds(frontier: DataFrame, depth: int) -> DataFrame:
    return frontier.select(F.lit(depth).alias("depth"), F.array(*[expand.image(i) for i in range(depth)]).alias("m"))


def _roots(ready: Prepared) -> DataFrame:
    return expand.search(ready.target, ready.plan, ready.domains, ready.label_match, ready.induced, ready.max_cross, upto=0)


def _dealt(seeds: DataFrame, tasks: int, how: str = "block") -> DataFrame:
    """Seeds over tasks: contiguous blocks of the roots' order, or one after the other."""
    if tasks <= 1:
        return seeds.coalesce(1)
    return seeds.repartitionByRange(tasks, "m") if how == "block" else seeds.repartition(tasks)


def run(ready: Prepared, engine: str = "auto", workers: int | None = None, budget: int | None = None, group_size: int = 4, time_limit_s: float | None = None, first_only: bool = False, count_only: bool = False, split_depth: int | str = "auto", over: int = 4, deal: str = "roundrobin", max_bytes: int | None = None, max_rounds: int | None = None, lookahead: bool = False) -> DataFrame:
    """Matches as p0, p1, ... by position; or with ``count_only`` one row (pairs, matches, timed_out).

    ``max_rounds`` ends a search in rounds, so that the pairs it considers are bounded; it then counts as timed out.
    """
    spark = ready.target.vertices.sparkSession
    if ready.infeasible:
        return spark.createDataFrame([(0, 0, False)], "pairs long, matches long, timed_out boolean") if count_only else _empty(ready)
    if engine == "halves":
        if ready.induced or ready.label_match is not None or ready.plan.uses_domains:
            raise ValueError("halves have no induced matches, label equivalence or domains")
        place = {s.pv: s.pos for s in ready.plan.steps}
        found = halves.search(ready.target, ready.plan.pattern, [expand.image(place[v]) for v in range(ready.plan.pattern.size)], workers, max_bytes)
        return found.agg(F.lit(None).cast("long").alias("pairs"), F.count("*").alias("matches"), F.lit(False).alias("timed_out")) if count_only else found
    csr = None
    if engine == "auto":
        try:
            csr, engine = ready.csr(max_bytes), "rounds"
            # A short search is not worth many workers: its pairs are guessed from the roots and the mean degree.
            roots = csr.n if ready.sizes is None else ready.sizes.size[ready.plan.steps[0].pv]
            pairs = roots * max(1.0, len(csr.keys) / max(1, csr.n)) ** min(len(ready.plan.steps) - 1, 8)
            workers = workers or worth(pairs, max(1, roots), most=spark.sparkContext.defaultParallelism)
        except TargetTooLarge:
            engine = "join"
    if engine == "join":
        reduced = None
        if ready.plan.uses_domains and not ready.ordered and any(s.anchor for s in ready.plan.steps):
            reduced = expand.chosen(ready.target, ready.plan, ready.domains)
            ready.plan = reduced.plan
        found = expand.search(ready.target, ready.plan, ready.domains, ready.label_match, ready.induced, ready.max_cross, reduced=reduced)
        return found.agg(F.lit(None).cast("long").alias("pairs"), F.count("*").alias("matches"), F.lit(False).alias("timed_out")) if count_only else found
    csr = csr or ready.csr(max_bytes)
    tasks = (workers or spark.sparkContext.defaultParallelism) * (over if (workers or 2) > 1 else 1)
    frontier, depth, k = _roots(ready), 1, len(ready.plan.steps)
    before = csr.n if not ready.plan.uses_domains else ready.sizes.size[ready.plan.steps[0].pv]
    if engine == "hybrid":
        want = 16 * tasks if split_depth == "auto" else None
        frontier = materialise(frontier, "seeds")
        counted = [before]
        while depth < k and (depth < split_depth if want is None else frontier.count() < want):
            step = ready.plan.steps[depth]
            rows = expand.generate(frontier, ready.target, ready.plan, step, expand.vertex_info(ready.target, ready.plan, ready.domains), ready.max_cross, label_early=False)
            rows = materialise(rows, "pairs")
            counted.append(rows.count())
            if step.anchor is not None and step.anchor.elabel is not None:
                rows = expand.with_edge(rows, ready.target, step.anchor)
            frontier = materialise(expand.grown(expand.step_rules(rows, ready.target, ready.plan, step, ready.label_match, ready.induced), step), "seeds")
            depth += 1
        before = sum(counted)
    seeds = _dealt(_seeds(frontier, depth), tasks, deal)
    if engine in ("dfs", "hybrid"):
        parts = [materialise(explore(seeds, csr, ready, None, group_size, time_limit_s, first_only, count_only, lookahead), "explored")]
    elif engine == "rounds":
        budget = budget or 20_000_000
        parts, end = [], None if time_limit_s is None else time.monotonic() + time_limit_s
        while True:
            limit = None if end is None else max(0.0, end - time.monotonic())
            parts.append(materialise(explore(seeds, csr, ready, budget, group_size, limit, first_only, count_only, lookahead), "round"))
            left = parts[-1].filter("kind = 'todo'")
            late = limit is not None and not limit or max_rounds is not None and len(parts) >= max_rounds
            if late or left.isEmpty() or first_only and not parts[-1].filter("kind = 'match'").isEmpty():
                break
            seeds = left.select("depth", "m").repartition(tasks, F.hash("m"))
    else:
        raise ValueError(f"{engine} is no engine")
    tagged = reduce(DataFrame.unionByName, parts)
    if engine == "rounds":  # what is left after the last round is work not done
        tagged = tagged.unionByName(parts[-1].filter("kind = 'todo'").limit(1).select(F.lit("late").alias("kind"), "depth", "m", F.lit(1).cast("long").alias("pairs"), "part"))
    ready.stats |= {"rounds": len(parts), "tagged": tagged, "root_pairs": before}
    if count_only:
        total = lambda kind: F.coalesce(F.sum(F.when(F.col("kind") == kind, F.col("pairs"))), F.lit(0))
        return tagged.agg((total("stat") + before).alias("pairs"), total("count").alias("matches"), (total("late") > 0).alias("timed_out"))
    return _matches(tagged, ready)


def wide(found: DataFrame, plan: SearchPlan) -> DataFrame:
    """m0, m1, ... by pattern vertex."""
    place = {s.pv: s.pos for s in plan.steps}
    return found.select(*[F.col(expand.image(place[v])).alias(f"m{v}") for v in range(plan.pattern.size)])


def deliver(found: DataFrame, plan: SearchPlan, form: str = "wide") -> DataFrame:
    """Matches as columns, as one array by pattern vertex, or as a map from pattern vertex to target vertex."""
    rows = wide(found, plan)
    images = F.array(*[f"m{v}" for v in range(plan.pattern.size)])
    if form == "wide":
        return rows
    if form == "array":
        return rows.select(images.alias("m"))
    if form == "map":
        return rows.select(F.map_from_arrays(F.array(*[F.lit(v) for v in range(plan.pattern.size)]), images).alias("m"))
    raise ValueError(f"{form} is no form")


def enumerate(target: TargetGraph, pattern: PatternGraph, method: str = "ord", engine: str = "join", rounds: int | str = 1, induced: bool = False, label_match=None, form: str = "wide", max_cross: int = 10**7, order=None, **how) -> DataFrame:
    """Every mapping of ``pattern`` into ``target``."""
    ready = prepare(target, pattern, method, rounds, induced, label_match, max_cross, order)
    return deliver(run(ready, engine, **how), ready.plan, form)


def counts(target: TargetGraph, pattern: PatternGraph, method: str = "ord", engine: str = "dfs", rounds: int | str = 1, induced: bool = False, label_match=None, max_cross: int = 10**7, order=None, **how) -> DataFrame:
    """One row (pairs, matches, timed_out)."""
    return run(prepare(target, pattern, method, rounds, induced, label_match, max_cross, order), engine, count_only=True, **how)


def count(target: TargetGraph, pattern: PatternGraph, method: str = "ord", engine: str = "dfs", **how) -> int:
    return counts(target, pattern, method, engine, **how).first()["matches"]


def exists(target: TargetGraph, pattern: PatternGraph, method: str = "ord", engine: str = "dfs", **how) -> bool:
    """Is there a match? Ends at the first."""
    ready = prepare(target, pattern, method, **{k: how.pop(k) for k in ("rounds", "induced", "label_match", "max_cross") if k in how})
    return not run(ready, engine, first_only=engine != "join", **how).isEmpty()


def is_isomorphic(a: TargetGraph, pattern: PatternGraph) -> bool:
    """Is a target the same graph as ``pattern``? Equal numbers and an induced match."""
    n, m = a.vertices.count(), a.edges.count()
    return n == pattern.size and m == len(pattern.edges) and exists(a, pattern, "ord", "dfs", induced=True)


def distinct_subgraphs(matches: DataFrame, pattern: PatternGraph) -> DataFrame:
    """Wide matches to their edge images, each once: edges as sorted (from, to, label) structs."""
    if not pattern.edges:
        return matches.select(F.array_sort(F.array(*matches.columns)).alias("vertices")).distinct()
    image = F.array(*[F.struct(F.col(f"m{s}").alias("s"), F.col(f"m{d}").alias("d"), F.lit(x).cast("string").alias("e")) for s, d, x in pattern.edges])
    alone = [f"m{v}" for v in range(pattern.size) if not any(v in (s, d) for s, d, _ in pattern.edges)]
    lone = F.array_sort(F.array(*alone)) if alone else F.array().cast("array<bigint>")
    return matches.select(F.array_sort(image).alias("edges"), lone.alias("vertices")).distinct()
