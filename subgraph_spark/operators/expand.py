"""Level-synchronous search: one join per pattern vertex, for targets of any size.

The driver only builds the plan. Cheap rules are filters behind the join that makes the candidates; edge rules are semi
joins. A frontier is written once it is so many joins deep.
"""

from __future__ import annotations

import copy
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import TargetGraph
from ..plans.search_plan import Check, SearchPlan, Step, build
from ..session import materialise
from .domains import LabelMatch, has_bit, label_condition, mask_columns, reduce_edges, sizes

#: Joins after which a frontier is written.
MAX_LINEAGE = 8


class CrossJoinTooLarge(RuntimeError):
    """A vertex without an anchor would meet more rows than allowed."""


def image(pos: int) -> str:
    return f"p{pos}"


def vertex_info(target: TargetGraph, plan: SearchPlan, domains: DataFrame | None) -> DataFrame:
    """(cand, what the cheap rules look at): masks for the domain methods, label and degrees otherwise."""
    if plan.uses_domains:
        return domains.select(F.col("vid").alias("cand"), *mask_columns(plan.pattern))
    return target.degrees().select(F.col("vid").alias("cand"), "vlabel", "indeg", "outdeg")


def fits(plan: SearchPlan, step: Step, label_match: LabelMatch | None) -> list[tuple[str, Column]]:
    """The cheap rules in the method's order, by name."""
    unused = reduce(lambda a, b: a & b, [F.col("cand") != F.col(image(i)) for i in range(step.pos)], F.lit(True))
    if plan.uses_domains:
        return [("in domain", has_bit(step.pv)), ("unused", unused)]
    label = F.coalesce(label_condition(step.vlabel, label_match), F.lit(False))
    return [("unused", unused), ("label", label), ("degrees", (F.col("indeg") >= step.indeg) & (F.col("outdeg") >= step.outdeg))]


def _edges(target: TargetGraph, label: str | None) -> DataFrame:
    return target.pairs() if label is None else target.edges.filter(F.col("elabel") == label).select("src", "dst").distinct()


def candidates(frontier: DataFrame, target: TargetGraph, step: Step, label_early: bool = True) -> DataFrame:
    """The frontier with a row per candidate, ``cand``. Without ``label_early`` all of the anchor's neighbours are generated."""
    a = step.anchor
    near, far = ("src", "dst") if a.out else ("dst", "src")
    edges = _edges(target, a.elabel if label_early else None)
    return frontier.join(edges.select(F.col(near).alias(image(a.pos)), F.col(far).alias("cand")), image(a.pos))


def with_edge(rows: DataFrame, target: TargetGraph, check: Check, forbid: bool = False) -> DataFrame:
    """Rows whose candidate has the edge (or, ``forbid``, hasn't)."""
    near, far = ("src", "dst") if check.out else ("dst", "src")
    edges = _edges(target, check.elabel).select(F.col(near).alias(image(check.pos)), F.col(far).alias("cand"))
    return rows.join(edges, [image(check.pos), "cand"], "left_anti" if forbid else "left_semi")


def with_loop(rows: DataFrame, target: TargetGraph, label: str | None) -> DataFrame:
    return rows.join(_edges(target, label).filter("src = dst").select(F.col("src").alias("cand")), "cand", "left_semi")


def _forbidden(plan: SearchPlan, step: Step) -> list[Check]:
    """For induced matches: edges that the pattern doesn't have between this vertex and earlier ones."""
    have = {(s, d) for s, d, _ in plan.pattern.edges}
    out = []
    for i in range(step.pos):
        u = plan.steps[i].pv
        if (u, step.pv) not in have:
            out.append(Check(i, True, None))
        if (step.pv, u) not in have:
            out.append(Check(i, False, None))
    return out


def generate(frontier: DataFrame | None, target: TargetGraph, plan: SearchPlan, step: Step, info: DataFrame, max_cross: int, label_early: bool = True) -> DataFrame:
    """All candidates of a position, with what the cheap rules look at. These are the pairs considered."""
    if frontier is None:
        return info.filter(has_bit(step.pv)) if plan.uses_domains else info
    if step.anchor is not None:
        rows = candidates(frontier, target, step, label_early)
        return rows.join(info, "cand", "left" if plan.uses_domains else "inner")
    free = info.filter(has_bit(step.pv)) if plan.uses_domains else info
    n = frontier.count() * free.count()
    if n > max_cross:
        raise CrossJoinTooLarge(f"position {step.pos} has no anchor: {n} pairs, {max_cross} are allowed")
    return frontier.crossJoin(free)


def step_rules(rows: DataFrame, target: TargetGraph, plan: SearchPlan, step: Step, label_match, induced: bool) -> DataFrame:
    for _, rule in fits(plan, step, label_match):
        rows = rows.filter(rule)
    return edge_rules(rows, target, plan, step, step.checks, induced)


def edge_rules(rows: DataFrame, target: TargetGraph, plan: SearchPlan, step: Step, checks, induced: bool) -> DataFrame:
    for check in checks:
        rows = with_edge(rows, target, check)
    for label in step.loops:
        rows = with_loop(rows, target, label)
    if induced:
        for check in _forbidden(plan, step):
            rows = with_edge(rows, target, check, forbid=True)
        if not step.loops:
            rows = rows.join(_edges(target, None).filter("src = dst").select(F.col("src").alias("cand")), "cand", "left_anti")
    return rows


def grown(rows: DataFrame, step: Step) -> DataFrame:
    return rows.select(*[image(i) for i in range(step.pos)], F.col("cand").alias(image(step.pos)))


class ReducedEdges:
    """A target's edges that some pattern edge can use, both ends in their domains; and how many each pattern edge can use.

    The join engine makes candidates from these, so that domains need no look-up of their own, and by the pattern edge with the
    smallest fan-out, whatever the plan's anchor is. The plan's order stays.
    """

    def __init__(self, target: TargetGraph, plan: SearchPlan, domains: DataFrame):
        self.simple, self.plan, pattern = target.simple, plan, plan.pattern
        self.edges = materialise(reduce_edges(target, pattern, domains), "reduced-edges")
        kinds = [self._uses(s, d, x) for s, d, x in pattern.edges] or [F.lit(False)]
        row = self.edges.agg(*[F.count_if(k).alias(f"e{i}") for i, k in enumerate(kinds)]).first()
        self.count = {e: row[f"e{i}"] for i, e in enumerate(pattern.edges)}
        self.size = sizes(domains, pattern).size

    def under(self, plan: SearchPlan) -> ReducedEdges:
        """The same edges for another order."""
        other = copy.copy(self)
        other.plan = plan
        return other

    @staticmethod
    def _uses(s: int, d: int, label: str | None) -> Column:
        both = has_bit(s, "src_") & has_bit(d, "dst_")
        return both if label is None else both & F.coalesce(F.col("elabel") == label, F.lit(False))

    def edge(self, step: Step, check: Check) -> tuple[int, int, str | None]:
        """The pattern edge that a check of a step stands for."""
        other = self.plan.steps[check.pos].pv
        return (other, step.pv, check.elabel) if check.out else (step.pv, other, check.elabel)

    def fan_out(self, step: Step, check: Check) -> float:
        return self.count[self.edge(step, check)] / max(1, self.size[self.plan.steps[check.pos].pv])

    def generator(self, step: Step) -> Check:
        return min([step.anchor, *step.checks], key=lambda c: self.fan_out(step, c))

    def ends(self, step: Step, check: Check) -> DataFrame:
        """(image, cand) of the edges that a check may use, each once."""
        near, far = ("src", "dst") if check.out else ("dst", "src")
        rows = self.edges.filter(self._uses(*self.edge(step, check))).select(F.col(near).alias(image(check.pos)), F.col(far).alias("cand"))
        return rows if self.simple or check.elabel is not None else rows.distinct()

    def pairs(self) -> float:
        """About how many pairs the plan's order makes: fan-outs multiplied, less what the other edges are likely to refuse."""
        total, rows = 0.0, 1.0
        for step in self.plan.steps:
            used = None if step.anchor is None else self.generator(step)
            rows *= self.size[step.pv] if used is None else self.fan_out(step, used)
            total += rows
            for c in {step.anchor, *step.checks} - {used, None}:
                rows *= min(1.0, self.count[self.edge(step, c)] / max(1, self.size[step.pv] * self.size[self.plan.steps[c.pos].pv]))
        return total


def chosen(target: TargetGraph, plan: SearchPlan, domains: DataFrame) -> ReducedEdges:
    """The reduced edges, under the plan's order or the one with (or without) the smaller-domain tie-break, whichever is likely to make fewer pairs."""
    own = ReducedEdges(target, plan, domains)
    other = own.under(build(plan.pattern, "dom" if plan.method in ("dom_s", "dom_sf") else "dom_s", own.size))
    return min((own, other), key=ReducedEdges.pairs)


def cheaper(target: TargetGraph, plan: SearchPlan, domains: DataFrame) -> SearchPlan:
    return chosen(target, plan, domains).plan


def _domain_step(frontier: DataFrame, target: TargetGraph, plan: SearchPlan, step: Step, reduced: ReducedEdges, induced: bool) -> DataFrame:
    """The frontier and its candidates that pass, by edges whose ends are in their domains."""
    used = reduced.generator(step)
    rows = frontier.join(reduced.ends(step, used), image(used.pos))
    rows = rows.filter(reduce(lambda a, b: a & b, [F.col("cand") != F.col(image(i)) for i in range(step.pos)]))
    for check in [step.anchor, *step.checks]:
        if check != used:
            rows = rows.join(reduced.ends(step, check), [image(check.pos), "cand"], "left_semi")
    return edge_rules(rows, target, plan, step, (), induced)


def search(target: TargetGraph, plan: SearchPlan, domains: DataFrame | None = None, label_match: LabelMatch | None = None, induced: bool = False, max_cross: int = 10**7, upto: int | None = None, max_lineage: int = MAX_LINEAGE, reduced: ReducedEdges | None = None) -> DataFrame:
    """Frontier after position ``upto`` (all positions by default): columns p0, p1, ..."""
    info, frontier = vertex_info(target, plan, domains), None
    if any(s.pos and s.anchor is None for s in plan.steps):
        info = materialise(info, "vertex-info")
    steps = plan.steps[: None if upto is None else upto + 1]
    if reduced is None and plan.uses_domains and any(s.anchor for s in steps):
        reduced = ReducedEdges(target, plan, domains)
    for step in steps:
        if reduced is not None and step.anchor is not None:
            rows = _domain_step(frontier, target, plan, step, reduced, induced)
        else:
            rows = step_rules(generate(frontier, target, plan, step, info, max_cross), target, plan, step, label_match, induced)
        frontier = grown(rows, step)
        if step.pos and step.pos % max_lineage == 0:
            frontier = materialise(frontier, "frontier")
    return frontier


def pairs_by_partition(target: TargetGraph, plan: SearchPlan) -> DataFrame:
    """(kind, depth, part, pairs): pairs behind the roots by the Spark partition that makes them, for targets whose arrays are too large.

    A level is a round. Partitions follow the anchors' images, so that where the first vertex anchors all others the roots' deal is kept.
    """
    info, frontier, out = materialise(vertex_info(target, plan, None), "vertex-info"), None, []
    for step in plan.steps:
        rows = generate(frontier, target, plan, step, info, 10**7, label_early=False)
        if step.pos:
            out.append(rows.groupBy(F.spark_partition_id().alias("part")).agg(F.count("*").alias("pairs")).select(F.lit("stat").alias("kind"), F.lit(step.pos).alias("depth"), "part", "pairs"))
        if step.pos + 1 < len(plan.steps):
            if step.anchor is not None and step.anchor.elabel is not None:
                rows = with_edge(rows, target, step.anchor)
            frontier = materialise(grown(step_rules(rows, target, plan, step, None, False), step), "frontier")
    return materialise(reduce(DataFrame.unionByName, out), "pairs-by-partition")


def funnel(target: TargetGraph, plan: SearchPlan, domains: DataFrame | None = None, label_match: LabelMatch | None = None, max_cross: int = 10**7) -> list[dict]:
    """Per position: pairs considered, and how many are left after each rule in the method's order."""
    info, frontier, out = materialise(vertex_info(target, plan, domains), "vertex-info"), None, []
    for step in plan.steps:
        rows = generate(frontier, target, plan, step, info, max_cross, label_early=False)
        rules = fits(plan, step, label_match)
        passed, counts = F.lit(True), [F.count("*").alias("pairs")]
        for name, rule in rules:
            passed = passed & F.coalesce(rule, F.lit(False))
            counts.append(F.count_if(passed).alias(name))
        tested = materialise(rows.withColumn("passed", passed), "pairs") if frontier is not None else rows.withColumn("passed", passed)
        row = tested.agg(*counts).first().asDict()
        left = tested.filter("passed")
        if step.anchor is not None and step.anchor.elabel is not None:
            left = with_edge(left, target, step.anchor)
        for check in step.checks:
            left = with_edge(left, target, check)
        for label in step.loops:
            left = with_loop(left, target, label)
        frontier = materialise(grown(left, step), "frontier")
        row["edges"] = frontier.count()
        out.append({"depth": step.pos, "pairs": row["pairs"], "after_unused": row["unused"], "after_label_or_domain": row.get("label", row.get("in domain")), "after_degree": row.get("degrees"), "after_edges": row["edges"]})
    return out
