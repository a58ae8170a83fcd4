"""Candidate domains as bit masks: one row per target vertex, bit i set where it may be pattern vertex i's image.

A round of neighbourhood consistency costs two aggregates over the edges, whatever the pattern's size. Only one number
per pattern vertex comes to the driver.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Mapping
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import PatternGraph, TargetGraph
from ..session import materialise

#: Pattern vertices in a mask word; the sign bit stays clear.
WORD = 62

LabelMatch = Mapping[str, set[str]]


def words(pattern: PatternGraph) -> int:
    return -(-pattern.size // WORD)


def mask_columns(pattern: PatternGraph) -> list[str]:
    return [f"mask{w}" for w in range(words(pattern))]


def has_bit(i: int, prefix: str = "") -> Column:
    return F.col(f"{prefix}mask{i // WORD}").bitwiseAND(F.lit(1 << i % WORD)) != 0


def _word(bits) -> list[int]:
    out: dict[int, int] = defaultdict(int)
    for i in bits:
        out[i // WORD] |= 1 << i % WORD
    return out


def label_condition(label: str | None, label_match: LabelMatch | None, column: str = "vlabel") -> Column:
    """Does a target label fit a pattern label? None fits any."""
    if label is None:
        return F.lit(True)
    if label_match is not None:
        return F.col(column).isin(*sorted(label_match.get(label, ())))
    return F.col(column) == label


def _or(parts: list[Column]) -> Column:
    return reduce(lambda a, b: a.bitwiseOR(b), parts) if parts else F.lit(0).cast("long")


def _nonempty(pattern: PatternGraph) -> Column:
    return reduce(lambda a, b: a | b, [F.col(c) != 0 for c in mask_columns(pattern)])


def initial(target: TargetGraph, pattern: PatternGraph, label_match: LabelMatch | None = None) -> DataFrame:
    """(vid, mask0, ...): equal label, and no smaller in- or out-degree. Empty masks are left out."""
    kinds = defaultdict(list)
    for i in range(pattern.size):
        kinds[pattern.labels[i], pattern.in_degree(i), pattern.out_degree(i)].append(i)
    parts: list[list[Column]] = [[] for _ in range(words(pattern))]
    for (label, indeg, outdeg), bits in kinds.items():
        fits = F.coalesce(label_condition(label, label_match), F.lit(False)) & (F.col("indeg") >= indeg) & (F.col("outdeg") >= outdeg)
        for w, bit in _word(bits).items():
            parts[w].append(F.when(fits, F.lit(bit).cast("long")).otherwise(F.lit(0).cast("long")))
    rows = target.degrees().select("vid", *[_or(p).alias(c) for p, c in zip(parts, mask_columns(pattern), strict=True)])
    return rows.filter(_nonempty(pattern))


def consistent(target: TargetGraph, pattern: PatternGraph, domains: DataFrame) -> DataFrame:
    """One simultaneous round: a bit stays if every pattern edge at it has a compatible target edge into the other end's domain."""
    columns = mask_columns(pattern)
    edge_labels = sorted({x for _, _, x in pattern.edges if x is not None})
    needs: dict[tuple[bool, str | None], dict[int, set[int]]] = defaultdict(lambda: defaultdict(set))
    loops: dict[str | None, set[int]] = defaultdict(set)
    for s, d, x in pattern.edges:
        if s == d:
            loops[x].add(s)
        else:
            needs[True, x][s].add(d)
            needs[False, x][d].add(s)

    def gathered(near: str, far: str, side: str) -> DataFrame:
        rows = target.edges.join(domains.withColumnRenamed("vid", far), far)
        return rows.groupBy(F.col(near).alias("vid")).agg(
            *[F.bit_or(c).alias(f"{side}_{c}") for c in columns],
            *[F.bit_or(F.when(F.col("elabel") == x, F.col(c)).otherwise(F.lit(0).cast("long"))).alias(f"{side}{k}_{c}") for k, x in enumerate(edge_labels) for c in columns],
        )

    rows = domains
    if any(out for out, _ in needs):
        rows = rows.join(gathered("src", "dst", "out"), "vid", "left").join(gathered("dst", "src", "in"), "vid", "left")
    if loops:
        own = target.edges.filter("src = dst").groupBy(F.col("src").alias("vid")).agg(F.collect_set("elabel").alias("own_labels"))
        rows = rows.join(own.withColumn("own_loop", F.lit(True)), "vid", "left")
    fails: list[list[Column]] = [[] for _ in columns]
    for (out, label), by_vertex in needs.items():
        side = ("out" if out else "in") + ("" if label is None else str(edge_labels.index(label)))
        for i, others in by_vertex.items():
            met = [F.coalesce(F.col(f"{side}_mask{w}"), F.lit(0)).bitwiseAND(F.lit(bits)) == bits for w, bits in _word(others).items()]
            fails[i // WORD].append(F.when(reduce(lambda a, b: a & b, met), F.lit(0).cast("long")).otherwise(F.lit(1 << i % WORD).cast("long")))
    for label, vertices in loops.items():
        met = F.coalesce(F.col("own_loop"), F.lit(False)) if label is None else F.coalesce(F.array_contains("own_labels", label), F.lit(False))
        for w, bits in _word(vertices).items():
            fails[w].append(F.when(met, F.lit(0).cast("long")).otherwise(F.lit(bits).cast("long")))
    rows = rows.select("vid", *[F.col(c).bitwiseAND(F.bitwise_not(_or(f))).alias(c) for c, f in zip(columns, fails, strict=True)])
    return rows.filter(_nonempty(pattern))


@dataclass(frozen=True)
class Sizes:
    """Per pattern vertex the size of its domain, and the vertex in it where that is one."""

    size: tuple[int, ...]
    only: tuple[int | None, ...]

    @property
    def infeasible(self) -> bool:
        return 0 in self.size


def sizes(domains: DataFrame, pattern: PatternGraph) -> Sizes:
    """One aggregate; two numbers per pattern vertex reach the driver."""
    row = domains.agg(*[F.count_if(has_bit(i)).alias(f"n{i}") for i in range(pattern.size)], *[F.min(F.when(has_bit(i), F.col("vid"))).alias(f"v{i}") for i in range(pattern.size)]).first()
    count = tuple(int(row[f"n{i}"]) for i in range(pattern.size))
    return Sizes(count, tuple(row[f"v{i}"] if count[i] == 1 else None for i in range(pattern.size)))


def remove_singletons(domains: DataFrame, pattern: PatternGraph, found: Mapping[int, int]) -> DataFrame:
    """Take each singleton's vertex (``found``: pattern vertex to target vertex) out of all other domains."""
    owners = defaultdict(list)
    for i, vid in found.items():
        owners[vid].append(i)
    columns = mask_columns(pattern)
    keep = {vid: (_word(own) if len(own) == 1 else {}) for vid, own in owners.items()}
    at = F.col("vid").isin(*keep)
    out = []
    for w, c in enumerate(columns):
        table = F.create_map(*[F.lit(x) for vid, bits in keep.items() for x in (vid, bits.get(w, 0))]).cast("map<bigint,bigint>")
        out.append(F.when(at, F.col(c).bitwiseAND(F.element_at(table, F.col("vid")))).otherwise(F.col(c)).alias(c))
    return domains.select("vid", *out).filter(_nonempty(pattern))


def forward_check(domains: DataFrame, pattern: PatternGraph, now: Sizes | None = None, on_round=None, target: TargetGraph | None = None, reconsistency: bool = False) -> tuple[DataFrame, Sizes]:
    """Rounds of ``remove_singletons``, each for the domains that have just become single; stops when there are none, or one is empty.

    ``reconsistency`` (with ``target``) runs a round of consistency after each.
    """
    now = now or sizes(domains, pattern)
    done: set[int] = set()
    while not now.infeasible:
        new = {i: now.only[i] for i in range(pattern.size) if now.size[i] == 1 and i not in done}
        if not new:
            break
        done |= set(new)
        domains = remove_singletons(domains, pattern, new)
        if reconsistency and target is not None:
            domains = consistent(target, pattern, domains)
        domains = materialise(domains, "domains")
        now = sizes(domains, pattern)
        if on_round:
            on_round(domains, now)
    return domains, now


def prepare(target: TargetGraph, pattern: PatternGraph, method: str = "dom", rounds: int | str = 1, label_match: LabelMatch | None = None, reconsistency: bool = False, stop_early: bool = True) -> tuple[DataFrame, Sizes]:
    """Domains as ``method`` wants them: initial, consistent for some rounds or to the fixpoint, forward-checked for the f methods.

    An empty domain ends the rounds (no match is left), unless ``stop_early`` is off.
    """
    domains = materialise(initial(target, pattern, label_match), "domains")
    now = sizes(domains, pattern)
    done = 0
    while not (stop_early and now.infeasible) and (rounds == "fixpoint" or done < int(rounds)):
        domains = materialise(consistent(target, pattern, domains), "domains")
        before, now, done = now, sizes(domains, pattern), done + 1
        if rounds == "fixpoint" and now == before:
            break
    if method in ("dom_f", "dom_sf") and not now.infeasible:
        domains, now = forward_check(domains, pattern, now, target=target, reconsistency=reconsistency)
    return domains, now


def rows(domains: DataFrame, pattern: PatternGraph) -> DataFrame:
    """Row form: (pv, vid)."""
    every = F.filter(F.array(*[F.when(has_bit(i), F.lit(i)) for i in range(pattern.size)]), lambda x: x.isNotNull())
    return domains.select(F.explode(every).alias("pv"), "vid")


def reduce_edges(target: TargetGraph, pattern: PatternGraph, domains: DataFrame) -> DataFrame:
    """Edges that some pattern edge could use, with both ends' masks (src_mask0.., dst_mask0..)."""
    columns = mask_columns(pattern)
    ends = lambda side: domains.select(F.col("vid").alias(side), *[F.col(c).alias(f"{side}_{c}") for c in columns])
    both = target.edges.join(ends("src"), "src").join(ends("dst"), "dst")
    uses = [has_bit(s, "src_") & has_bit(d, "dst_") & (F.lit(True) if x is None else F.coalesce(F.col("elabel") == x, F.lit(False))) for s, d, x in pattern.edges]
    return both.filter(reduce(lambda a, b: a | b, uses)) if uses else both.limit(0)
