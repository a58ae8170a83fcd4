"""What all engines execute: per position its vertex, where its candidates come from, and what they must meet."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from ..model import PatternGraph
from .order import anchors, constraint_first

METHODS = ("ord", "dom", "dom_s", "dom_f", "dom_sf")


@dataclass(frozen=True)
class Check:
    """An edge to the image at ``pos``; ``out``: it leaves that image and enters the candidate."""

    pos: int
    out: bool
    elabel: str | None


@dataclass(frozen=True)
class Step:
    pos: int
    pv: int
    anchor: Check | None
    checks: tuple[Check, ...]
    loops: tuple[str | None, ...]
    vlabel: str | None
    indeg: int
    outdeg: int


@dataclass(frozen=True)
class SearchPlan:
    pattern: PatternGraph
    method: str
    steps: tuple[Step, ...]

    @property
    def uses_domains(self) -> bool:
        return self.method != "ord"

    @property
    def order(self) -> list[int]:
        return [x.pv for x in self.steps]

    def rules(self) -> list[str]:
        """In the order in which they are tried: the cheap ones first."""
        return ["in domain", "unused", "edges"] if self.uses_domains else ["unused", "label", "degrees", "edges"]

    def explain(self, fan_out: float | None = None) -> str:
        lines = [f"{self.method}: {self.pattern.name}, {self.pattern.size} vertices, {len(self.pattern.edges)} edges; rules: {', '.join(self.rules())}"]
        rows = None
        for s in self.steps:
            where = "every vertex" if s.anchor is None else f"{'out' if s.anchor.out else 'in'}-neighbours of position {s.anchor.pos}" + (f" by {s.anchor.elabel}" if s.anchor.elabel else "")
            tests = [f"{'from' if c.out else 'to'} {c.pos}" + (f" by {c.elabel}" if c.elabel else "") for c in s.checks] + ["itself"] * len(s.loops)
            if fan_out is not None:
                rows = (rows or 1.0) * (fan_out if s.anchor is not None else 1.0)
            lines.append(f"  {s.pos}: vertex {s.pv}" + (f" [{s.vlabel}]" if s.vlabel else "") + f" from {where}" + (f"; edges {', '.join(tests)}" if tests else "") + (f"; about {rows:.3g} pairs a root" if rows else ""))
        return "\n".join(lines)

    def rows(self) -> list[tuple]:
        """(pattern_id, pos, pv, anchor_pos, anchor_out, anchor_elabel, checks)"""
        return [(self.pattern.name, s.pos, s.pv, s.anchor and s.anchor.pos, s.anchor and s.anchor.out, s.anchor and s.anchor.elabel, [(c.pos, c.out, c.elabel) for c in s.checks]) for s in self.steps]


def build(pattern: PatternGraph, method: str = "ord", sizes: Sequence[int] | None = None, order: Sequence[int] | None = None) -> SearchPlan:
    """Every pattern edge becomes one anchor, one check, or one loop test."""
    if method not in METHODS:
        raise ValueError(f"{method} is none of {METHODS}")
    if order is None:
        order = constraint_first(pattern, sizes, method in ("dom_s", "dom_sf"), method != "ord")
    place = {v: i for i, v in enumerate(order)}
    steps = []
    for i, (v, first) in enumerate(zip(order, anchors(pattern, order), strict=True)):
        anchor = Check(*first) if first else None
        checks = {Check(place[s], True, x) for s, d, x in pattern.edges if d == v and place[s] < i} | {Check(place[d], False, x) for s, d, x in pattern.edges if s == v and place[d] < i}
        rest = sorted(checks - {anchor}, key=lambda c: (c.pos, not c.out, c.elabel or ""))
        steps.append(Step(i, v, anchor, tuple(rest), tuple(x for s, d, x in pattern.edges if s == d == v), pattern.labels[v], pattern.in_degree(v), pattern.out_degree(v)))
    return SearchPlan(pattern, method, tuple(steps))
