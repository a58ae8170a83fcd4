"""Vertex orders of a pattern, and each vertex's anchor among those before it."""

from __future__ import annotations

import random as _random
from collections.abc import Sequence

from ..model import PatternGraph


def w_m(near: list[set[int]], placed: set[int], v: int) -> int:
    """Neighbours of v that are placed."""
    return len(near[v] & placed)


def w_n(near: list[set[int]], placed: set[int], v: int) -> int:
    """Placed vertices that share with v a neighbour which isn't placed."""
    between = near[v] - placed - {v}
    return sum(1 for p in placed if near[p] & between)


def constraint_first(pattern: PatternGraph, sizes: Sequence[int] | None = None, domain_tiebreak: bool = False, singletons_first: bool = False) -> list[int]:
    """Greedy: most placed neighbours, then most placed vertices with a common neighbour to come, then degree, then (optionally) the smaller domain, then the smaller id."""
    near = pattern.adjacency()
    placed: list[int] = []
    left = set(range(pattern.size))
    alone = {v for v in left if singletons_first and sizes is not None and sizes[v] == 1}

    def key(v: int) -> tuple:
        done = set(placed)
        return w_m(near, done, v), w_n(near, done, v), len(near[v]), -sizes[v] if domain_tiebreak and sizes is not None else 0, -v

    while left:
        best = max(alone & left or left, key=key)
        placed.append(best)
        left.remove(best)
    return placed


def by_degree(pattern: PatternGraph) -> list[int]:
    near = pattern.adjacency()
    return sorted(range(pattern.size), key=lambda v: (-len(near[v]), v))


def by_domain_size(pattern: PatternGraph, sizes: Sequence[int]) -> list[int]:
    return sorted(range(pattern.size), key=lambda v: (sizes[v], v))


def identity(pattern: PatternGraph) -> list[int]:
    return list(range(pattern.size))


def random(pattern: PatternGraph, seed: int = 0) -> list[int]:
    order = identity(pattern)
    _random.Random(seed).shuffle(order)
    return order


def anchors(pattern: PatternGraph, order: Sequence[int]) -> list[tuple[int, bool, str | None] | None]:
    """Per position: (anchor's position, whether the edge leaves the anchor, edge label), or None.

    The anchor is the earliest neighbour; an edge that leaves it is preferred to one that enters it.
    """
    place = {v: i for i, v in enumerate(order)}
    out: list[tuple[int, bool, str | None] | None] = []
    for i, v in enumerate(order):
        edges = [(place[s], False, x or "", x) for s, d, x in pattern.edges if d == v and place[s] < i]
        edges += [(place[d], True, x or "", x) for s, d, x in pattern.edges if s == v and place[d] < i]
        first = min(edges, key=lambda e: e[:3], default=None)
        out.append(None if first is None else (first[0], not first[1], first[3]))
    return out
