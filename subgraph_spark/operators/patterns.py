"""The catalogue of patterns, and patterns taken from a target."""

from __future__ import annotations

import heapq

import numpy as np

from ..model import Csr, PatternGraph

P = PatternGraph.parse
CATALOG = {
    "P1": P("a->b; b->c; c->a", "P1"),
    "P2": P("a->b; b->c; a->c", "P2"),
    "P3": P("a:9->b:19; b->c:11; a->c", "P3"),
    "P4": P("a->b; b->c; c->d; d->a", "P4"),
    "P5": P("a:order-[placed_by]->b:customer; a-[ships_from]->c:supplier; b-[in_nation]->d:nation; c-[in_nation]->d", "P5"),
    "P6": P("a:user->b:assistant; b->c:user; c->d:assistant", "P6"),
    "P7": P("a->c:path; b->c", "P7"),
    "P8": P("a-[0]->b; b-[1]->c; a-[1]->c", "P8"),
    "P9": P("a:Brand#1->b:Brand#2; b->c:Brand#3; c->a", "P9"),
    "P10": P("a->b; c->d", "P10"),
    "P11": P("a", "P11"),
    "P12": P("a->a", "P12"),
    "P13": P("a:nowhere->b; b->c; a->c", "P13"),
}


def _mark(keys: np.ndarray, seed: int) -> np.ndarray:
    x = (keys.astype(np.uint64) + np.uint64(seed) * np.uint64(0x9E3779B97F4A7C15)) * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(31)
    return x * np.uint64(0x94D049BB133111EB) >> np.uint64(1)


def first_edge(csr: Csr, seed: int) -> int:
    """The edge with the smallest hash, and of equal ones the smallest. All edges are looked at, so that patterns of several sizes and a seed share it."""
    n, best = csr.n, None
    with np.errstate(over="ignore"):
        for a, b in csr.blocks():
            near = np.repeat(np.arange(a, b), np.diff(csr.out_ptr[a : b + 1]))
            to = csr.out_to[csr.out_ptr[a] : csr.out_ptr[b]]
            keys = (near * n + to)[near != to]
            if len(keys):
                marks = _mark(keys, seed)
                at = int(np.argmin(marks))
                best = min(best or (int(marks[at]), int(keys[at])), (int(marks[at]), int(keys[at])))
    if best is None:
        raise ValueError("the target has no edge")
    return best[1]


def extract(csr: Csr, n_edges: int, density: str, seed: int, edge_labels: bool = False, first: int | None = None) -> PatternGraph:
    """A connected part of a target with ``n_edges`` edges and its labels, so that it has a match at least.

    It grows from a drawn edge (``first``, where it is known) by the incident edge with the smallest hash: ``dense`` prefers edges between chosen vertices,
    ``sparse`` edges to new ones, ``semi`` takes turns. If the component has fewer edges, the pattern has too.
    """
    n = csr.n

    with np.errstate(over="ignore"):
        first = first_edge(csr, seed) if first is None else first
        chosen, places = [first], {first // n: 0, first % n: 1}
        taken = {first}
        inner: list[tuple[int, int]] = []  # edges between chosen vertices, by hash
        outer: list[tuple[int, int, int]] = []  # per chosen vertex its next edge to another one, by hash
        open_: dict[int, tuple[np.ndarray, np.ndarray, int]] = {}

        def advance(v: int) -> None:
            """Vertex ``v`` offers its next edge that isn't between chosen vertices; those are in ``inner``."""
            marks, keys, at = open_[v]
            while at < len(keys) and (k := int(keys[at])) // n in places and k % n in places:
                at += 1
            open_[v] = marks, keys, at + 1
            if at < len(keys):
                heapq.heappush(outer, (int(marks[at]), int(keys[at]), v))

        def reach(v: int) -> None:
            out = v * n + csr.out_to[csr.out_ptr[v] : csr.out_ptr[v + 1]].astype(np.int64)
            into = csr.in_to[csr.in_ptr[v] : csr.in_ptr[v + 1]].astype(np.int64) * n + v
            keys = np.concatenate([out, into])
            keys = keys[keys // n != keys % n]
            marks = _mark(keys, seed)
            own = np.array(list(places))
            closed = np.isin(keys // n, own) & np.isin(keys % n, own)
            for x in zip(marks[closed].tolist(), keys[closed].tolist(), strict=True):
                heapq.heappush(inner, x)
            marks, keys = marks[~closed], keys[~closed]
            order = np.lexsort((keys, marks))
            open_[v] = marks[order], keys[order], 0
            advance(v)

        def settle() -> None:
            """The heads are edges that can be taken."""
            while inner and inner[0][1] in taken:
                heapq.heappop(inner)
            while outer and outer[0][1] // n in places and outer[0][1] % n in places:
                advance(heapq.heappop(outer)[2])

        for v in list(places):
            reach(v)
        settle()
        while len(chosen) < n_edges and (inner or outer):
            closes = density == "dense" or density == "semi" and len(chosen) % 2 == 1
            if inner and (closes or not outer):
                key = heapq.heappop(inner)[1]
            else:
                _, key, v = heapq.heappop(outer)
            taken.add(key)
            chosen.append(key)
            for u in (key // n, key % n):
                if u not in places:
                    places[u] = len(places)
                    reach(u)
                    advance(v)
            settle()
    name_of = {i: x for x, i in csr.label_code.items()}
    labels = tuple(name_of[int(csr.vlabel[v])] for v in places)

    def label(key: int) -> str | None:
        if not edge_labels:
            return None
        s, d = np.array([key // n]), np.array([key % n])
        return next((x for x in sorted(csr.label_keys) if csr.has_edge(s, d, x)[0]), None)

    return PatternGraph(labels, tuple((places[k // n], places[k % n], label(k)) for k in chosen), f"{density}-{n_edges}-{seed}")


def density_class(pattern: PatternGraph) -> float:
    """Edges per vertex."""
    return len(pattern.edges) / pattern.size
