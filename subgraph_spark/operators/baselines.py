"""What the methods are compared with: one join per edge as SQL, and a state-space matcher with look-ahead."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ..model import Csr, PatternGraph, TargetGraph


def sql_join(pattern: PatternGraph, simple: bool = True, edges: str = "e", vertices: str = "v", count: bool = False, induced: bool = False) -> str:
    """A select over ``edges`` and ``vertices``: a join per pattern edge, injectivity and labels in the where clause."""
    where, source = [], []
    first: dict[int, str] = {}
    table = edges if simple else f"(SELECT DISTINCT src, dst FROM {edges})"
    for k, (s, d, x) in enumerate(pattern.edges):
        source.append(f"{edges if x is not None or simple else table} e{k}")
        for v, column in ((s, f"e{k}.src"), (d, f"e{k}.dst")):
            if v in first:
                where.append(f"{column} = {first[v]}")
            else:
                first[v] = column
        if x is not None:
            where.append(f"e{k}.elabel = '{x}'")
    for v in range(pattern.size):
        if pattern.labels[v] is not None or v not in first:
            source.append(f"{vertices} v{v}")
            if v in first:
                where.append(f"v{v}.vid = {first[v]}")
            first.setdefault(v, f"v{v}.vid")
            if pattern.labels[v] is not None:
                where.append(f"v{v}.vlabel = '{pattern.labels[v]}'")
    where += [f"{first[a]} <> {first[b]}" for b in range(pattern.size) for a in range(b)]
    if induced:
        have = {(s, d) for s, d, _ in pattern.edges}
        where += [f"NOT EXISTS (SELECT 1 FROM {edges} x WHERE x.src = {first[a]} AND x.dst = {first[b]})" for a in range(pattern.size) for b in range(pattern.size) if (a, b) not in have]
    what = "count(*) AS n" if count else ", ".join(f"{first[v]} AS m{v}" for v in range(pattern.size))
    return f"SELECT {what} FROM {', '.join(source)}" + (f" WHERE {' AND '.join(where)}" if where else "")


def state_space_matches(target: TargetGraph, pattern: PatternGraph) -> DataFrame:
    """Matches of ``state_space`` as m0, m1, ...; it runs in one task, over arrays whose size is checked."""
    spark = target.vertices.sparkSession
    shared = spark.sparkContext.broadcast(target.csr())
    names = [f"m{v}" for v in range(pattern.size)]

    def run(batches):
        for _ in batches:
            found = np.array(state_space(shared.value, pattern)[1], np.int64).reshape(-1, pattern.size)
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in found.T], names=names)

    return spark.range(0, 1, 1, 1).mapInArrow(run, ", ".join(f"{x} long" for x in names))


def state_space(csr: Csr, pattern: PatternGraph, first_only: bool = False) -> tuple[int, list[tuple[int, ...]]]:
    """(pairs considered, mappings): candidates are the target's frontier around the mapped part, in no clever order; a pair is
    dropped if the target vertex has fewer neighbours on the frontier, or fewer on it and beyond, than the pattern vertex.
    """
    near = pattern.adjacency()
    need = {(s, d): x for s, d, x in pattern.edges}
    code = [None if x is None else csr.label_code.get(x, -1) for x in pattern.labels]
    around = [np.unique(np.concatenate([csr.out_to[csr.out_ptr[v] : csr.out_ptr[v + 1]], csr.in_to[csr.in_ptr[v] : csr.in_ptr[v + 1]]])) for v in range(csr.n)]
    around = [x[x != v] for v, x in enumerate(around)]

    def has(s: int, d: int, label: str | None) -> bool:
        keys = csr.keys if label is None else csr.keys_of(label)
        at = np.searchsorted(keys, s * csr.n + d)
        return at < len(keys) and keys[at] == s * csr.n + d

    pairs, found = 0, []

    def extend(mapped: dict[int, int], used: set[int], edge_p: set[int], edge_t: set[int]) -> bool:
        nonlocal pairs
        if len(mapped) == pattern.size:
            found.append(tuple(int(csr.vids[mapped[v]]) for v in range(pattern.size)))
            return first_only
        on = bool(edge_p)
        v = min(edge_p) if on else min(set(range(pattern.size)) - mapped.keys())
        for t in sorted(edge_t) if on else range(csr.n):
            if t in used:
                continue
            pairs += 1
            if code[v] is not None and csr.vlabel[t] != code[v]:
                continue
            if not all(has(t, mapped[d], x) if s == v and d in mapped else has(mapped[s], t, x) if d == v and s in mapped else has(t, t, x) if s == d == v else True for (s, d), x in need.items()):
                continue
            open_p, open_t = near[v] - mapped.keys(), set(around[t].tolist()) - used
            if len(open_p & edge_p) > len(open_t & edge_t) or len(open_p) > len(open_t):
                continue
            if extend(mapped | {v: t}, used | {t}, (edge_p | open_p) - {v}, (edge_t | open_t) - {t}):
                return True
        return False

    extend({}, set(), set(), set())
    return pairs, found
