"""Directed cycles by two halves that meet, over a target's arrays.

A cycle is a path that leaves its first vertex and one that leads back to it, half as long each, with the same far end. A task makes
both halves of its roots, a block at a time, and joins them there, so that neither the paths nor what closes them is shuffled.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ..model import Csr, PatternGraph, TargetGraph
from ..plans.search_plan import build
from ..sources import array_files
from .dfs import Counters, Kernel

#: Rows of a half that are held at a time.
BLOCK = 1 << 19
#: Edges of the target for a task's roots.
EDGES = 500_000


def cycle(pattern: PatternGraph) -> list[int] | None:
    """The pattern's vertices along its edges if it is one directed cycle of three or more without edge labels."""
    after = {s: d for s, d, x in pattern.edges if x is None}
    if pattern.size < 3 or not len(after) == len(pattern.edges) == pattern.size:
        return None
    way = [0]
    while len(way) < pattern.size and after.get(way[-1], 0) not in way:
        way.append(after[way[-1]])
    return way if len(way) == pattern.size and after.get(way[-1]) == 0 else None


def _path(csr: Csr, labels: list[str | None], out: bool) -> Kernel:
    """Paths of these labels that leave their first vertex, or lead to it."""
    edges = tuple((i, i + 1, None) if out else (i + 1, i, None) for i in range(len(labels) - 1))
    return Kernel(csr, build(PatternGraph(tuple(labels), edges), "ord", order=list(range(len(labels)))))


def closed(csr: Csr, labels: list[str | None], roots: np.ndarray, block: int = BLOCK) -> Iterator[np.ndarray]:
    """Cycles of these labels through ``roots`` as their first vertex."""
    half = (len(labels) + 2) // 2
    leaving, leading = _path(csr, labels[:half], True), _path(csr, [labels[0], *labels[: half - 2 : -1]], False)
    for _, there in leaving.run(leaving.seeds(roots), Counters(), block=block):
        ends = there[:, 0] * csr.n + there[:, -1]
        for _, back in leading.run(np.unique(there[:, 0])[:, None], Counters(), block=block):
            met = back[:, 0] * csr.n + back[:, -1]
            order = np.argsort(met, kind="stable")
            met = met[order]
            low = np.searchsorted(met, ends)
            row = np.flatnonzero(met[np.minimum(low, len(met) - 1)] == ends)
            low, count = low[row], np.searchsorted(met, ends[row], "right") - low[row]
            inner = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
            left, right = there[np.repeat(row, count)], back[order[np.repeat(low, count) + inner]][:, -2:0:-1]
            fine = np.ones(len(left), bool)
            for i in range(right.shape[1]):
                fine &= (left != right[:, i : i + 1]).all(axis=1)
            if fine.any():
                yield np.concatenate([left, right], axis=1)[fine]


def search(target: TargetGraph, pattern: PatternGraph, columns: list[str], tasks: int | None = None, max_bytes: int | None = None, block: int = BLOCK) -> DataFrame:
    """Every mapping of a cycle, a column per pattern vertex."""
    way = cycle(pattern)
    if way is None:
        raise ValueError("halves are for directed cycles without edge labels")
    spark = target.vertices.sparkSession
    arrays, labels = array_files.opener(target, max_bytes), [pattern.labels[v] for v in way]
    tasks = tasks or max(4 * spark.sparkContext.defaultParallelism, -(-target.edges.count() // EDGES))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in batch.column(0).to_pylist():
                csr = arrays()
                for found in closed(csr, labels, np.arange(part, csr.n, tasks), block):
                    yield pa.RecordBatch.from_pydict({columns[v]: csr.vids[found[:, i]] for i, v in enumerate(way)})

    found = spark.range(0, tasks, 1, tasks).mapInArrow(run, ", ".join(f"{columns[v]} long" for v in way))
    return found.select(*columns)
