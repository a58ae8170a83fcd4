"""Near-duplicate vectors: random-hyperplane sign hashing in several tables, exact cosines, connected components.

Equal vectors are one node with a multiplicity. Each table hashes a node to the signs of its products with ``bits``
random directions. A node whose bucket holds another one is a candidate there; cosines are computed in double precision
for all pairs of a bucket, in blocks, and a pair is counted in the first table in which it meets. What leaves a bucket is
a count and one link per node, never its pairs.

``bits`` and the number of tables follow from the number of nodes by one formula: two bits more than its logarithm, and as
many tables as leave a pair exactly at the threshold unmet with probability ``miss``; closer pairs are missed less.

Defined cases: null or zero vectors and those with null or non-finite components link with nothing, nor do vectors of
different lengths; null ids sort last in choosing a smallest id; rows that share an id are rows of their own; an empty
table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stage
from .components import components

#: Nodes of a block; a task compares two blocks at most.
BLOCK = 2048
_PAIRS = 100_000


def plan_tables(nodes: int, threshold: float, miss: float) -> tuple[int, int]:
    """(bits, tables) for so many nodes."""
    bits = min(40, max(6, math.ceil(math.log2(max(nodes, 2))) + 2))
    meet = (1 - math.acos(threshold) / math.pi) ** bits
    return bits, math.ceil(math.log(miss) / math.log1p(-meet))


class Hyperplanes:
    """The signs of a vector's products with random directions, per table as one integer."""

    def __init__(self, bits: int, tables: int, seed: int):
        self.bits, self.tables, self.seed = bits, tables, seed
        self._planes: dict[int, np.ndarray] = {}

    def codes(self, x: np.ndarray) -> np.ndarray:
        planes = self._planes.get(x.shape[1])
        if planes is None:
            planes = self._planes[x.shape[1]] = np.random.default_rng([self.seed, x.shape[1]]).standard_normal((x.shape[1], self.tables * self.bits))
        signs = (x @ planes > 0).reshape(len(x), self.tables, self.bits)
        return signs @ (1 << np.arange(self.bits, dtype=np.int64))


def _unit(raws: list[bytes]) -> np.ndarray:
    x = np.frombuffer(b"".join(raws), np.float64).reshape(len(raws), -1)
    x = x / np.abs(x).max(1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _vectors(table: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """Rows (vec_id, v): the components as doubles, packed; null where the vector links with nothing."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[bytes | None] = []
            for one in batch.column(1):
                x = None if not one.is_valid or one.values.null_count else one.values.to_numpy(zero_copy_only=False).astype(np.float64) + 0.0
                out.append(x.tobytes() if x is not None and np.isfinite(x).all() and x.any() else None)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], names=["vec_id", "v"])

    return table.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).cast("array<double>").alias("v")).mapInArrow(pack, "vec_id long, v binary")


def _buckets(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[list[tuple]]:
    """Rows that share the first ``keys`` columns, of batches sorted by these."""
    group: list[tuple] = []
    for batch in batches:
        for row in zip(*(x.to_pylist() for x in batch.columns), strict=True):
            if group and group[-1][:keys] != row[:keys]:
                yield group
                group = []
            group.append(row)
    if group:
        yield group


def compare(x: np.ndarray, weight: np.ndarray, block: np.ndarray, cross: bool, table: int, planes: Hyperplanes, threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """Of a bucket's nodes (unit rows of x): links first met in this table, by the weight of the other end, and roots.

    ``cross``: only pairs between the two blocks count.
    """
    link = x @ x.T >= threshold
    np.fill_diagonal(link, False)
    if cross:
        link &= block[:, None] != block[None, :]
    counted = np.zeros(len(x), np.int64)
    a, b = np.nonzero(np.triu(link))
    if len(a):
        used = np.unique(np.concatenate([a, b]))
        codes = planes.codes(x[used])[:, :table]
        a, b = np.searchsorted(used, a), np.searchsorted(used, b)
        for at in range(0, len(a), _PAIRS):
            p, q = a[at : at + _PAIRS], b[at : at + _PAIRS]
            new = ~(codes[p] == codes[q]).any(1)
            np.add.at(counted, used[p[new]], weight[used[q[new]]])
            np.add.at(counted, used[q[new]], weight[used[p[new]]])
    root = np.arange(len(x))
    while len(a):
        least = root.copy()
        for part in range(0, len(x), 512):
            rows = link[part : part + 512]
            np.minimum(least[part : part + 512], np.where(rows, root[None, :], len(x)).min(1), out=least[part : part + 512])
        least = least[least]
        if (least == root).all():
            break
        root = least
    return counted, root


def link_nodes(nodes: DataFrame, threshold: float, miss: float, seed: int, block: int = BLOCK) -> DataFrame:
    """From written rows (node, v, n) to rows (node, links, root), at most one per node and bucket."""
    bits, tables = plan_tables(nodes.count(), threshold, miss)
    planes = Hyperplanes(bits, tables, seed)

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            by_length: dict[int, list[int]] = {}
            raws = batch.column(1).to_pylist()
            for i, raw in enumerate(raws):
                by_length.setdefault(len(raw), []).append(i)
            for length, rows in by_length.items():
                for at in range(0, len(rows), 1024):
                    part = rows[at : at + 1024]
                    codes = planes.codes(_unit([raws[i] for i in part]))
                    node = np.repeat(batch.column(0).to_numpy()[part], tables)
                    yield pa.RecordBatch.from_arrays([pa.array(node), pa.array(np.tile(np.arange(tables, dtype=np.int32), len(part))), pa.array(np.full(len(node), length, np.int32)), pa.array(codes.ravel())], names=["node", "tab", "size", "code"])

    places = stage(nodes.select("node", "v").mapInArrow(hashed, "node long, tab int, size int, code long"), "hashes")
    shared = places.groupBy("tab", "size", "code").agg(F.count("*").alias("members")).filter("members > 1")
    rows = places.join(shared, ["tab", "size", "code"]).withColumn("blocks", F.ceil(F.col("members") / block).cast("int")).withColumn("own", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    # A node goes to the tasks of every pair of blocks that has its own.
    rows = rows.select("*", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")).select("tab", "size", "code", F.least("own", "other").alias("low"), F.greatest("own", "other").alias("high"), "own", "node")
    keys = ["tab", "size", "code", "low", "high"]
    rows = rows.join(nodes, "node").select(*keys, "own", "node", "n", "v").repartition(*keys).sortWithinPartitions(*keys)

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in _buckets(batches, 5):
            table, _, _, low, high = group[0][:5]
            own, node, weight, raws = zip(*(x[5:] for x in group), strict=True)
            if len(node) < 2:
                continue
            node = np.array(node, np.int64)
            counted, root = compare(_unit(list(raws)), np.array(weight, np.int64), np.array(own), low != high, table, planes, threshold)
            found = (counted > 0) | (root != np.arange(len(node)))
            if found.any():
                yield pa.RecordBatch.from_arrays([pa.array(node[found]), pa.array(counted[found]), pa.array(node[root[found]])], names=["node", "links", "root"])

    return rows.mapInArrow(verify, "node long, links long, root long")


def near_duplicate_vectors(table: DataFrame, threshold: float = 0.95, miss: float = 1e-4, seed: int = 7, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """Rows (vec_id, n_links, component_id, kept)."""
    rows = stage(_vectors(table, id_col, vector_col), "vectors")
    distinct = rows.filter("v is not null").groupBy("v").agg(F.min("vec_id").alias("least"), F.count("*").alias("n"))
    nodes = stage(distinct.withColumn("node", F.monotonically_increasing_id()), "nodes")
    found = stage(link_nodes(nodes.select("node", "v", "n"), threshold, miss, seed), "vector-links")
    links = found.groupBy("node").agg(F.sum("links").alias("links"))
    roots = components(found.select(F.col("node").alias("a"), F.col("root").alias("b")))
    least = roots.join(nodes.select("node", "least"), "node").groupBy("root").agg(F.min("least").alias("smallest"))
    linked = roots.join(least, "root").select("node", "smallest")
    known = nodes.join(links, "node", "left").join(linked, "node", "left").select("v", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("smallest", "least").alias("component_id"))
    out = rows.join(known, "v", "left").select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.when(F.col("n_links").isNull(), F.col("vec_id")).otherwise(F.col("component_id")).alias("component_id"))
    return out.withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))
