"""SimHash fingerprints of word shingles, linked within a Hamming radius by Burkhard-Keller trees.

Fingerprints. Words of the ASCII-lower-cased text, shingles of ``width`` words, XXH64 with seed 42; a bit is set if it is
in over half of the hashes.

Search. Equal fingerprints are one node. Two fingerprints within radius r share at least one of r + 1 bit blocks, so they
meet in a shard of that block's value, and no pair is missed. In a shard a tree is grown in which a child hangs
on the edge that carries its distance to the parent; a search follows only edges within the radius of the distance it
measures. A shard with more nodes than ``shard`` is cut into trees of at most about that size, and each tree, whose
size is bounded, is carried to all of the shard's queries. What leaves a shard is a forest, never its pairs.

Defined cases: a null text is empty and has fingerprint zero, which links like any other; null ids sort last in choosing
a component's smallest id; rows that share an id are rows of their own in the result; an empty table gives no rows;
other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import in_arrow, stage, whole_text
from .components import components

#: Nodes of a tree, about.
SHARD = 4096
#: Hashes whose bits are counted at a time.
_BLOCK = 1 << 14


def majority(hashes: Iterable[np.ndarray]) -> int:
    """The bits that are set in over half of the hashes, which come in blocks."""
    counts, n = np.zeros(64, np.int64), 0
    for part in hashes:
        counts += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
        n += len(part)
    return int(np.packbits((2 * counts > n).astype(np.uint8), bitorder="little").view(np.uint64)[0])


def fingerprint(text: str, width: int = 3) -> int:
    """The 64-bit fingerprint of one text."""
    words = text.encode().lower().split()
    return majority(shingle_hashes(words, width)) if words else 0


def shingle_hashes(words: list[bytes], width: int) -> Iterator[np.ndarray]:
    """XXH64 with seed 42 of each shingle, in blocks; fewer words than ``width`` are one shingle."""
    from xxhash import xxh64_intdigest

    for at in range(0, max(1, len(words) - width + 1), _BLOCK):
        part = words[at : at + _BLOCK + width - 1]
        flat = b" ".join(part)
        if len(words) <= width:
            shingles = [flat]
        else:
            starts = np.zeros(len(part) + 1, np.int64)
            np.cumsum([len(w) + 1 for w in part], out=starts[1:])
            shingles = [flat[a:b] for a, b in zip(starts[: len(part) - width + 1].tolist(), (starts[width:] - 1).tolist(), strict=True)]
        yield np.array([xxh64_intdigest(x, 42) for x in shingles], np.uint64)


def fingerprints(docs: DataFrame, width: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (doc_id, fp), fp the fingerprint as a signed long. Nothing is shuffled."""

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = np.array([fingerprint(x.as_py(), width) for x in batch.column(1)], np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found.view(np.int64))], names=["doc_id", "fp"])

    return in_arrow(docs.select(F.col(id_col).cast("long").alias("doc_id"), whole_text(text_col).alias("text")), make, "doc_id long, fp long")


class BKTree:
    """A tree over distinct 64-bit values, as arrays: each node's value and its children by distance."""

    def __init__(self, values: np.ndarray):
        self.values = np.asarray(values, np.uint64)
        self.children: list[dict[int, int]] = [{} for _ in self.values]
        plain = self.values.tolist()
        for node in range(1, len(plain)):
            value, at = plain[node], 0
            while True:
                distance = (plain[at] ^ value).bit_count()
                below = self.children[at].get(distance)
                if below is None:
                    self.children[at][distance] = node
                    break
                at = below

    def links(self, queries: np.ndarray, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(query, node) index pairs within the radius, a tree level at a time, over all queries together."""
        if not len(self.values) or not len(queries):
            return
        edges = [(parent, distance, child) for parent, x in enumerate(self.children) for distance, child in x.items()]
        edges.sort()
        table = np.array(edges, np.int64).reshape(-1, 3)
        first = np.searchsorted(table[:, 0], np.arange(len(self.values) + 1))
        # Positions in the edge table: those of a parent are sorted by distance.
        code = table[:, 0] * 128 + table[:, 1]
        query, node = np.arange(len(queries)), np.zeros(len(queries), np.int64)
        while len(query):
            distance = np.bitwise_count(queries[query] ^ self.values[node]).astype(np.int64)
            near = distance <= radius
            if near.any():
                yield query[near], node[near]
            inner = first[node] < first[node + 1]
            query, node, distance = query[inner], node[inner], distance[inner]
            low = np.searchsorted(code, node * 128 + np.maximum(distance - radius, 0))
            high = np.searchsorted(code, node * 128 + np.minimum(distance + radius, 127), "right")
            count = high - low
            query = np.repeat(query, count)
            place = np.repeat(low - np.concatenate([[0], np.cumsum(count)[:-1]]), count) + np.arange(len(query)) if len(query) else query
            node = table[place, 2]


def forest(queries: np.ndarray, tree: BKTree, radius: int, block: int = 2048) -> tuple[np.ndarray, np.ndarray]:
    """Links that join the same values as all links within the radius do, at most one per value: (value, root)."""
    every = np.unique(np.concatenate([queries, tree.values]))
    root = np.arange(len(every))
    node_of = np.searchsorted(every, tree.values)

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for at in range(0, len(queries), block):
        part = queries[at : at + block]
        query_of = np.searchsorted(every, part)
        for query, node in tree.links(part, radius):
            a, b = query_of[query], node_of[node]
            apart = root[a] != root[b]
            for x, y in zip(a[apart].tolist(), b[apart].tolist(), strict=True):
                p, q = find(x), find(y)
                if p != q:
                    root[max(p, q)] = min(p, q)
    roots = np.array([find(x) for x in range(len(every))], np.int64)
    joined = roots != np.arange(len(every))
    return every[joined], every[roots[joined]]


def pair(fps: np.ndarray, hangs: np.ndarray, asks: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """``forest`` for a shard of two ascending values, most shards: a tree of one node or two, walked without making it."""
    near = (int(fps[0]) ^ int(fps[1])).bit_count() <= radius and (hangs & asks[::-1]).any()
    return (fps[1:], fps[:1]) if near else (fps[:0], fps[:0])


def _blocks(radius: int) -> list[tuple[int, int]]:
    """Place and length of radius + 1 blocks that cover 64 bits."""
    cuts = [64 * k // (radius + 1) for k in range(radius + 2)]
    return [(a, b - a) for a, b in zip(cuts, cuts[1:], strict=False)]


def link_fingerprints(distinct: DataFrame, radius: int = 2, shard: int = SHARD) -> DataFrame:
    """Edges (a, b) over the distinct fingerprints of ``distinct`` (fp), that have the components of all links."""
    keys = F.array(*[F.struct(F.lit(k).alias("block"), F.shiftrightunsigned("fp", place).bitwiseAND(F.lit((1 << n) - 1).cast("long")).alias("value")) for k, (place, n) in enumerate(_blocks(radius))])
    rows = distinct.select("fp", F.explode(keys).alias("key")).select("fp", "key.block", "key.value")
    sizes = rows.groupBy("block", "value").agg(F.count("*").alias("n")).filter("n > 1")
    rows = rows.join(sizes, ["block", "value"]).withColumn("trees", F.ceil(F.col("n") / shard).cast("int")).withColumn("slices", F.ceil(F.col("n") / (64 * shard)).cast("int"))
    # A value hangs in one of its shard's trees, which goes to all slices of queries, and queries every tree in one slice.
    # In a shard of one tree and one slice these are one row.
    rows = rows.select("block", "value", "fp", "slices", F.pmod(F.xxhash64("fp"), F.col("trees")).alias("own"), F.pmod(F.hash("fp"), F.col("slices")).alias("mine"), F.explode(F.sequence(F.lit(0), F.col("trees") - 1)).alias("tree"))
    rows = rows.select("*", F.explode(F.when(F.col("own") == F.col("tree"), F.sequence(F.lit(0), F.col("slices") - 1)).otherwise(F.array("mine"))).alias("slice"))
    rows = rows.select("block", "value", "tree", "slice", "fp", (F.col("own") == F.col("tree")).alias("hangs"), (F.col("mine") == F.col("slice")).alias("asks"))
    rows = rows.repartition("block", "value", "tree", "slice").sortWithinPartitions("block", "value", "tree", "slice", "fp")

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for fps, hangs, asks in _shards(batches):
            a, b = pair(fps, hangs, asks, radius) if len(fps) == 2 else forest(fps[asks], BKTree(fps[hangs]), radius)
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"])

    return rows.mapInArrow(search, "a long, b long")


def _shards(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """The sorted rows of each (block, value, tree, slice): fingerprints, which hang in the tree, and which are queries."""
    held: list[np.ndarray] | None = None
    for batch in batches:
        if not batch.num_rows:
            continue
        columns = [x.to_numpy(zero_copy_only=False) for x in batch.columns]
        columns[4] = columns[4].astype(np.int64).view(np.uint64)
        if held is not None:
            columns = [np.concatenate([a, b]) for a, b in zip(held, columns, strict=True)]
        change = np.zeros(len(columns[0]), bool)
        for x in columns[:4]:
            change[1:] |= x[1:] != x[:-1]
        cuts = [0, *np.flatnonzero(change).tolist()]
        for a, b in zip(cuts, cuts[1:], strict=False):
            yield columns[4][a:b], columns[5][a:b].astype(bool), columns[6][a:b].astype(bool)
        held = [x[cuts[-1] :] for x in columns]
    if held is not None:
        yield held[4], held[5].astype(bool), held[6].astype(bool)


def near_duplicates(docs: DataFrame, width: int = 3, radius: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (doc_id, fingerprint, component_id): component_id is the smallest id reachable over links.

    Ids meet their fingerprint's component in a join whose uneven side Spark splits; all else is on distinct fingerprints.
    """
    marked = stage(fingerprints(docs, width, id_col, text_col), "fingerprints")
    nodes = stage(marked.groupBy("fp").agg(F.min("doc_id").alias("least")), "distinct-fingerprints")
    roots = components(link_fingerprints(nodes.select("fp"), radius))
    least = roots.join(nodes, roots["node"] == nodes["fp"]).groupBy("root").agg(F.min("least").alias("component_id"))
    linked = roots.join(least, "root").select(F.col("node").alias("fp"), "component_id")
    known = stage(nodes.join(linked, "fp", "left").select("fp", F.coalesce("component_id", "least").alias("component_id")), "components")
    text = F.lower(F.lpad(F.hex("fp"), 16, "0"))
    return marked.join(known, "fp").select("doc_id", text.alias("fingerprint"), "component_id")
