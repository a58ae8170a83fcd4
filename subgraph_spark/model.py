"""Pattern graphs, which are small and live on the driver, and target graphs, which are tables."""

from __future__ import annotations

import itertools
import re
from collections import defaultdict
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .session import materialise

VERTICES = T.StructType([T.StructField("vid", T.LongType()), T.StructField("vlabel", T.StringType())])
EDGES = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType()), T.StructField("elabel", T.StringType())])


def require(df: DataFrame, schema: T.StructType) -> DataFrame:
    """``df`` with the columns of ``schema``, cast to its types; an error names what is missing."""
    missing = [x.name for x in schema if x.name not in df.columns]
    if missing:
        raise ValueError(f"columns {missing} are missing; there are {df.columns}")
    return df.select(*[F.col(x.name).cast(x.dataType).alias(x.name) for x in schema])


@dataclass(frozen=True)
class PatternGraph:
    """``labels[i]`` is vertex i's label, None a wildcard; edges are (from, to, label or None)."""

    labels: tuple[str | None, ...]
    edges: tuple[tuple[int, int, str | None], ...] = ()
    name: str = "pattern"

    def __post_init__(self):
        if not self.labels:
            raise ValueError("a pattern has a vertex at least")
        if any(not (0 <= s < self.size and 0 <= d < self.size) for s, d, _ in self.edges):
            raise ValueError("an edge leaves the pattern")
        if len({(s, d, x) for s, d, x in self.edges}) != len(self.edges):
            raise ValueError("an edge is given twice")

    @classmethod
    def parse(cls, text: str, name: str = "pattern") -> PatternGraph:
        """Edges ``a->b`` or ``a-[label]->b`` and lone vertices, separated by semicolons; ``a:label`` names a vertex's label once."""
        ids: dict[str, int] = {}
        labels: dict[int, str | None] = {}
        edges = []

        def vertex(word: str) -> int:
            key, _, label = word.strip().partition(":")
            i = ids.setdefault(key, len(ids))
            labels[i] = label or labels.get(i)
            return i

        for part in filter(None, (x.strip() for x in text.split(";"))):
            m = re.fullmatch(r"(.+?)-(?:\[(.*)\]-)?>(.+)", part)
            if m:
                edges.append((vertex(m[1]), vertex(m[3]), m[2]))
            else:
                vertex(part)
        return cls(tuple(labels[i] for i in range(len(ids))), tuple(edges), name)

    @property
    def size(self) -> int:
        return len(self.labels)

    def adjacency(self) -> list[set[int]]:
        """Neighbours whatever the direction, without loops."""
        near: list[set[int]] = [set() for _ in self.labels]
        for s, d, _ in self.edges:
            if s != d:
                near[s].add(d)
                near[d].add(s)
        return near

    def out_degree(self, v: int) -> int:
        return len({d for s, d, _ in self.edges if s == v})

    def in_degree(self, v: int) -> int:
        return len({s for s, d, _ in self.edges if d == v})

    def components(self) -> int:
        near, seen, n = self.adjacency(), set(), 0
        for v in range(self.size):
            if v not in seen:
                n, todo = n + 1, [v]
                while todo:
                    x = todo.pop()
                    if x not in seen:
                        seen.add(x)
                        todo += near[x]
        return n

    def with_labels(self, labels) -> PatternGraph:
        return PatternGraph(tuple(labels), self.edges, self.name)

    def automorphisms(self) -> int:
        """Label-keeping mappings of the pattern onto itself."""
        edges = set(self.edges)
        near = self.adjacency()
        kind = [(self.labels[v], self.in_degree(v), self.out_degree(v)) for v in range(self.size)]

        def grow(image: list[int]) -> int:
            v = len(image)
            if v == self.size:
                return 1
            total = 0
            for w in range(self.size):
                if w in image or kind[w] != kind[v]:
                    continue
                new = [*image, w]
                if all((new[s], new[d], x) in edges for s, d, x in self.edges if max(s, d) == v):
                    total += grow(new)
            return total

        return grow([]) if near is not None else 0


def by_label(labels: Iterable[str | None]) -> list[str | None]:
    """Distinct labels in the order of their codes."""
    return sorted({*labels}, key=lambda x: (x is not None, x or ""))


@dataclass
class Csr:
    """A target as arrays: vertex ids ascending, neighbours sorted, keys (src * n + dst) for look-ups.

    Mapped arrays have no keys, edge labels and loops: look-ups go to the source's neighbours.
    """

    vids: np.ndarray
    vlabel: np.ndarray  # codes
    label_code: dict[str | None, int]
    out_ptr: np.ndarray
    out_to: np.ndarray
    in_ptr: np.ndarray
    in_to: np.ndarray
    keys: np.ndarray | None
    label_keys: dict[str, np.ndarray] | None
    loops: np.ndarray | None
    masks: np.ndarray | None = None  # domain words, a column each

    @property
    def n(self) -> int:
        return len(self.vids)

    def degree(self, v: np.ndarray, out: bool) -> np.ndarray:
        ptr = self.out_ptr if out else self.in_ptr
        return ptr[v + 1] - ptr[v]

    def keys_of(self, label: str) -> np.ndarray:
        if self.label_keys is None:
            raise ValueError("mapped arrays have no edge labels")
        return self.label_keys.get(label, np.zeros(0, np.int64))

    def has_edge(self, s: np.ndarray, d: np.ndarray, label: str | None = None) -> np.ndarray:
        """Is there an edge, for each pair of vertices?"""
        if label is None and self.keys is None:
            low, high = self.out_ptr[s], self.out_ptr[s + 1]
            ends = high
            while np.any(low < high):
                middle = (low + high) // 2
                right = (low < high) & (self.out_to[np.minimum(middle, len(self.out_to) - 1)] < d)
                low, high = np.where(right, middle + 1, low), np.where(right, high, np.minimum(high, middle))
            return (low < ends) & (self.out_to[np.minimum(low, len(self.out_to) - 1)] == d) if len(self.out_to) else np.zeros(len(ends), bool)
        keys = self.keys if label is None else self.keys_of(label)
        if not len(keys):
            return np.zeros(len(s), bool)
        want = s * self.n + d
        at = np.minimum(np.searchsorted(keys, want), len(keys) - 1)
        return keys[at] == want

    def blocks(self, size: int = 1 << 20) -> Iterator[tuple[int, int]]:
        """Ranges of vertices with ``size`` edges in either direction at most, or of one vertex."""
        a = 0
        while a < self.n:
            ends = [int(np.searchsorted(p, p[a] + size, "right")) - 1 for p in (self.out_ptr, self.in_ptr)]
            b = max(a + 1, min(*ends, a + size, self.n))
            yield a, b
            a = b


class TargetTooLarge(RuntimeError):
    """The target's arrays would take more memory than allowed."""


@dataclass
class TargetGraph:
    """``vertices`` (vid, vlabel) and ``edges`` (src, dst, elabel).

    ``simple`` targets have one edge per (src, dst), labelled with the smallest label; others one per (src, dst, elabel).
    Edges whose ends aren't vertices have no part in joins or arrays.
    """

    vertices: DataFrame
    edges: DataFrame
    simple: bool = True
    name: str = "target"
    _degrees: DataFrame | None = field(default=None, repr=False)

    @classmethod
    def of(cls, vertices: DataFrame, edges: DataFrame, simple: bool = True, name: str = "target", written: bool = False) -> TargetGraph:
        vertices, edges = require(vertices, VERTICES), require(edges, EDGES)
        edges = edges.groupBy("src", "dst").agg(F.min("elabel").alias("elabel")) if simple else edges.distinct()
        if written:
            vertices, edges = materialise(vertices, "vertices"), materialise(edges, "edges")
        return cls(vertices, edges, simple, name)

    def written(self, degrees: bool = True) -> TargetGraph:
        """The same target from written tables, degrees included where searches by joins need them, for several searches."""
        new = TargetGraph(materialise(self.vertices, "vertices"), materialise(self.edges, "edges"), self.simple, self.name)
        if degrees:
            new._degrees = materialise(new.degrees(), "degrees")
        return new

    def pairs(self) -> DataFrame:
        """(src, dst), each once."""
        edges = self.edges.select("src", "dst")
        return edges if self.simple else edges.distinct()

    def degrees(self) -> DataFrame:
        """(vid, vlabel, indeg, outdeg), neighbours counted once per direction."""
        if self._degrees is not None:
            return self._degrees
        pairs = self.pairs()
        out = pairs.groupBy(F.col("src").alias("vid")).agg(F.count("*").cast("int").alias("outdeg"))
        into = pairs.groupBy(F.col("dst").alias("vid")).agg(F.count("*").cast("int").alias("indeg"))
        rows = self.vertices.join(into, "vid", "left").join(out, "vid", "left")
        return rows.select("vid", "vlabel", F.coalesce("indeg", F.lit(0)).alias("indeg"), F.coalesce("outdeg", F.lit(0)).alias("outdeg"))

    def symmetrized(self) -> TargetGraph:
        back = self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "elabel")
        return TargetGraph.of(self.vertices, self.edges.unionByName(back), self.simple, self.name)

    def array_bytes(self, words: int = 0) -> int:
        n, m = self.vertices.count(), self.edges.count()
        return 8 * (5 * n + 4 * m + n * words)

    def csr(self, max_bytes: int = 1 << 30, masks: DataFrame | None = None, words: int = 0) -> Csr:
        """The arrays, on the driver. Their size is computed before anything is collected."""
        need = self.array_bytes(words)
        if need > max_bytes:
            raise TargetTooLarge(f"{need} bytes for the target's arrays; {max_bytes} are allowed")
        vertices = self.vertices.toArrow()
        if vertices.column("vid").null_count:
            raise TypeError("a vertex has no id")
        ids, vlabel = vertices.column("vid").to_numpy(), vertices.column("vlabel")
        order = np.argsort(ids, kind="stable")
        vids = ids[order]
        n = len(vids)
        code = {x: i for i, x in enumerate(by_label(vlabel.unique().to_pylist()))}
        vlabel = pc.index_in(vlabel, pa.array(list(code), vlabel.type)).to_numpy()[order].astype(np.int64)  # labels are never held as Python's texts, of which there is one a row
        edges = self.edges.dropna(subset=["src", "dst"]).toArrow()
        ends = [edges.column(c).to_numpy() for c in ("src", "dst")]
        known = np.isin(ends[0], vids) & np.isin(ends[1], vids)
        src, dst = (np.searchsorted(vids, x[known]) for x in ends)
        names = [x for x in edges.column("elabel").unique().to_pylist() if x is not None]
        labels = pc.index_in(edges.column("elabel"), pa.array(names, edges.column("elabel").type)).fill_null(-1).to_numpy()[known]
        names = {x: i for i, x in enumerate(names) if np.any(labels == i)}
        keys = np.unique(src.astype(np.int64) * n + dst)
        s, d = keys // max(n, 1), keys % max(n, 1)
        back = np.lexsort((s, d))
        labelled = {x: np.unique((src[labels == i].astype(np.int64) * n + dst[labels == i])) for x, i in names.items()}
        found = None
        if masks is not None:
            rows = masks.toArrow()
            found = np.zeros((n, words), np.int64)
            at = np.searchsorted(vids, rows.column("vid").to_numpy())
            for w in range(words):
                found[at, w] = rows.column(f"mask{w}").to_numpy()
        ptr = lambda x: np.concatenate([[0], np.cumsum(np.bincount(x, minlength=n))]).astype(np.int64)
        return Csr(vids, vlabel, code, ptr(s), d, ptr(d[back]), s[back], keys, labelled, np.isin(np.arange(n, dtype=np.int64) * (n + 1), keys), found)


def random_graph(n: int, m: int, labels: int, seed: int) -> tuple[list[tuple[int, str]], list[tuple[int, int, str | None]]]:
    """A seeded graph as lists, for tests."""
    rng = np.random.default_rng(seed)
    every = list(itertools.product(range(n), repeat=2))
    picked = rng.choice(len(every), min(m, len(every)), replace=False)
    return [(i, f"L{rng.integers(labels)}") for i in range(n)], [(*every[i], f"e{rng.integers(2)}") for i in picked]


def edges_between(edges) -> dict[tuple[int, int], set[str | None]]:
    """Labels by (from, to)."""
    out = defaultdict(set)
    for s, d, x in edges:
        out[s, d].add(x)
    return out
