"""A target's arrays as files that tasks make and map, for targets whose arrays neither the driver nor every worker can hold.

Vertices are ranked by range-dealt tasks, edges are turned into pairs of ranks, written, and sorted twice, by source and by destination. Each
task writes a piece of an array below ``spark.checkpoint.dir``; the pieces are then joined to one file an array, and removed. The driver sees
names and counts, and the distinct vertex labels. Workers map the files read-only, so that they share one copy in the machine's cache;
from another file system they are first copied to a nameless local file.
"""

from __future__ import annotations

import contextlib
import tempfile
import uuid
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import Csr, TargetGraph, by_label
from ..session import materialise, shared_folder

#: Rows of a task that writes a piece.
PIECE = 4_000_000
COPY = 4 << 20
PIECES = "part int, name string, uri string, n long"

_opened: dict[str, Csr] = {}


def _at(uri: str):
    from pyarrow import fs

    if uri.startswith("file:/"):
        return fs.LocalFileSystem(), "/" + uri[len("file:") :].lstrip("/")
    return (fs.LocalFileSystem(), uri) if "://" not in uri else fs.FileSystem.from_uri(uri)


@contextlib.contextmanager
def _new(folder: str, name: str) -> Iterator[tuple[str, pa.NativeFile]]:
    """A file of a name that no other attempt of a task uses; readers go by what finished tasks return."""
    uri = f"{folder}/{name}-{uuid.uuid4().hex[:12]}"
    system, path = _at(uri)
    system.create_dir(_at(folder)[1], recursive=True)
    with system.open_output_stream(path, compression=None) as out:
        yield uri, out


def _mapped(uri: str, dtype: str) -> np.ndarray:
    system, path = _at(uri)
    if not system.get_file_info(path).size:
        return np.zeros(0, dtype)
    if system.type_name == "local":
        return np.asarray(np.memmap(path, dtype, "r"))
    with tempfile.TemporaryFile() as copy, system.open_input_file(path) as read:
        while some := read.read(COPY):
            copy.write(some)
        copy.flush()
        return np.asarray(np.memmap(copy, dtype, "r"))


@dataclass(frozen=True)
class ArrayFiles:
    """The names of a target's arrays, and what tasks need to open them. Pattern edges with labels can't be searched with these."""

    files: dict[str, tuple[str, str]]  # uri and dtype by array
    label_code: dict[str | None, int]

    def open(self) -> Csr:
        """The arrays, mapped; a process keeps those of the last target."""
        key = self.files["out_to"][0]
        if key not in _opened:
            _opened.clear()
            a = {k: _mapped(*x) for k, x in self.files.items()}
            _opened[key] = Csr(a["vids"], a["vlabel"], self.label_code, a["out_ptr"], a["out_to"], a["in_ptr"], a["in_to"], None, None, None)
        return _opened[key]


def _pieces(rows: DataFrame, folder: str, by: str, count: int, made: Callable[[pa.RecordBatch], dict[str, np.ndarray]]) -> dict[str, list[str]]:
    """Files per array in the order of ``by``; a task per range, ``made`` gives what a sorted batch adds to each."""

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, files, rows = TaskContext.get().partitionId(), {}, 0
        with contextlib.ExitStack() as stack:
            for batch in batches:
                rows += batch.num_rows
                for name, array in made(batch).items():
                    if name not in files:
                        files[name] = stack.enter_context(_new(folder, f"piece-{name}"))
                    files[name][1].write(np.ascontiguousarray(array).data)
        yield pa.RecordBatch.from_pydict({"part": pa.array([part] * len(files), pa.int32()), "name": pa.array(list(files), pa.string()), "uri": pa.array([x[0] for x in files.values()], pa.string()), "n": pa.array([rows] * len(files), pa.int64())})

    tasks = max(rows.sparkSession.sparkContext.defaultParallelism, -(-count // PIECE))
    out: dict[str, list[str]] = {}
    for x in sorted(rows.repartitionByRange(tasks, by).sortWithinPartitions(by).mapInArrow(write, PIECES).collect()):
        out.setdefault(x.name, []).append(x.uri)
    return out


def _joined(spark: SparkSession, folder: str, pieces: dict[str, list[str]], n: int, index: str) -> dict[str, str]:
    """One file per array. Degrees, which are (vertex, edges) pairs, become the places where vertices' edges begin."""

    def copy(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, uris in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                degrees = np.zeros(n, np.int64) if name.endswith("_ptr") else None
                with _new(folder, name) as (uri, out):
                    for piece in uris:
                        if degrees is not None:
                            runs = _mapped(piece, index).reshape(-1, 2)
                            for at in range(0, len(runs), 1 << 20):
                                np.add.at(degrees, runs[at : at + (1 << 20), 0], runs[at : at + (1 << 20), 1])
                            continue
                        system, path = _at(piece)
                        with system.open_input_stream(path, compression=None) as read:
                            while some := read.read(COPY):
                                out.write(some)
                    if degrees is not None:
                        out.write(np.zeros(1, np.int64).data)
                        out.write(np.cumsum(degrees).data)
                yield pa.RecordBatch.from_pydict({"name": [name], "uri": [uri]})

    rows = spark.createDataFrame(list(pieces.items()), "name string, uris array<string>").repartition(len(pieces))
    out = {x.name: x.uri for x in rows.mapInArrow(copy, "name string, uri string").collect()}
    for uri in (x for uris in pieces.values() for x in uris):
        system, path = _at(uri)
        system.delete_file(path)
    return out


def write(target: TargetGraph) -> ArrayFiles:
    """Make the files. Ends of edges that are no vertices don't count, as in joins."""
    spark = target.vertices.sparkSession
    folder = f"{shared_folder(spark).rstrip('/')}/arrays-{uuid.uuid4().hex}"
    n, m = target.vertices.count(), target.edges.count()
    if n >= 3_000_000_000:
        raise ValueError(f"{n} vertices; pairs of their ranks don't fit 64 bits")
    index = "int32" if n < 1 << 31 else "int64"
    names = by_label(x.vlabel for x in target.vertices.select("vlabel").distinct().collect())
    code = {x: i for i, x in enumerate(names)}
    known = pa.array(names, pa.string())

    def vertex_arrays(batch: pa.RecordBatch) -> dict[str, np.ndarray]:
        return {"vids": batch.column(0).to_numpy(), "vlabel": pc.index_in(batch.column(1), known).to_numpy(zero_copy_only=False).astype(index)}

    none = {"vids": [], "vlabel": []}
    made = _joined(spark, folder, none | _pieces(target.vertices.select("vid", "vlabel"), folder, "vid", n, vertex_arrays), n, index)
    vids = made["vids"]

    def rank(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = _mapped(vids, "int64")
        for batch in batches:
            at, keep = [], np.full(batch.num_rows, n > 0)
            for column in (0, 1):
                end = batch.column(column).to_numpy()
                at.append(np.minimum(np.searchsorted(ids, end), n - 1))
                keep &= ids[at[-1]] == end if n else False
            yield pa.RecordBatch.from_pydict({"src": at[0][keep].astype(index), "dst": at[1][keep].astype(index)})

    kind = "int" if index == "int32" else "long"
    ranked = materialise(target.pairs().select("src", "dst").dropna().mapInArrow(rank, f"src {kind}, dst {kind}"), "ranked-edges")  # ranked once; each side's ranges are sampled and sorted from it

    for side, near, far in (("out", "src", "dst"), ("in", "dst", "src")):

        def edge_arrays(batch: pa.RecordBatch, side=side) -> dict[str, np.ndarray]:
            key = batch.column(0).to_numpy()
            vertex, edges = np.unique(key // n, return_counts=True)
            return {f"{side}_to": (key % n).astype(index), f"{side}_ptr": np.stack([vertex, edges], 1).astype(index)}

        none = {f"{side}_to": [], f"{side}_ptr": []}
        made |= _joined(spark, folder, none | _pieces(ranked.select((F.col(near).cast("long") * n + F.col(far)).alias("key")), folder, "key", m, edge_arrays), n, index)
    kinds = {"vids": "int64", "vlabel": index, "out_ptr": "int64", "out_to": index, "in_ptr": "int64", "in_to": index}
    return ArrayFiles({k: (made[k], x) for k, x in kinds.items()}, code)


#: Bytes of arrays up to which a target is broadcast: the driver holds it once as rows and twice as arrays.
HELD = 16 << 20


def opener(target: TargetGraph, max_bytes: int | None = None) -> Callable[[], Csr]:
    """What tasks call for the target's arrays: broadcast where they take ``max_bytes`` at most, mapped files where more."""
    if target.array_bytes() <= (HELD if max_bytes is None else max_bytes):
        shared = target.vertices.sparkSession.sparkContext.broadcast(target.csr())
        return lambda: shared.value
    return write(target).open


def are_mapped(arrays: Callable[[], Csr]) -> bool:
    """Does ``opener``'s result map files?"""
    return isinstance(getattr(arrays, "__self__", None), ArrayFiles)
