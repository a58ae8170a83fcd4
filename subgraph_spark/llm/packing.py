"""Hierarchical residual packing of documents into sequences of a fixed length.

A document's ids and an end id are cut only if longer than a sequence. Whole sequences are done at once. The other
pieces are items: each task packs the items it has by best fit, longest first, and emits the bins that are nearly full.
Bins that aren't become items themselves, meet those of other tasks in a tree, and are packed again, until one task
holds the rest or a round no longer saves bins. A bin's row carries its members, so no step looks anything up.

Defined cases: a null text is empty (the end id alone); null and repeated ids are documents of their own; an empty
table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import in_arrow, stage, whole_text
from .encoding import MOST, encoder_for

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
_MEMBER = np.dtype([("doc_id", "<i8"), ("null", "u1"), ("piece", "<i4"), ("start", "<i8"), ("length", "<i4"), ("crc", "<u4"), ("offset", "<i4")])
_BINS = "sequence_id long, used int, members binary"
#: Items that a task packs at a time.
ITEMS = 100_000
#: Tasks of one round whose underfull bins meet in a task of the next.
FAN_IN = 8


def best_fit(lengths: np.ndarray, capacity: int) -> list[list[int]]:
    """Items by bin. Longest first, each into the fullest bin that has room for it.

    Bins are found by their room: bit r of ``open_rooms`` is set while some bin has room r.
    """
    by_room: list[list[int]] = [[] for _ in range(capacity + 1)]
    bins: list[list[int]] = []
    open_rooms = 0
    order = np.argsort(-lengths, kind="stable")
    for item, length in zip(order.tolist(), lengths[order].tolist(), strict=True):
        fitting = open_rooms >> length
        if fitting:
            room = length + (fitting & -fitting).bit_length() - 1
            at = by_room[room].pop()
            if not by_room[room]:
                open_rooms ^= 1 << room
            bins[at].append(item)
        else:
            at, room = len(bins), capacity
            bins.append([item])
        if room > length:
            by_room[room - length].append(at)
            open_rooms |= 1 << room - length
    return bins


def cut_documents(docs: DataFrame, tokenizer: str, end_id: int, capacity: int, keeps_space: bool = False, id_col: str = "doc_id", text_col: str = "text", most: int = MOST) -> DataFrame:
    """Rows ``PIECES``: encoded, ended and cut. Texts don't move; only these short rows go on."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = None
        for batch in batches:
            encoder = encoder or encoder_for(tokenizer, keeps_space, most)
            end, rows = np.array([end_id], "<u4").tobytes(), []
            for doc, packed in zip(batch.column(0).to_pylist(), encoder.encode(x.as_py() for x in batch.column(1)), strict=True):
                ids = memoryview(np.frombuffer(packed, f"<u{encoder.width}").astype("<u4").tobytes() + end)
                for k, at in enumerate(range(0, len(ids), 4 * capacity)):
                    piece = ids[at : at + 4 * capacity]
                    rows.append((doc, k, at // 4, len(piece) // 4, zlib.crc32(piece)))
            columns = zip(*rows, strict=True) if rows else [[]] * 5
            types = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(columns, types, strict=True)], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return in_arrow(docs.select(F.col(id_col).cast("long").alias("doc_id"), whole_text(text_col).alias("text")), cut, PIECES)


def _members(batch: pa.RecordBatch) -> np.ndarray:
    """A piece's row as the only member of its bin."""
    out = np.zeros(batch.num_rows, _MEMBER)
    doc = batch.column(0)
    out["doc_id"], out["null"] = doc.fill_null(0).to_numpy(zero_copy_only=False), doc.is_null().to_numpy(zero_copy_only=False)
    for name, k in (("piece", 1), ("start", 2), ("length", 3), ("crc", 4)):
        out[name] = batch.column(k).to_numpy(zero_copy_only=False)
    return out


def _merged(items: list[bytes]) -> bytes:
    """One bin's members, each item's moved behind the one before."""
    if len(items) == 1:
        return items[0]
    parts, at = [], 0
    for raw in items:
        part = np.frombuffer(raw, _MEMBER).copy()
        part["offset"] += at
        at += int(part["length"].sum(dtype=np.int64))
        parts.append(part.tobytes())
    return b"".join(parts)


def _chunks(batches: Iterable[pa.RecordBatch], first_round: bool) -> Iterator[tuple[np.ndarray, list[bytes]]]:
    """Lengths and members of up to ITEMS items at a time."""
    lengths, members = [], []
    for batch in batches:
        if first_round:
            rows = _members(batch)
            lengths.append(rows["length"].astype(np.int64))
            raw = rows.tobytes()
            members += [raw[k : k + _MEMBER.itemsize] for k in range(0, len(raw), _MEMBER.itemsize)]
        else:
            lengths.append(batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64))
            members += batch.column(1).to_pylist()
        if len(members) >= ITEMS:
            yield np.concatenate(lengths), members
            lengths, members = [], []
    if members:
        yield np.concatenate(lengths), members


def _pack(items: DataFrame, capacity: int, level: int) -> DataFrame:
    """Best fit in each task; a row of ``_BINS`` per bin, with ids that no other task or round uses."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        sequence = level << 58 | TaskContext.get().partitionId() << 36
        for lengths, members in _chunks(batches, level == 1):
            bins = best_fit(lengths, capacity)
            for at in range(0, len(bins), 10_000):
                part = bins[at : at + 10_000]
                used = [int(lengths[b].sum()) for b in part]
                yield pa.RecordBatch.from_pydict({"sequence_id": pa.array(range(sequence, sequence + len(part)), pa.int64()), "used": pa.array(used, pa.int32()), "members": pa.array([_merged([members[i] for i in b]) for b in part], pa.binary())})
                sequence += len(part)

    return stage(items.mapInArrow(pack, _BINS), f"packing-{level}")


def _placed(bins: DataFrame) -> DataFrame:
    """A row per member."""

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 5_000):
                raws = batch.column(1).slice(at, 5_000).to_pylist()
                rows = np.frombuffer(b"".join(raws), _MEMBER)
                ids = np.repeat(batch.column(0).slice(at, 5_000).to_numpy(), [len(x) // _MEMBER.itemsize for x in raws])
                doc = pa.array(rows["doc_id"], mask=rows["null"].astype(bool))
                yield pa.RecordBatch.from_arrays([doc, pa.array(rows["piece"]), pa.array(rows["start"]), pa.array(rows["length"].astype(np.int64)), pa.array(rows["crc"].astype(np.int64)), pa.array(ids), pa.array(rows["offset"].astype(np.int64))], names=["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return bins.select("sequence_id", "members").mapInArrow(place, PIECES + ", sequence_id long, offset long")


def pack_pieces(pieces: DataFrame, capacity: int, nearly_full: float = 0.995, saved: float = 0.001) -> DataFrame:
    """Pack written ``PIECES``; adds sequence_id and offset.

    ``nearly_full``: bins filled this far are emitted in the round that made them. A round over several tasks that
    saves less than the share ``saved`` of its bins ends the search.
    """
    full = pieces.filter(F.col("length") >= capacity).select("*", F.monotonically_increasing_id().alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    out, level = [full], 1
    items = pieces.filter(F.col("length") < capacity)
    tasks = max(1, items.rdd.getNumPartitions())
    least = int(capacity * nearly_full)
    before = None
    while True:
        bins = _pack(items, capacity, level)
        left = bins.filter(F.col("used") < least)
        n = left.count()
        done = tasks == 1 and n <= ITEMS or before is not None and n > before * (1 - saved) or not n
        out.append(_placed(bins if done else bins.filter(F.col("used") >= least)))
        if done:
            break
        # Those that meet are drawn by their ids' hash, anew in each round.
        tasks = max(-(-tasks // FAN_IN), -(-n // ITEMS))
        items = left.select("used", "members", "sequence_id").repartition(tasks, F.hash(F.lit(level), "sequence_id")).select("used", "members") if tasks > 1 else left.select("used", "members").coalesce(1)
        before, level = n, level + 1
    first, *rest = out
    for x in rest:
        first = first.unionByName(x)
    return first


def pack_documents(docs: DataFrame, tokenizer: str, end_id: int = 0, capacity: int = 2048, most: int = MOST) -> DataFrame:
    """Rows (doc_id, piece, start, length, ids_crc32, sequence_id, offset) for all of ``docs``."""
    return pack_pieces(stage(cut_documents(docs, tokenizer, end_id, capacity, most=most), "pieces"), capacity)
