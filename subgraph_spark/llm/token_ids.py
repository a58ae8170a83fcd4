"""Token-id files: one concatenated id array per shard, with Elias-Fano coded document boundaries behind it.

A shard is
    ids      n_tokens unsigned little-endian integers of ``width`` bytes, documents one after another
    ends     Elias-Fano code of each document's end (ids up to there), non-decreasing
    docs     Elias-Fano code of the document ids less the first, for the documents whose id isn't null
    footer   32 bytes: the magic word, width, and the lengths of ends and docs; null ids' number
Documents lie in ascending order of their id, in the shard and from shard to shard. The boundaries take about
2 + log2(tokens a document) bits each, where a table of offsets takes 64, and any of them is found by one select.

Defined cases: a null text is empty (the end id alone); null ids come first; documents that share an id follow each
other, by their texts' hashes; an empty table gives no shard; other columns are ignored.
"""

from __future__ import annotations

import struct
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import in_arrow, new_folder, stage, whole_text
from .encoding import encoder_for
from .storage import new_file, old_file

_WORD = b"IDS+EF01"
_FOOTER = "<8sQQQ"
_HEAD = "<QQQ"
#: Ids that are read at a time, about.
_READ = 1 << 20
#: A select sample per so many set bits.
_SAMPLE = 512

SHARDS = "shard int, path string, width int, n_docs long, n_tokens long, ends_bytes long, docs_bytes long, n_null long"


class EliasFano:
    """A non-decreasing sequence of non-negative integers, with constant-time select.

    The low bits of every value lie packed in one array; the high parts are set bits of a bit vector, value i at
    place high(i) + i. ``samples`` has the place of every 512th set bit: select(i) counts on from there.
    """

    def __init__(self, n: int, last: int, low: np.ndarray, high: np.ndarray, samples: np.ndarray):
        self.n, self.last, self.low, self.high, self.samples = n, last, low, high, samples
        self.shift = self._shift(n, last)

    @staticmethod
    def _shift(n: int, last: int) -> int:
        return max(0, ((last + 1) // max(n, 1)).bit_length() - 1)

    @classmethod
    def build(cls, values: np.ndarray) -> EliasFano:
        values = np.asarray(values, np.uint64)
        n = len(values)
        if n and (values[1:] < values[:-1]).any():
            raise ValueError("the sequence decreases")
        last = int(values[-1]) if n else 0
        shift = cls._shift(n, last)
        bits = ((values[:, None] >> np.arange(shift, dtype=np.uint64)) & np.uint64(1)).astype(np.uint8).ravel()
        places = (values >> np.uint64(shift)).astype(np.int64) + np.arange(n)
        upper = np.zeros(((last >> shift) + n + 64) // 64 * 64, np.uint8)
        upper[places] = 1
        return cls(n, last, np.packbits(bits, bitorder="little"), np.packbits(upper, bitorder="little"), places[::_SAMPLE].astype(np.uint64))

    def tobytes(self) -> bytes:
        return struct.pack(_HEAD, self.n, self.last, len(self.high)) + self.high.tobytes() + self.low.tobytes() + self.samples.tobytes()

    @classmethod
    def frombytes(cls, raw: bytes) -> EliasFano:
        n, last, high = struct.unpack_from(_HEAD, raw)
        low = (n * cls._shift(n, last) + 7) // 8
        data = np.frombuffer(raw, np.uint8, offset=struct.calcsize(_HEAD))
        return cls(n, last, data[high : high + low], data[:high], np.frombuffer(raw[struct.calcsize(_HEAD) + high + low :], np.uint64))

    def _low(self, i: int) -> int:
        at = i * self.shift
        window = int.from_bytes(self.low[at // 8 : (at + self.shift + 7) // 8].tobytes(), "little")
        return window >> at % 8 & (1 << self.shift) - 1

    def select(self, i: int) -> int:
        """The i-th value, from 0, without decoding the others."""
        if not 0 <= i < self.n:
            raise IndexError(i)
        place, left = int(self.samples[i // _SAMPLE]), i % _SAMPLE
        at = place // 8
        first = int(self.high[at]) >> place % 8 << place % 8
        step = 256
        while True:
            block = self.high[at : at + step].copy()
            block[0] = first
            counts = np.cumsum(np.bitwise_count(block), dtype=np.int64)
            if counts[-1] > left:
                k = int(np.searchsorted(counts, left, "right"))
                left -= int(counts[k - 1]) if k else 0
                byte = int(block[k])
                for _ in range(left):
                    byte &= byte - 1
                return ((at + k) * 8 + (byte & -byte).bit_length() - 1 - i) << self.shift | self._low(i)
            left -= int(counts[-1])
            at += step
            first = int(self.high[at])

    def values(self, first: int = 0, to: int | None = None) -> np.ndarray:
        """The values from ``first`` up to ``to``, decoded together."""
        to = self.n if to is None else to
        if first >= to:
            return np.zeros(0, np.int64)
        low, high = first // _SAMPLE, (to - 1) // _SAMPLE + 1
        begin = int(self.samples[low])
        end = int(self.samples[high]) if high < len(self.samples) else 8 * len(self.high)
        places = np.flatnonzero(np.unpackbits(self.high[begin // 8 : (end + 7) // 8], bitorder="little")) + begin // 8 * 8
        places = places[places >= begin][first - low * _SAMPLE : to - low * _SAMPLE]
        at = first * self.shift
        bits = np.unpackbits(self.low[at // 8 : (to * self.shift + 7) // 8], bitorder="little")[at % 8 :][: (to - first) * self.shift]
        bits = bits.reshape(to - first, self.shift).astype(np.int64)
        return ((places - np.arange(first, to)).astype(np.int64) << self.shift) + (bits << np.arange(self.shift)).sum(1, dtype=np.int64)


def write_shards(docs: DataFrame, folder: str, tokenizer: str, end_id: int, keeps_space: bool = True, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Encode whole texts and write shards under ``folder``; returns ``SHARDS`` with each shard's first id's place, ``base``.

    Texts are dealt by ranges of (id, hash of the text), so neither a hot id nor long texts meet in one task beyond
    what shares both; a task writes ids as they come and holds two integers per document.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("id"), whole_text(text_col).alias("text")).withColumn("h", F.xxhash64("text"))
    rows = rows.repartitionByRange("id", "h").sortWithinPartitions(F.asc_nulls_first("id"), "h", "text").select("id", "text")

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encoder, end = encoder_for(tokenizer, keeps_space), None
        ends, ids, nulls, total = array("Q"), array("q"), 0, 0
        batches = (b for b in batches if b.num_rows)
        batch = next(batches, None)
        if batch is None:
            return
        shard = TaskContext.get().partitionId()
        end = end_id.to_bytes(encoder.width, "little")
        with new_file(folder, f"shard-{shard:06d}", ".ids") as (path, out):
            while batch is not None:
                for doc in batch.column(0).to_pylist():
                    if doc is None:
                        nulls += 1
                    else:
                        ids.append(doc)
                for packed in encoder.encode(x.as_py() for x in batch.column(1)):
                    out.write(packed)
                    out.write(end)
                    total += len(packed) // encoder.width + 1
                    ends.append(total)
                batch = next(batches, None)
            base = ids[0] if ids else 0
            index = EliasFano.build(np.frombuffer(ends, np.uint64)).tobytes()
            names = struct.pack("<q", base) + EliasFano.build((np.frombuffer(ids, np.int64) - base).astype(np.uint64)).tobytes()
            out.write(index)
            out.write(names)
            out.write(struct.pack(_FOOTER, _WORD, encoder.width, len(index), len(names)))
        yield pa.RecordBatch.from_pydict({"shard": pa.array([shard], pa.int32()), "path": [path], "width": pa.array([encoder.width], pa.int32()), "n_docs": [len(ends)], "n_tokens": [total], "ends_bytes": [len(index)], "docs_bytes": [len(names)], "n_null": [nulls]})

    shards = stage(in_arrow(rows, write, SHARDS), "token-shards")
    # A row per file: the only running sum over all data is over these.
    before = F.coalesce(F.sum("n_tokens").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return shards.withColumn("base", before.cast("long"))


class Shard:
    """Random access to a shard's documents."""

    def __init__(self, file, path: str = ""):
        self.file, size = file, file.size()
        file.seek(size - struct.calcsize(_FOOTER))
        word, self.width, ends, docs = struct.unpack(_FOOTER, file.read(struct.calcsize(_FOOTER)))
        if word != _WORD:
            raise ValueError(f"{path} is no token-id file")
        file.seek(size - struct.calcsize(_FOOTER) - ends - docs)
        self.ends = EliasFano.frombytes(file.read(ends))
        names = file.read(docs)
        self._first, self._docs = struct.unpack_from("<q", names)[0], EliasFano.frombytes(names[8:])
        self._nulls = self.ends.n - self._docs.n

    def __len__(self) -> int:
        return self.ends.n

    def doc_id(self, i: int) -> int | None:
        return None if i < self._nulls else self._first + self._docs.select(i - self._nulls)

    def start(self, i: int) -> int:
        return self.ends.select(i - 1) if i else 0

    def doc_ids(self, first: int, to: int) -> list[int | None]:
        named = self._docs.values(max(first, self._nulls) - self._nulls, max(to, self._nulls) - self._nulls) + self._first
        return [None] * (min(to, self._nulls) - min(first, self._nulls)) + named.tolist()

    def starts(self, first: int, to: int) -> np.ndarray:
        """Starts of the documents from ``first`` on, and the end of the last before ``to``."""
        return np.concatenate([[self.start(first)], self.ends.values(first, to)])

    def ids(self, i: int, to: int | None = None) -> np.ndarray:
        """The ids of document i, or of those from i up to ``to``."""
        start, end = self.start(i), self.ends.select((i + 1 if to is None else to) - 1)
        self.file.seek(start * self.width)
        return np.frombuffer(self.file.read((end - start) * self.width), f"<u{self.width}")


DOCUMENTS = "doc_id long, start long, n_tokens long, ids_crc32 long"


def read_documents(shards: DataFrame, docs_a_task: int = 10_000) -> DataFrame:
    """Per document of ``shards``: its id, place, length and the checksum of its ids, read from the files."""
    first = F.explode(F.sequence(F.lit(0).cast("long"), F.col("n_docs") - 1, F.lit(docs_a_task).cast("long")))
    parts = shards.select("path", "base", "n_docs", first.alias("first")).select("path", "base", "first", F.least(F.col("first") + docs_a_task, "n_docs").alias("to"))

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in batch.to_pylist():
                with old_file(part["path"]) as file:
                    shard = Shard(file, part["path"])
                    first, to = part["first"], part["to"]
                    starts, sums = shard.starts(first, to), []
                    while first < to:  # documents of about _READ ids at a time
                        own = starts[first - part["first"] :]
                        last = min(to, first + max(1, int(np.searchsorted(own, own[0] + _READ, "right")) - 1))
                        ids = memoryview(shard.ids(first, last).astype("<u4").tobytes())
                        cuts = 4 * (own[: last - first + 1] - own[0])
                        sums += [zlib.crc32(ids[a:b]) for a, b in zip(cuts.tolist(), cuts[1:].tolist(), strict=False)]
                        first = last
                    yield pa.RecordBatch.from_pydict({"doc_id": pa.array(shard.doc_ids(part["first"], to), pa.int64()), "start": starts[:-1] + part["base"], "n_tokens": np.diff(starts), "ids_crc32": pa.array(sums, pa.int64())})

    count = shards.agg(F.sum(F.ceil(F.col("n_docs") / docs_a_task))).first()[0] or 1
    return parts.repartition(min(int(count), 20_000)).mapInArrow(read, DOCUMENTS)


def token_round_trip(spark: SparkSession, docs: DataFrame, tokenizer: str, end_id: int = 2) -> DataFrame:
    """Write the shards, then read each document back from them."""
    return read_documents(write_shards(docs, new_folder(spark, "token-ids"), tokenizer, end_id))
