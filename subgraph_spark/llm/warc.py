"""Web archives: one gzip member per record, written by tasks, and read back by byte ranges.

Writing. Of records with equal payloads (equal SHA-1, at least ``least_bytes`` long) the one with the smallest
page id becomes a ``response``; the others become ``revisit`` records that name it and carry no payload.

Reading. A file is divided into byte ranges of any size. A task looks for gzip's magic number in its range, takes a
place for a record's start only if inflating there gives a WARC version line and a whole header, and from the first
such place walks from member to member. It owns the records that start inside its range, and reads past the end of
the range to finish the last one. So each record is read exactly once, however the ranges are cut.

Defined cases: a null payload is empty, and equal to other empty ones; null ids sort last and come back as null; of
rows that repeat an id and its payload all are responses if that id is the smallest; an empty table gives no archive
and no rows; other columns are ignored. A payload that itself is a stored, uncompressed run of WARC members can look
like records if a range begins inside it: such files must be read with one range per file (``split_bytes=None``).
A header may be of any length. A member that is damaged or cut off ends the reading with an error that names its place, unless
``skip_damaged``: then its range is read on from the next record's start.
"""

from __future__ import annotations

import base64
import hashlib
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import OWN, in_arrow, new_folder, stage, whole_text
from .storage import new_file, old_file

_MAGIC = b"\x1f\x8b\x08"
_VERSION = b"WARC/1."
_HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
_EPOCH = "2020-01-01T00:00:00Z"
_READ = 1 << 20
#: Rows are handed on when so many bytes have gathered.
_HAND_ON = 8 << 20
#: Ranges beyond this number share tasks.
_MOST_TASKS = 20_000

ARCHIVES = "path string, bytes long, records long"
RECORDS = "record_id string, record_type string, target_uri string, refers_to string, payload_digest string, payload_bytes long, payload binary, path string, offset long"


def base32_sha1(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def _record_id(page_id, digest: str) -> str:
    return f"urn:x-page:{'null' if page_id is None else page_id}:{digest}"


def _page_of(record_id: str | None) -> int | None:
    if record_id is None:
        return None
    page = record_id.split(":")[2]
    return None if page == "null" else int(page)


def record(page_id, url: str | None, payload: bytes, digest: str, first_id, revisit: bool) -> bytes:
    """One gzip member."""
    head = [
        "WARC/1.1",
        f"WARC-Type: {'revisit' if revisit else 'response'}",
        f"WARC-Record-ID: <{_record_id(page_id, digest)}>",
        f"WARC-Date: {_EPOCH}",
        f"WARC-Payload-Digest: sha1:{digest}",
        f"X-Payload-Length: {len(payload)}",
        "Content-Type: application/http; msgtype=response",
    ]
    if url is not None:
        head.insert(4, "WARC-Target-URI: " + "".join(x for x in url if x.isprintable()).strip())
    if revisit:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <{_record_id(first_id, digest)}>"]
    block = _HTTP if revisit else _HTTP + payload
    head.append(f"Content-Length: {len(block)}")
    deflate = zlib.compressobj(6, zlib.DEFLATED, 31)
    return deflate.compress("\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n") + deflate.flush()


def _revisits(pages: DataFrame, id_col: str, payload_col: str, least_bytes: int) -> DataFrame:
    """Rows (id, digest, first id) of the records that repeat an earlier payload. Only ids and digests are shuffled."""
    payload = whole_text(payload_col)
    light = pages.filter(F.octet_length(payload) >= least_bytes).select(F.col(id_col).alias("id"), F.unhex(F.sha1(payload)).alias("digest"))
    light = stage(light, "warc-digests")
    first = light.groupBy("digest").agg(F.min("id").alias("first_id"), F.count("*").alias("n")).filter("n > 1").drop("n")
    repeated = light.join(first, "digest").filter(~F.col("id").eqNullSafe(F.col("first_id")))
    return stage(repeated.select("id", "digest", "first_id").distinct(), "warc-revisits")


def write_archives(pages: DataFrame, folder: str, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", least_bytes: int = 0) -> DataFrame:
    """Write ``pages`` as archives under ``folder``; returns the list of archives (``ARCHIVES``).

    The payloads meet the few repeated ids by a join on id and digest, which no hot payload makes uneven.
    """
    repeats = _revisits(pages, id_col, payload_col, least_bytes).select(F.col("id").alias(f"{OWN}id"), F.col("digest").alias(f"{OWN}digest"), F.col("first_id").alias(f"{OWN}first"), F.lit(True).alias(f"{OWN}again"))
    payload = whole_text(payload_col)
    rows = pages.select(F.col(id_col).alias("id"), F.col(url_col).cast("string").alias("url"), payload.cast("binary").alias("payload"), F.unhex(F.sha1(payload)).alias("digest"))
    rows = rows.join(repeats, F.col("id").eqNullSafe(F.col(f"{OWN}id")) & (F.col("digest") == F.col(f"{OWN}digest")), "left")
    rows = rows.select("id", "url", "payload", "digest", F.col(f"{OWN}first").alias("first_id"), F.coalesce(f"{OWN}again", F.lit(False)).alias("again"))

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        size = count = 0
        rows = (x for b in batches for x in zip(*(b.column(i) for i in range(6)), strict=True))
        if (one := next(rows, None)) is None:
            return
        with new_file(folder, f"part-{TaskContext.get().partitionId():06d}", ".warc.gz") as (path, out):
            while one is not None:
                page, url, payload, digest, first, again = (x.as_py() for x in one)
                size += out.write(made := record(page, url, payload, base64.b32encode(digest).decode(), first, again)) or len(made)
                count += 1
                one = next(rows, None)
        yield pa.RecordBatch.from_pydict({"path": [path], "bytes": [size], "records": [count]})

    return stage(in_arrow(rows, write, ARCHIVES), "warc-archives")


class _Bytes:
    """Reads a file forwards, in blocks, from a place on."""

    def __init__(self, file, at: int):
        self.file, self.at = file, at
        file.seek(at)

    def more(self) -> bytes:
        got = self.file.read(_READ)
        self.at += len(got)
        return got


def _parse(raw: bytes) -> tuple[dict[str, str], bytes] | None:
    """Header fields by lower-case name, and the block; None if ``raw`` isn't a WARC record."""
    if not raw.startswith(_VERSION):
        return None
    head, found, block = raw.partition(b"\r\n\r\n")
    if not found:
        return None
    fields = {}
    for line in head.split(b"\r\n")[1:]:
        name, colon, value = line.partition(b":")
        if not colon:
            return None
        fields[name.strip().lower().decode("latin-1")] = value.strip().decode("utf-8", "replace")
    if not fields.get("content-length", "").isdigit():
        return None
    return fields, block


def _header_begins(file, at: int) -> bool:
    """Does inflating from ``at`` give a version line and a whole header?"""
    inflate, out, source = zlib.decompressobj(31), bytearray(), _Bytes(file, at)
    try:
        while not inflate.eof and (got := source.file.read(4096)):
            seen = max(0, len(out) - 3)
            out += inflate.decompress(got)
            if not out.startswith(_VERSION[: len(out)]):
                return False
            if out.find(b"\r\n\r\n", seen) >= 0:
                return _parse(bytes(out)) is not None
    except zlib.error:
        return False
    return False


def _first_start(file, begin: int, end: int) -> int | None:
    """The first place of [begin, end) at which a record starts."""
    source, held, base = _Bytes(file, begin), b"", begin
    while base < end:
        got = source.more()
        held += got
        at = held.find(_MAGIC)
        while 0 <= at and base + at < end:
            if _header_begins(file, base + at):
                return base + at
            at = held.find(_MAGIC, at + 1)
        if not got:
            return None
        file.seek(source.at)
        base, held = base + max(0, len(held) - 2), held[-2:]
    return None


def members(file, begin: int, end: int, skip_damaged: bool = False) -> Iterator[tuple[int, bytes]]:
    """Offsets and inflated bytes of the gzip members that start in [begin, end)."""
    at = _first_start(file, begin, end)
    while at is not None and at < end:
        source, held = _Bytes(file, at), b""
        try:
            while at < end:
                inflate, out, used = zlib.decompressobj(31), [], 0
                while not inflate.eof:
                    if not held:
                        held = source.more()
                        if not held:
                            if used:
                                raise zlib.error("it is cut off")
                            return
                    used += len(held)
                    out.append(inflate.decompress(held))
                    held = inflate.unused_data if inflate.eof else b""
                used -= len(held)
                yield at, b"".join(out)
                at += used
            return
        except zlib.error as e:
            if not skip_damaged:
                raise ValueError(f"the record at {at} can't be read: {e}") from e
            at = _first_start(file, at + 1, end)


def read_range(path: str, begin: int, end: int, skip_damaged: bool = False) -> Iterator[dict]:
    """The records (``RECORDS``) that start in a byte range."""
    with old_file(path) as file:
        for offset, raw in members(file, begin, end, skip_damaged):
            parsed = _parse(raw)
            if parsed is None:
                raise ValueError(f"{path} has no WARC record at {offset}")
            fields, block = parsed
            block = block[: int(fields["content-length"])]
            kind, digest = fields.get("warc-type"), fields.get("warc-payload-digest", "").removeprefix("sha1:") or None
            payload = block.partition(b"\r\n\r\n")[2] if "application/http" in fields.get("content-type", "") else block
            length = len(payload)
            if kind == "revisit":
                payload, length = None, int(fields["x-payload-length"]) if "x-payload-length" in fields else None
            elif digest is not None and base32_sha1(payload) != digest:
                raise ValueError(f"{path}: the payload at {offset} doesn't have its digest")
            yield {"record_id": fields.get("warc-record-id", "").strip("<>"), "record_type": kind, "target_uri": fields.get("warc-target-uri"), "refers_to": fields["warc-refers-to"].strip("<>") if "warc-refers-to" in fields else None, "payload_digest": digest, "payload_bytes": length, "payload": payload, "path": path, "offset": offset}


def byte_ranges(archives: DataFrame, split_bytes: int | None) -> DataFrame:
    """A row (path, begin, end) per range, dealt over as many tasks; ``split_bytes`` None: a range per file."""
    cut = F.lit(1 << 62) if split_bytes is None else F.lit(split_bytes)
    begins = F.sequence(F.lit(0).cast("long"), F.greatest(F.col("bytes") - 1, F.lit(0).cast("long")), cut.cast("long"))
    ranges = archives.select("path", "bytes", F.explode(begins).alias("begin")).select("path", "begin", F.least(F.col("begin") + cut, "bytes").cast("long").alias("end"))
    count = archives.count() if split_bytes is None else archives.agg(F.sum(F.ceil(F.col("bytes") / split_bytes))).first()[0] or 1
    return ranges.repartition(min(max(int(count), 1), _MOST_TASKS))


def read_archives(archives: DataFrame, split_bytes: int | None = 32 << 20, columns: list[str] | None = None, skip_damaged: bool = False) -> DataFrame:
    """All records of ``archives`` (path, bytes), as ``RECORDS`` or those ``columns`` of it."""
    schema = [x.strip().split(" ") for x in RECORDS.split(",")]
    kept = [(k, t) for k, t in schema if columns is None or k in columns]
    types = {"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, size = [], 0
        made = lambda: pa.RecordBatch.from_pydict({k: pa.array([x[k] for x in rows], types[t]) for k, t in kept})
        for batch in batches:
            for where in batch.to_pylist():
                for one in read_range(where["path"], where["begin"], where["end"], skip_damaged):
                    rows.append({k: one[k] for k, _ in kept})
                    size += 200 + (len(one["payload"] or b"") if columns is None or "payload" in columns else 0)
                    if size >= _HAND_ON:
                        yield made()
                        rows, size = [], 0
        if rows:
            yield made()

    return byte_ranges(archives.select("path", "bytes"), split_bytes).mapInArrow(read, ", ".join(f"`{k}` {t}" for k, t in kept))


def page_of(column: str):
    """The page id inside a record id of ours."""
    part = F.split_part(F.col(column), F.lit(":"), F.lit(3))
    return F.when(part != "null", part.cast("long"))


def archive_round_trip(spark: SparkSession, pages: DataFrame, split_bytes: int = 8 << 20, least_bytes: int = 0) -> DataFrame:
    """Write ``pages``, read the archives back, and tell of each record what the archive says."""
    archives = write_archives(pages, new_folder(spark, "warc"), least_bytes=least_bytes)
    records = read_archives(archives, split_bytes, ["record_id", "record_type", "refers_to", "payload_digest", "payload_bytes"])
    return records.select(page_of("record_id").alias("page_id"), "payload_bytes", "payload_digest", "record_type", page_of("refers_to").alias("refers_to"))
