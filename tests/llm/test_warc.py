"""Archives: round trips under every cut, hard payloads, repeated pages."""

import pytest

from subgraph_spark.llm import warc
from subgraph_spark.llm.common import new_folder


def pages_df(spark, rows, tmp_path):
    path = str(tmp_path / "pages.parquet")
    spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "'x' AS id", "'y' AS digest", "'z' AS payload").repartition(3).write.parquet(path)
    return spark.read.parquet(path)


ROWS = [(5, "http://a.example/", "<p>one</p>"), (3, "http://b.example/\r\nX: y", "<p>one</p>"), (9, None, "<p>one</p>"), (1, "u", None), (2, "u", ""), (7, "u", "\r\n\r\nWARC/1.1\r\n" * 50), (8, "u", "é" * 200_000), (None, "u", "no id"), (4, "u", "twice"), (4, "u", "twice"), (None, "u", "<p>one</p>")]


def expected(rows):
    first = {}
    for i, _, h in rows:
        k = h or ""
        if i is not None:
            first[k] = min(first.get(k, i), i)
    out = []
    for i, _, h in rows:
        b = (h or "").encode()
        f = first.get(h or "")
        again = f is not None and i != f
        out.append((i, len(b), warc.base32_sha1(b), "revisit" if again else "response", f if again else None))
    return sorted(out, key=repr)


@pytest.mark.parametrize("split", [37, 1000, 1 << 20, None])
def test_round_trip(spark, tmp_path, split):
    got = warc.archive_round_trip(spark, pages_df(spark, ROWS, tmp_path), split)
    assert sorted(map(tuple, got.collect()), key=repr) == expected(ROWS)


def test_real_pages_and_payloads(spark, sf):
    pages = spark.read.parquet(f"{sf}/pages.parquet")
    archives = warc.write_archives(pages, new_folder(spark, "warc"))
    got = {r.record_id: r for r in warc.read_archives(archives, 5000).collect()}
    for r in pages.collect():
        digest = warc.base32_sha1(r.html.encode())
        one = got.pop(f"urn:x-page:{r.page_id}:{digest}")
        assert one.record_type == "response" and one.payload == r.html.encode() and one.target_uri == r.url
    assert not got


def test_least_bytes(spark, tmp_path):
    got = warc.archive_round_trip(spark, pages_df(spark, [(1, "u", "aa"), (2, "u", "aa"), (3, "u", "a" * 50), (4, "u", "a" * 50)], tmp_path), least_bytes=10)
    assert {r.page_id: r.record_type for r in got.collect()} == {1: "response", 2: "response", 3: "response", 4: "revisit"}


def test_empty_table(spark, tmp_path):
    assert warc.archive_round_trip(spark, spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_every_record_has_one_owner(tmp_path):
    raws = [warc.record(i, "u", bytes([31, 139, 8]) * i, warc.base32_sha1(bytes([31, 139, 8]) * i), None, False) for i in range(12)]
    data = b"".join(raws)
    (tmp_path / "a").write_bytes(data)
    for cut in (1, 2, 3, 50, 333, len(data)):
        found = [x["offset"] for a in range(0, len(data), cut) for x in warc.read_range(str(tmp_path / "a"), a, min(a + cut, len(data)))]
        assert found == [sum(map(len, raws[:k])) for k in range(12)]


def test_cut_off_archive(tmp_path):
    raw = warc.record(1, "u", b"x" * 5000, warc.base32_sha1(b"x" * 5000), None, False)
    (tmp_path / "a").write_bytes(raw[:-10])
    with pytest.raises(ValueError):
        list(warc.read_range(str(tmp_path / "a"), 0, len(raw)))


@pytest.mark.parametrize("place", [0, 1, 2])
def test_long_headers(spark, tmp_path, place):
    """A URL of 300,000 characters that hardly compress, in the first, a middle and the last record, under cuts of any size."""
    import random

    long = "http://x.example/" + "".join(random.Random(place).choices("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789-_", k=300_000))
    urls = [long if i == place else "u" for i in range(3)]
    raws = [warc.record(i, url, b"payload %d" % i, warc.base32_sha1(b"payload %d" % i), None, False) for i, url in enumerate(urls)]
    data = b"".join(raws)
    (tmp_path / "a").write_bytes(data)
    for cut in (101, 5000, 70_000, len(data)):
        found = [x["target_uri"] for a in range(0, len(data), cut) for x in warc.read_range(str(tmp_path / "a"), a, min(a + cut, len(data)))]
        assert found == urls
    rows = [(i, url, f"payload {i}") for i, url in enumerate(urls)]
    got = warc.archive_round_trip(spark, pages_df(spark, rows, tmp_path), 1000)
    assert sorted(map(tuple, got.collect()), key=repr) == expected(rows)


def test_damaged_records(tmp_path):
    """A damaged member is an error that names its place, or is left out with ``skip_damaged``."""
    raws = [bytearray(warc.record(i, "u", bytes(range(256)) * 20, warc.base32_sha1(bytes(range(256)) * 20), None, False)) for i in range(4)]
    raws[1][len(raws[1]) // 2] ^= 0xFF
    data = b"".join(raws)
    (tmp_path / "a").write_bytes(data)
    with pytest.raises(ValueError, match=str(len(raws[0]))):
        list(warc.read_range(str(tmp_path / "a"), 0, len(data)))
    kept = [x["record_id"].split(":")[2] for x in warc.read_range(str(tmp_path / "a"), 0, len(data), True)]
    assert kept == ["0", "2", "3"]
