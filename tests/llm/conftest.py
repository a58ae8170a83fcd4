import re

import pytest

WORD = r"[^\x20\x09-\x0D]+"


@pytest.fixture(scope="session")
def docs_rows(sf):
    """Rows of the smallest table, and the awkward ones: nulls, empty, long, repeated."""
    import duckdb

    rows = duckdb.sql(f"SELECT doc_id, text, lang, source, n_chars FROM '{sf}/documents.parquet' ORDER BY doc_id").fetchall()
    long = " ".join(f"word{i % 97}x{i % 13}" for i in range(40_000))
    odd = [
        (1_000_001, None, "en", "src0", 0),
        (1_000_002, "", "en", None, 0),
        (1_000_003, " \t\r\n ", None, None, 5),
        (1_000_004, long, "en", "src1", len(long)),
        (1_000_005, "Tie and tie", "en", "ünïcode", 11),
        (1_000_005, "Tie and tie", "en", "ünïcode", 11),
        (1_000_006, "Tie  and\ttie", "en", "src1", 12),
        (None, "no id here", "en", "src2", 10),
        (None, None, None, None, None),
        (1_000_007, "café 😀 naïve   <|endoftext|> it's 123,456 ٠ẞ\x1c\x1d end ", "fr", "src2", 60),
        (1_000_008, "x" * 5000, "en", "src2", 5000),
    ]
    return rows + odd


@pytest.fixture(scope="session")
def docs(spark, docs_rows, tmp_path_factory):
    """The rows as a table of several files, with columns whose names clash with what the operators make."""
    from pyspark.sql import functions as F

    path = str(tmp_path_factory.mktemp("docs") / "documents.parquet")
    df = spark.createDataFrame(docs_rows, "doc_id long, text string, lang string, source string, n_chars long").repartition(3)
    df.withColumns({k: F.lit("clash") for k in ("size", "fp", "kept", "digest", "file", "row", "line", "label", "id", "rate", "hits", "score", "start")}).write.parquet(path)
    return spark.read.parquet(path)


@pytest.fixture(scope="session")
def empty(docs):
    return docs.limit(0)


@pytest.fixture(scope="session")
def words():
    return lambda text: re.findall(WORD, text or "")
