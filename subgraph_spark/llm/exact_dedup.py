"""Exact deduplication by a stream with keyed state, in DataFrame operations alone.

Each row's digest, id and place (file and row in it) go through a structured stream whose state, on disk in RocksDB and
never expired, holds per digest the row that stays and the group's size. The state is then read as a table. Rows whose
digest is met more than once are hits: their full normalised texts are compared, and should a digest ever stand for
several texts, its rows are grouped by the texts themselves.

Only hits move their texts. A hit's digest is looked for through a table of at most 2**20 hash values, whose size bounds
what is broadcast; the comparison combines equal texts before the shuffle, so no hot text lands in one task.

Defined cases: a null text is empty; null ids come after all others; of rows that share the smallest id, the first by file
and row stays, alone; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACES, new_folder, stage, whole_text

#: The state lies on disk; a task closes its store once its part is committed to the shared folder, so that an executor holds
#: only the stores it is working on; those share a bounded memory.
_STORES = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    "spark.sql.streaming.stateStore.unloadOnCommit": "true",
    "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage": "true",
    "spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB": "64",
    "spark.sql.streaming.stateStore.rocksdb.writeBufferSizeMB": "4",
}
#: Hash values that tell hits from other rows.
_MARKS = 1 << 20


def normalised(text_col: str | Column) -> Column:
    """Runs of white space as one space."""
    return F.regexp_replace(whole_text(text_col), SPACES, " ")


def located(docs: DataFrame) -> DataFrame:
    """``docs`` with __own_file and __own_row, the place of each row; rows that lie in no file are written first."""
    if {"__own_file", "__own_row"} <= set(docs.columns):
        return docs
    try:
        return docs.select("*", F.col("_metadata.file_path").alias("__own_file"), F.col("_metadata.row_index").alias("__own_row"))
    except AnalysisException:
        return stage(docs, "placed").select("*", F.col("_metadata.file_path").alias("__own_file"), F.col("_metadata.row_index").alias("__own_row"))


def first_of(stream: DataFrame) -> DataFrame:
    """Per digest of ``stream`` (digest, doc_id, file, row): the row that stays, and the number of rows."""
    # Structs compare field by field: an id before none, then the smaller id, then the place.
    first = F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", "file", "row")
    return stream.groupBy("digest").agg(F.min(first).alias("first"), F.count("*").alias("n"))


def keyed_state(rows_folder: str, rows: DataFrame, bytes_a_trigger: int = 16 << 30, folder: str | None = None) -> DataFrame:
    """Run the written ``rows`` through the stream, and read its state: (digest, first, n).

    ``folder`` is the stream's own (None: a new one). If it is given again, the stream goes on where it stopped: with the state
    so far, and with the files of ``rows_folder`` that are new.
    """
    spark = rows.sparkSession
    before = {k: spark.conf.get(k, None) for k in _STORES}
    folder = folder or new_folder(spark, "dedup-state")
    stream = spark.readStream.schema(rows.schema).option("maxBytesPerTrigger", str(bytes_a_trigger)).parquet(rows_folder)
    try:
        for k, v in _STORES.items():
            spark.conf.set(k, v)
        query = first_of(stream).writeStream.format("noop").outputMode("update").option("checkpointLocation", folder).trigger(availableNow=True).start()
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    query.awaitTermination()
    # The state's columns are the aggregates' buffers: a minimum and a count.
    return spark.read.format("statestore").load(folder).select(F.col("key.digest").alias("digest"), F.col("value.min").alias("first"), F.col("value.count").alias("n"))


def duplicate_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", digest=None) -> DataFrame:
    """Per row: (doc_id, file, row, sha256, keep_id, group_size, kept).

    ``digest`` makes the key of a normalised text (SHA-256 if None).
    """
    spark = docs.sparkSession
    digest = digest or (lambda text: F.unhex(F.sha2(text, 256)))
    text = normalised(text_col)
    rows = located(docs).select(F.col(id_col).cast("long").alias("doc_id"), F.col("__own_file").alias("file"), F.col("__own_row").alias("row"), text.alias("text"))
    rows = rows.select("doc_id", "file", "row", "text", digest(F.col("text")).alias("digest"), F.sha2("text", 256).alias("sha256"))
    folder = new_folder(spark, "digests")
    light = rows.select("digest", "doc_id", "file", "row", "sha256")
    light.write.option("compression", "zstd").parquet(folder)
    light = spark.read.schema(light.schema).parquet(folder)
    state = keyed_state(folder, light.select("digest", "doc_id", "file", "row"))
    hits = stage(state.filter("n > 1"), "hits")

    mark = F.pmod(F.xxhash64("digest"), F.lit(_MARKS))
    marks = F.broadcast(hits.select(mark.alias("mark")).distinct())
    texts = rows.withColumn("mark", mark).join(marks, "mark", "left_semi").join(hits.select("digest"), "digest", "left_semi").select("digest", "text", "doc_id", "file", "row")
    unlike = stage(texts.groupBy("digest").agg(F.min("text").alias("low"), F.max("text").alias("high")).filter("low <> high").select("digest"), "unlike")

    one = light.join(hits, "digest", "left")
    alike = one if unlike.isEmpty() else one.join(unlike, "digest", "left_anti")
    same = (F.col("file") == F.col("first.file")) & (F.col("row") == F.col("first.row"))
    out = alike.select("doc_id", "file", "row", "sha256", F.when(F.col("first").isNull(), F.col("doc_id")).otherwise(F.col("first.doc_id")).alias("keep_id"), F.coalesce("n", F.lit(1)).cast("long").alias("group_size"), F.coalesce(same, F.lit(True)).alias("kept"))
    if alike is one:
        return out
    apart = stage(texts.join(unlike, "digest", "left_semi"), "apart")
    groups = first_of(apart.withColumn("digest", F.struct("digest", "text"))).select("digest.*", "first", "n")
    apart = apart.join(groups, ["digest", "text"]).select("doc_id", "file", "row", F.sha2("text", 256).alias("sha256"), F.col("first.doc_id").alias("keep_id"), F.col("n").cast("long").alias("group_size"), same.alias("kept"))
    return out.unionByName(apart)
