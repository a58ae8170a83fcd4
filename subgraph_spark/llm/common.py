"""What the operators of this subpackage share: the shared folder, written stages, and plain expressions."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Internal columns start with this, so they can't meet a column of the caller's.
OWN = "__own_"

#: Space, tab, line feed, vertical tab, form feed, carriage return: the white space of the contracts.
SPACES = r"[\x20\x09-\x0D]+"


#: Rows and bytes of an Arrow batch.
ROWS, BYTES = 512, 8 << 20


def shared_folder(spark: SparkSession) -> str:
    """A folder that the driver and every executor reach: the session's spark.checkpoint.dir.

    Only where that is unset, on one machine, a folder below the temp folder is made and set; a cluster must name one.
    """
    context = spark.sparkContext
    there = spark.conf.get("spark.checkpoint.dir", None)
    if not there:
        set_dir = context._jsc.sc().getCheckpointDir()
        if set_dir.isDefined():
            return set_dir.get()
        if not context.master.startswith("local") or context.master.startswith("local-cluster"):
            raise ValueError("spark.checkpoint.dir is unset, and executors of a cluster share no local folder")
        there = "file://" + tempfile.mkdtemp(prefix="shared-")
        context.setCheckpointDir(there)
    return there


def new_folder(spark: SparkSession, name: str) -> str:
    """A path in the shared folder that no other run uses."""
    return f"{shared_folder(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"


def stage(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage ends there and lost executors lose nothing."""
    spark = df.sparkSession
    path = new_folder(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._own_folder = path
    return out


def in_arrow(df: DataFrame, work: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema) -> DataFrame:
    """``df.mapInArrow``, with few rows and bytes to a batch, as whole texts travel in them.

    The session's setting is lowered where it is larger, and stays so, since a batch is cut when the plan runs.
    """
    for key, most in (("spark.sql.execution.arrow.maxRecordsPerBatch", ROWS), ("spark.sql.execution.arrow.maxBytesPerBatch", BYTES)):
        now = df.sparkSession.conf.get(key, None)
        if now is None or not now.isdigit() or not 0 < int(now) <= most:
            df.sparkSession.conf.set(key, str(most))
    return df.mapInArrow(work, schema)


def drop(*stages: DataFrame) -> None:
    """Remove the files of stages that nothing reads any more, such as a loop's earlier rounds."""
    for df in stages:
        context = df.sparkSession.sparkContext
        target = context._jvm.org.apache.hadoop.fs.Path(df._own_folder)
        target.getFileSystem(context._jsc.hadoopConfiguration()).delete(target, True)


def whole_text(column: str | Column) -> Column:
    """The text, empty where it is null."""
    return F.coalesce(F.col(column) if isinstance(column, str) else column, F.lit(""))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_path(name: str) -> str:
    """Where a public tokenizer's file lies; OWN_TOKENIZERS names another folder than the installed package's."""
    folder = os.environ.get("OWN_TOKENIZERS")
    if folder:
        return os.path.join(folder, name)
    import public_tokenizers

    return public_tokenizers.path(name)
