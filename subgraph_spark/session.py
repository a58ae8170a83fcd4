"""Where materialised steps go."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The session's spark.checkpoint.dir; where that is unset, on one machine, a new folder, which is then set. A cluster must name one."""
    there = spark.conf.get("spark.checkpoint.dir", None)
    if there:
        return there
    context = spark.sparkContext
    known = context._jsc.sc().getCheckpointDir()
    if known.isDefined():
        return known.get()
    if not context.master.startswith("local") or context.master.startswith("local-cluster"):
        raise ValueError("spark.checkpoint.dir is unset, and executors of a cluster share no local folder")
    there = "file://" + tempfile.mkdtemp(prefix="shared-")
    context.setCheckpointDir(there)
    return there


#: Bytes of files up to which a written step may be broadcast. Compressed ids take a byte or two a row, and a plan takes even that times its share of the columns.
BROADCAST_FILES = 256 << 10


def bounded_broadcasts(spark: SparkSession) -> None:
    """Plans broadcast by the size of files no more than BROADCAST_FILES; joins whose sides are measured while they run keep the session's threshold."""
    now = spark._jsparkSession.sessionState().conf().autoBroadcastJoinThreshold()
    if now > BROADCAST_FILES:
        if spark.conf.get("spark.sql.adaptive.autoBroadcastJoinThreshold", None) is None:
            spark.conf.set("spark.sql.adaptive.autoBroadcastJoinThreshold", str(now))
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", str(BROADCAST_FILES))


def materialise(df: DataFrame, name: str = "step") -> DataFrame:
    """Write and read back: lineage is cut, and a lost executor loses nothing."""
    bounded_broadcasts(df.sparkSession)
    path = f"{shared_folder(df.sparkSession).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
