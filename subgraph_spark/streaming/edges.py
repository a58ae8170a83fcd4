"""Arriving edges: windows, late rows, sessions, and new matches of a pattern per batch."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..model import PatternGraph, TargetGraph
from ..operators import engines, expand
from ..plans.search_plan import build
from ..session import shared_folder


def events_stream(spark, folder: str, schema, files_a_trigger: int = 1) -> DataFrame:
    """A file stream of events, with ``ts`` as a timestamp, which watermarks need."""
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_a_trigger).parquet(folder)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def windowed_counts(events: DataFrame, length: str, slide: str | None = None, late: str = "10 minutes", by: str = "event_type") -> DataFrame:
    """Rows per window and kind; tumbling, or sliding with ``slide``."""
    at = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.withWatermark("ts", late).groupBy(at.alias("w"), by).agg(F.count("*").alias("n")).select(F.unix_seconds("w.start").alias("start_s"), by, "n")


def sessions(events: DataFrame, gap: str, late: str = "10 minutes") -> DataFrame:
    """Rows per user session."""
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.unix_seconds("w.start").alias("start_s"), "user_id", "n")


def with_labels(events: DataFrame, labels: DataFrame) -> DataFrame:
    """Stream-static join: each event with its user's label."""
    return events.join(labels.select(F.col("vid").alias("user_id"), "vlabel"), "user_id")


def two_steps(events: DataFrame, seconds: int, late: str = "10 minutes") -> DataFrame:
    """Stream-stream join: an event and another user's of the same kind within so many seconds."""
    a = events.withWatermark("ts", late).select(F.col("user_id").alias("src"), F.col("event_type").alias("elabel"), F.col("ts").alias("at"))
    b = events.withWatermark("ts", late).select(F.col("user_id").alias("dst"), F.col("event_type").alias("kind"), F.col("ts").alias("then"))
    return a.join(b, F.expr(f"elabel = kind AND src <> dst AND then > at AND then <= at + interval {seconds} seconds")).select("src", "dst", "elabel")


def user_state(events: DataFrame) -> DataFrame:
    """Per user: rows so far and kinds of event so far, in state that a Python function keeps."""
    import pandas as pd

    def update(key, parts, state):
        n, kinds = state.get if state.exists else (0, "")
        kinds = set(filter(None, kinds.split(",")))
        for part in parts:
            n, kinds = n + len(part), kinds | set(part.event_type)
        state.update((n, ",".join(sorted(kinds))))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "kinds": [len(kinds)]})

    return events.select("user_id", "event_type").groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, kinds long", "n long, kinds string", "update", "NoTimeout")


def late_drop(spark, events: DataFrame, lateness: str = "10 minutes") -> DataFrame:
    """Play the events in two files: all but the first, then that first one, long after the watermark has passed it.

    Returns one row, ``kept``: the rows that windows counted.
    """
    from ..session import shared_folder

    folder = f"{shared_folder(spark).rstrip('/')}/late-{uuid.uuid4().hex}"
    first = F.min(F.struct("ts", "event_id"))
    oldest = events.agg(first.alias("f")).select("f.ts", "f.event_id")
    late = events.join(oldest, ["ts", "event_id"], "left_semi")
    events.join(oldest, ["ts", "event_id"], "left_anti").coalesce(1).write.parquet(f"{folder}/in", mode="append")
    stream = events_stream(spark, f"{folder}/in", events.schema)
    counts = stream.withWatermark("ts", lateness).groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n")).select("w.start", "n")

    def play() -> None:
        counts.writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/ck").outputMode("append").trigger(availableNow=True).start().awaitTermination()

    play()
    late.coalesce(1).write.parquet(f"{folder}/in", mode="append")
    # Two rows beyond all others push the watermark on, so that every window before is handed out.
    for days in (30, 60):
        events.agg((F.max(F.col("ts").cast("timestamp")) + F.expr(f"interval {days} days")).alias("ts")).select(*[F.col("ts").cast(x.dataType).alias("ts") if x.name == "ts" else F.lit(None).cast(x.dataType).alias(x.name) for x in events.schema]).coalesce(1).write.parquet(f"{folder}/in", mode="append")
        play()
    last = events.agg(F.max(F.col("ts").cast("timestamp")).alias("last"))
    return spark.read.parquet(f"{folder}/out").crossJoin(last).filter("start <= last").agg(F.sum("n").alias("kept"))


def delta_matches(vertices: DataFrame, old: DataFrame, new: DataFrame, pattern: PatternGraph) -> DataFrame:
    """Matches that need a new edge, each once: for pattern edge i, edges before it are old ones, it is new, and those after it are any.

    ``old`` and ``new`` (src, dst, elabel) have no edge in common. Columns are m0, m1, ...
    """
    every, out = old.unionByName(new), None
    for i, _ in enumerate(pattern.edges):
        # Join the new edge first, then along the constraint-first order from its ends.
        done: dict[int, str] = {}
        rows = None
        for k in [i, *_connected(pattern, i)]:
            s, d, label = pattern.edges[k]
            edges = (new if k == i else old if k < i else every).select(F.col("src").alias("s"), F.col("dst").alias("d"), "elabel")
            edges = (edges if label is None else edges.filter(F.col("elabel") == label)).select("s", "d").distinct()
            if s == d:
                edges = edges.filter("s = d")
            if rows is None:
                rows = edges.select(F.col("s").alias(f"m{s}"), *([] if s == d else [F.col("d").alias(f"m{d}")]))
            else:
                named = edges.select(F.col("s").alias(f"m{s}"), *([] if s == d else [F.col("d").alias(f"m{d}")]))
                rows = rows.join(named, [x for x in named.columns if x in rows.columns]) if set(named.columns) & set(rows.columns) else rows.crossJoin(named)
            for v in {s, d} - done.keys():
                for u in done:
                    if f"m{u}" in rows.columns:
                        rows = rows.filter(F.col(f"m{u}") != F.col(f"m{v}"))
                done[v] = f"m{v}"
        for v, label in enumerate(pattern.labels):
            if label is not None:
                rows = rows.join(vertices.filter(F.col("vlabel") == label).select(F.col("vid").alias(f"m{v}")), f"m{v}", "left_semi")
        rows = rows.select(*[f"m{v}" for v in range(pattern.size)])
        out = rows if out is None else out.unionByName(rows)
    return out


def _connected(pattern: PatternGraph, first: int) -> list[int]:
    """The other edges, each touching those before it where it can."""
    seen, left, out = set(pattern.edges[first][:2]), [k for k in range(len(pattern.edges)) if k != first], []
    while left:
        k = next((k for k in left if set(pattern.edges[k][:2]) & seen), left[0])
        left.remove(k)
        out.append(k)
        seen |= set(pattern.edges[k][:2])
    return out


def delta_stream(edges: DataFrame, vertices: DataFrame, pattern: PatternGraph, store: str, out: str, checkpoint: str):
    """A query that appends each batch's new matches to ``out`` and its new edges to ``store`` (Parquet folders by batch).

    A batch that is run again overwrites its own folders and sees only the batches before it.
    """

    def batch(rows: DataFrame, n: int) -> None:
        spark = rows.sparkSession
        rows = rows.select("src", "dst", "elabel").distinct()
        old = spark.createDataFrame([], rows.schema)
        if n:
            old = spark.read.schema("src long, dst long, elabel string, batch long").parquet(store).filter(F.col("batch") < n).drop("batch")
        new = rows.join(old, ["src", "dst"], "left_anti").groupBy("src", "dst").agg(F.min("elabel").alias("elabel"))
        new.write.mode("overwrite").parquet(f"{store}/batch={n}")
        new = spark.read.schema(rows.schema).parquet(f"{store}/batch={n}")
        delta_matches(vertices, old, new, pattern).write.mode("overwrite").parquet(f"{out}/batch={n}")

    return edges.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def drained(stream: DataFrame, name: str, mode: str = "complete", after: Callable | None = None, folder: str | None = None) -> DataFrame:
    """Run a stream over what there is, into Parquet in the shared folder, a folder per batch that a repeated batch overwrites.

    In complete mode the last batch is the result, else all are. A stream that is given its ``folder`` again goes on where it stopped.
    """
    folder = folder or f"{shared_folder(stream.sparkSession).rstrip('/')}/{name}-{uuid.uuid4().hex}"

    def keep(rows: DataFrame, n: int) -> None:
        rows.write.mode("overwrite").parquet(f"{folder}/rows/batch={n}")

    query = stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start()
    query.awaitTermination()
    if after:
        after(query)
    spark = stream.sparkSession
    rows = T.StructType([*stream.schema.fields, T.StructField("batch", T.LongType())])
    try:
        found = spark.read.schema(rows).parquet(f"{folder}/rows")
    except AnalysisException:  # no batch had come
        return spark.createDataFrame([], stream.schema)
    if mode == "complete":
        found = found.filter(F.col("batch") == found.agg(F.max("batch")).first()[0])
    return found.drop("batch")


def restarted(events: DataFrame) -> DataFrame:
    """Counts by event_type of a stream over two halves of ``events`` (event_id, event_type): it is stopped after the first, and goes on with its state."""
    spark = events.sparkSession
    folder = f"{shared_folder(spark).rstrip('/')}/restarted-{uuid.uuid4().hex}"
    out = None
    for half in (0, 1):
        events.filter(F.pmod("event_id", F.lit(2)) == half).write.mode("append").parquet(f"{folder}/in")
        stream = spark.readStream.schema(events.schema).parquet(f"{folder}/in").groupBy("event_type").agg(F.count("*").alias("n"))
        out = drained(stream, "counts", "complete", folder=f"{folder}/out")
    return out


__all__ = ["TargetGraph", "build", "delta_matches", "delta_stream", "drained", "engines", "events_stream", "expand", "restarted", "sessions", "two_steps", "windowed_counts", "with_labels"]
