"""Edge lists and match tables in the usual formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import EDGES, VERTICES, TargetGraph


def read_edge_list(spark: SparkSession, path: str, fmt: str = "text", target_from_file: bool = False) -> DataFrame:
    """(src, dst, elabel) from parquet, orc, csv, json or text (``src dst [label]``, # for comments).

    ``target_from_file`` adds target_id, the file's name: a folder of one graph per file.
    """
    if fmt == "text":
        lines = spark.read.text(path)
        rows = lines.select(F.split(F.trim("value"), r"\s+").alias("w"), F.col("_metadata.file_name").alias("target_id")).filter((F.size("w") >= 2) & ~F.col("w")[0].startswith("#"))
        edges = rows.select(F.col("w")[0].cast("long").alias("src"), F.col("w")[1].cast("long").alias("dst"), F.get("w", F.lit(2)).alias("elabel"), "target_id")
    elif fmt in ("csv", "json", "parquet", "orc"):
        reader = spark.read.schema(EDGES)
        edges = (reader.option("header", True).csv(path) if fmt == "csv" else reader.format(fmt).load(path)).select("*", F.col("_metadata.file_name").alias("target_id"))
    else:
        raise ValueError(f"{fmt} is no edge list format")
    return edges if target_from_file else edges.drop("target_id")


def target_of_edges(edges: DataFrame, vertices: DataFrame | None = None, simple: bool = True) -> TargetGraph:
    """A target from edges; without vertices, all ends are unlabelled vertices."""
    if vertices is None:
        ends = edges.select(F.col("src").alias("vid")).union(edges.select(F.col("dst").alias("vid"))).distinct()
        vertices = ends.withColumn("vlabel", F.lit(None).cast(VERTICES["vlabel"].dataType))
    return TargetGraph.of(vertices, edges, simple)


def write_matches(matches: DataFrame, path: str, fmt: str = "parquet", by: str | None = None, mode: str = "errorifexists") -> None:
    writer = matches.write.mode(mode).format(fmt)
    if fmt == "csv":
        writer = writer.option("header", True)
    (writer.partitionBy(by) if by else writer).save(path)


def write_edge_store(target: TargetGraph, table: str, buckets: int = 16) -> tuple[str, str]:
    """Two tables of the edges with their ends' labels, bucketed and sorted by src and by dst: joins from either end need no shuffle of the edges."""
    names = []
    v = target.vertices
    edges = target.edges.join(v.select(F.col("vid").alias("src"), F.col("vlabel").alias("src_label")), "src").join(v.select(F.col("vid").alias("dst"), F.col("vlabel").alias("dst_label")), "dst")
    for side in ("src", "dst"):
        names.append(f"{table}_by_{side}")
        edges.write.mode("overwrite").bucketBy(buckets, side).sortBy(side).saveAsTable(names[-1])
    return names[0], names[1]
