"""Dealing root tasks to workers, task groups, and how many workers a search is worth."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def deal(roots: DataFrame, workers: int, how: str = "block") -> DataFrame:
    """``roots`` (vid) with ``worker`` from 0: contiguous blocks of the ids' order, the remainder to the first workers; or one after the other.

    Over all roots at once, so for inspection and simulation; the engines deal by partitions.
    """
    order = Window.orderBy("vid")
    worker = F.ntile(workers).over(order) - 1 if how == "block" else F.pmod(F.row_number().over(order) - 1, F.lit(workers))
    return roots.withColumn("worker", worker.cast("int"))


def groups(tasks: DataFrame, group_size: int, parent: str = "prefix_id") -> DataFrame:
    """Siblings (``prefix_id``, ``pos``, ``vt``) in groups of ``group_size`` at most: (prefix_id, pos, grp, vts)."""
    at = F.floor((F.row_number().over(Window.partitionBy(parent, "pos").orderBy("vt")) - 1) / group_size)
    return tasks.withColumn("grp", at).groupBy(parent, "pos", "grp").agg(F.array_sort(F.collect_list("vt")).alias("vts"))


def worth(pairs: float, roots: int, least_pairs: int = 1_000_000, most: int = 10_000) -> int:
    """Workers worth having: one per ``least_pairs`` pairs, and no more than one per root."""
    return max(1, min(most, roots, int(min(pairs, 1e18) // least_pairs)))


def advise(pairs_by_root: DataFrame, least_pairs: int = 1_000_000, most: int = 10_000) -> int:
    """``worth`` from measured pairs per root."""
    row = pairs_by_root.agg(F.sum("pairs").alias("pairs"), F.count("*").alias("roots")).first()
    return worth(row["pairs"] or 0, row["roots"], least_pairs, most)
