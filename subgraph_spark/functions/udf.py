"""SQL access: a table function for patterns, aggregates and mask functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import arrow_udf, pandas_udf, udtf

from ..model import PatternGraph, TargetGraph
from ..operators import engines


@pandas_udf(T.DoubleType())
def geometric_mean(x: pd.Series) -> float:
    """Geometric mean, as an aggregate."""
    x = x.dropna()
    return float(np.exp(np.log(x).mean())) if len(x) else float("nan")


@arrow_udf(T.IntegerType())
def mask_size(mask: pa.Array) -> pa.Array:
    """Set bits of a mask."""
    return pa.array(np.bitwise_count(mask.fill_null(0).to_numpy(zero_copy_only=False)).astype(np.int32))


def register(spark: SparkSession, target: TargetGraph, name: str = "g") -> None:
    """Views ``{name}_vertices`` and ``{name}_edges``, the functions above, and ``match_pattern(text, method)`` as a table function over the target.

    The table function runs one search in one task, over arrays whose size is checked: for interactive use.
    """
    target.vertices.createOrReplaceTempView(f"{name}_vertices")
    target.edges.createOrReplaceTempView(f"{name}_edges")
    spark.udf.register("geometric_mean", geometric_mean)
    spark.udf.register("mask_size", mask_size)
    shared = spark.sparkContext.broadcast(target.csr())

    @udtf(returnType="m array<bigint>")
    class MatchPattern:
        def eval(self, text: str):
            from subgraph_spark.operators.dfs import Counters, Kernel
            from subgraph_spark.plans.search_plan import build

            pattern = PatternGraph.parse(text)
            plan = build(pattern)
            kernel = Kernel(shared.value, plan)
            place = np.argsort(plan.order)
            for _, block in kernel.run(kernel.seeds(), Counters()):
                for row in shared.value.vids[block][:, place].tolist():
                    yield (row,)

    spark.udtf.register("match_pattern", MatchPattern)


__all__ = ["engines", "geometric_mean", "mask_size", "register"]
