"""Headline searches at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import statistics
import time


def main() -> None:
    from pyspark.sql import SparkSession

    from subgraph_spark.model import PatternGraph
    from subgraph_spark.operators import engines, workloads
    from subgraph_spark.operators.patterns import CATALOG
    from subgraph_spark.sources.tables import BUILDERS

    sf, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "8g")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    targets = {n: BUILDERS[n](spark, sf).written() for n in ("part_flow", "supplier_echo", "commerce", "user_relay")}
    took: dict[str, float] = {}
    counts: dict[str, dict] = {}

    def timed(name: str, run, repeats: int = 3) -> None:
        """The median of some runs; the first of all queries also warms the engine up."""
        seconds = []
        for _ in range(repeats):
            began = time.monotonic()
            out = run()
            seconds.append(time.monotonic() - began)
        took[name] = round(statistics.median(seconds), 3)
        counts[name] = {k: out[k] for k in ("pairs", "matches")}

    def search(target: str, pattern: PatternGraph, method: str, engine: str, **how):
        return lambda: engines.counts(targets[target], pattern, method, engine, **how).first()

    search("part_flow", CATALOG["P1"], "ord", "dfs")()
    for name, target, key, method, engine in (
        ("cycle3_ord_join", "part_flow", "P1", "ord", "join"),
        ("cycle3_ord_dfs", "part_flow", "P1", "ord", "dfs"),
        ("cycle3_domsf_rounds", "part_flow", "P1", "dom_sf", "rounds"),
        ("cycle4_ord_dfs", "part_flow", "P4", "ord", "dfs"),
        ("conational_ord_join", "commerce", "P5", "ord", "join"),
        ("conational_domsf_join", "commerce", "P5", "dom_sf", "join"),
        ("ffl_nation_dom", "supplier_echo", "P3", "dom", "dfs"),
        ("ffl_nation_domsf", "supplier_echo", "P3", "dom_sf", "dfs"),
    ):
        timed(name, search(target, CATALOG[key], method, engine))
    # Long instances: own sequential version against all workers, on arrays prepared once.
    speedups = {}
    long = {"cycle4_part_flow": ("part_flow", CATALOG["P4"]), "cycle3_user_relay": ("user_relay", CATALOG["P1"]), "path4_supplier_echo": ("supplier_echo", PatternGraph.parse("a->b; b->c; c->d; a->d; a->c"))}
    for name, (target, pattern) in long.items():
        for method in ("ord", "dom_sf"):
            ready = engines.prepare(targets[target], pattern, method)
            csr = ready.csr()
            for workers in (1, int(cpus)):
                began = time.monotonic()
                seeds = engines._dealt(engines._seeds(engines._roots(ready), 1), workers * (4 if workers > 1 else 1), "roundrobin")
                row = engines.explore(seeds, csr, ready, count_only=True).groupBy("kind").sum("pairs").collect()
                seconds = time.monotonic() - began
                pairs = next((r["sum(pairs)"] for r in row if r["kind"] == "stat"), 0)
                speedups[f"{name}_{method}_{workers}"] = {"s": round(seconds, 3), "pairs_per_s": round(pairs / seconds)}
    # Whole pattern sets inside tasks: mean milliseconds of preparation and search, pairs, what the budget left, and peak memory of a worker.
    sets = {}
    for collection, names, methods in (("dense_many_labels", ("supplier_echo", "part_flow"), ("ord", "dom", "dom_s", "dom_sf")), ("denser_few_labels", ("user_relay",), ("dom", "dom_s", "dom_sf"))):
        began = time.monotonic()
        found = workloads.searches(collection, [targets[n] for n in names], methods, 3_000_000).toPandas()
        took[f"pattern_set_{collection}"] = round(time.monotonic() - began, 3)
        whole = found[~found.groupby("instance").cut.transform("max")]
        for m, rows in whole.groupby("method"):
            every = found[found.method == m]
            sets[f"{collection}_{m}"] = {"finished_by_all": len(rows), "unfinished": int(every.cut.sum()), "prep_ms": round(rows.prep_ms.mean(), 2), "match_ms": round(rows.match_ms.mean(), 2), "total_ms": round(rows.total_ms.mean(), 2), "total_ms_sd": round(rows.total_ms.std(ddof=0), 2), "pairs": round(rows.pairs.mean(), 1), "pairs_per_s": round(every.pairs.sum() / every.match_ms.sum() * 1000), "peak_worker_mb": round(every.peak_mb.max())}
    print(json.dumps({"metric": "sum of medians over headline searches", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "counts": counts, "workers": speedups, "sets": sets, "cpus": cpus, "sf": os.path.basename(sf.rstrip("/"))}))


if __name__ == "__main__":
    main()
