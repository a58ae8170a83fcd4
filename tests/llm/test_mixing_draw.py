"""The draw of mixing, against a walk down the order."""

import pytest
from pyspark.sql import functions as F

from subgraph_spark.llm import mixing
from subgraph_spark.llm.common import stage


@pytest.mark.parametrize("seed", [1, 2, 5])
def test_long_documents_are_skipped(spark, seed):
    """One long document among many short ones: the source comes within a short one of its target."""
    sizes = [("a", 40_000)] + [("a", 600)] * 100 + [("b", 50)] * 400 + [("c", 7)] * 50
    rows = [(None, s, n, hash((i, seed)) & 0xFFFFFFFF, "f", i) for i, (s, n) in enumerate(sizes)]
    df = stage(spark.createDataFrame(rows, "doc_id long, source string, size long, line long, file string, row long"), "rows")
    got = mixing.copies(df, share=0.3, cap=1, settle=0, seed=seed).collect()
    for source, least in (("a", 600), ("b", 50), ("c", 7)):
        mine = [r for r in got if r.source == source]
        lack = mine[0].target - sum(r.copies * r.size for r in mine)
        assert -1e-6 <= lack and (lack < least or all(r.copies for r in mine))


def test_passes_walk_down_the_order(spark):
    import random

    rng = random.Random(4)
    rows = [(s, int(rng.paretovariate(0.7) * 5), "f", i, rng.choice([rng.random(), rng.random() * 40, 0.5])) for i, s in enumerate("aaaaabbbc" * 60)]
    drawn = stage(spark.createDataFrame(rows, "source string, size long, file string, row long, order double").withColumn("bucket", mixing._bucket(F.col("order"))), "drawn")
    lacks = {"a": 4000.5, "b": 700.0, "c": 10.0**9}
    missing, passes = mixing._passes(drawn, spark.createDataFrame(list(lacks.items()), "source string, lacks double"))
    got = {r.row for r in mixing._by_source(drawn, passes, "passes").filter(mixing._taken()).collect()}
    expected, left = set(), dict(lacks)
    for s, n, _, i, _ in sorted(rows, key=lambda r: (r[4], r[2], r[3])):
        if n <= left[s]:
            expected.add(i)
            left[s] -= n
    assert got == expected
    assert {r.source: pytest.approx(r.missing) for r in missing.collect()} == left


def slow_rates(sizes, target, share, cap):
    """The dual of one source by bisection: rates share * exp(multiplier * size / mean), up to the cap, that meet the target."""
    import math

    mean = sum(sizes) / len(sizes)
    rate = lambda lam, n: min(cap, share * math.exp(min(lam * n / mean, 700)))
    low, high = -700.0, 700.0
    for _ in range(200):
        lam = (low + high) / 2
        low, high = (lam, high) if sum(n * rate(lam, n) for n in sizes) < target else (low, lam)
    return lam, [rate(lam, n) for n in sizes]


def test_multipliers_and_rates_of_the_dual(spark):
    import random

    rng = random.Random(6)
    sizes = {s: [int(rng.paretovariate(1.1) * 20) for _ in range(200)] for s in "abcde"}
    df = stage(spark.createDataFrame([(s, n) for s, all_ in sizes.items() for n in all_], "source string, size long"), "rows")
    counts = stage(df.groupBy("source", "size").agg(F.count("*").alias("n")), "counts")
    wanted = stage(mixing.targets(counts.groupBy("source").agg(F.sum(F.col("n") * F.col("size")).alias("source_size")), 1.5, 2, (5, 2, 1)), "targets")
    solved = mixing.balance(counts, wanted, 1.5, 2, "documents")
    rows = mixing._by_source(counts, solved, "source_size", "target", "mean", "lam").withColumn("rate", mixing.rate_of("documents", 1.5, 2)).collect()
    tilted = 0
    for s, all_ in sizes.items():
        mine = [r for r in rows if r.source == s]
        if mine[0].target >= 2 * sum(all_):
            assert all(r.rate == 2 for r in mine)
            continue
        lam, rates = slow_rates(all_, mine[0].target, 1.5, 2)
        rate_of = dict(zip(all_, rates, strict=True))
        assert mine[0].lam == pytest.approx(lam, rel=1e-6, abs=1e-9)
        assert all(r.rate == pytest.approx(rate_of[r.size], rel=1e-6) for r in mine)
        assert sum(r.n * r.size * r.rate for r in mine) == pytest.approx(mine[0].target, rel=1e-8)
        tilted += len({round(r.rate, 9) for r in mine}) > 10
    assert tilted >= 2


def test_rows_that_share_an_id_and_a_text(spark):
    """Ten thousand rows without an id, many of them of one text: each source comes within a thousandth of its target."""
    rows = [(None, "one two three four five six seven eight nine ten" if i % 3 else f"word{i} " * (i % 17), f"s{i % 4}") for i in range(10_000)]
    docs = stage(spark.createDataFrame(rows, "doc_id long, text string, source string"), "docs")
    for r in mixing.copies(mixing.sizes_of(docs)).groupBy("source").agg(F.sum(F.col("copies") * F.col("size")).alias("taken"), F.first("target").alias("target"), F.max("copies").alias("most")).collect():
        assert r.taken == pytest.approx(r.target, rel=1e-3) and r.most <= 2
