"""Every registered query with SQL, against DuckDB on the smallest tables; plans; sources and sinks."""

import duckdb
import pytest

import __spark_entry__ as entry
from subgraph_spark import catalog
from subgraph_spark.model import PatternGraph
from subgraph_spark.operators import engines, stats
from subgraph_spark.sources import io, tables

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def plain(x):
    return round(x, 6) if isinstance(x, float) else tuple(map(plain, x)) if isinstance(x, list) else x


@pytest.mark.parametrize("name", sorted(catalog.ORACLE_SQL))
def test_query_equals_sql(spark, sf, duck, name):
    df = catalog.QUERIES[name](spark, sf)
    columns = sorted(df.columns)
    got = sorted((tuple(plain(r[c]) for c in columns) for r in df.collect()), key=repr)
    made = duck.execute(catalog.ORACLE_SQL[name])
    names = [x[0] for x in made.description]
    expected = sorted((tuple(plain(r[names.index(c)]) for c in columns) for r in made.fetchall()), key=repr)
    assert sorted(names) == columns and got == expected


READ_TABLES = ["order_catalog_ord", "order_by_degree", "order_by_domain", "order_catalog_dom", "order_catalog_doms", "anchors_catalog", "plan_edges_once", "automorphisms_catalog", "fc_round_trace", "fc_worked_example", "pandas_udaf_gmean", "edges_uniform_dense"]


@pytest.mark.parametrize("name", READ_TABLES)
def test_query_reads_its_tables(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        catalog.QUERIES[name](spark, str(tmp_path)).collect()


def test_experiments_hold_what_they_must(spark, sf, monkeypatch):
    """Queries without SQL: sums, bounds and orders that hold whatever the numbers are."""
    monkeypatch.setattr(catalog, "BUDGET", 100_000)
    rows = lambda name: catalog.QUERIES[name](spark, sf).collect()
    for c in ("dense_many_labels", "sparse"):
        methods = catalog._SETS[c][0]
        spaces = rows(f"variants_{c}")
        open_ = {r.method: r for r in rows(f"unfinished_{c}")}
        assert set(open_) == set(methods) and len({r.instances for r in open_.values()}) == 1
        for kind in {r["class"] for r in spaces}:
            mine = [r for r in spaces if r["class"] == kind]
            assert len(mine) == len(methods) and len({(r.instances, r.finished_by_all, r.matches) for r in mine}) == 1
        for m in methods:
            assert sum(r.unfinished for r in spaces if r.method == m) == open_[m].unfinished
    assert all(r.of_baseline == 1.0 for r in rows("long_sample_dense_many_labels") if r.method == "dom")
    for name in ("speedup_over_self_sparse", "speedup_over_published_dense_many_labels"):
        found = rows(name)
        assert found and all(r.speedup_min <= r.speedup_gmean <= r.speedup_max for r in found)
        if "self" in name:
            assert all(r.speedup_avg == 1.0 for r in found if r.workers == 1) and not any(r.above_workers for r in found)
    stealing = {(r.group_size, r.stealing): r for r in rows("stealing_on_off")}
    assert stealing[1, True].makespan < stealing[1, False].makespan and stealing[1, False].steals_ok == 0
    assert all(r.stealing or r.steals_ok == 0 == r.steals_failed for r in rows("steal_sim_grid_sparse"))
    ways = {r.way: r for r in rows("steal_alternatives")}
    assert len({r.pairs for r in ways.values()}) == 1 and ways["no stealing"].steals_ok == 0
    assert ways["mapping copied per task"].cells_copied > ways["private deques"].cells_copied
    assert ways["mapping copied per task"].makespan > ways["private deques"].makespan
    assert all(r.least_edges == r.edges and r.components == 1 and r.least_vertices <= r.edges + 1 for r in rows("extract_patterns_semi"))
    assert any(r.branches for r in rows("large_branches_four_targets"))
    orders = {r.order: r for r in rows("orders_and_state_space")}
    assert len({r.matches for r in orders.values()}) == 1 and not any(r.cut for r in orders.values())
    assert orders["state_space"].pairs > orders["constraint_first"].pairs


def test_entry(spark):
    assert entry.entry(spark).count() == 2688
    assert set(entry.oracle_sql()) <= set(entry.queries())


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark, sf):
    t = tables.part_flow(spark, sf).written()
    plan = plan_of(engines.enumerate(t, PatternGraph.parse("a->b; b->c; c->a")))
    assert "LeftSemi" in plan and "Cartesian" not in plan and "NestedLoop" not in plan and "Python" not in plan
    scan = plan_of(tables.supplier_echo(spark, sf).edges)
    assert "l_extendedprice" not in scan and "NestedLoop" not in scan


def test_edge_lists(spark, tmp_path):
    (tmp_path / "g1.txt").write_text("# a graph\n1 2 x\n2 3\n\n")
    (tmp_path / "g2.txt").write_text("7 8\n")
    rows = io.read_edge_list(spark, str(tmp_path), target_from_file=True).collect()
    assert {tuple(r) for r in rows} == {(1, 2, "x", "g1.txt"), (2, 3, None, "g1.txt"), (7, 8, None, "g2.txt")}
    t = io.target_of_edges(io.read_edge_list(spark, str(tmp_path)))
    found = engines.enumerate(t, PatternGraph.parse("a->b; b->c"))
    for fmt in ("parquet", "orc", "json", "csv"):
        io.write_matches(found, str(tmp_path / f"out-{fmt}"), fmt)
        assert spark.read.format(fmt).option("header", True).load(str(tmp_path / f"out-{fmt}")).count() == 1
        io.write_matches(t.edges, str(tmp_path / f"edges-{fmt}"), fmt)
        assert io.read_edge_list(spark, str(tmp_path / f"edges-{fmt}"), fmt).count() == 3


def test_components_and_core(spark):
    t = io.target_of_edges(spark.createDataFrame([(1, 2, None), (2, 3, None), (3, 1, None), (3, 4, None), (8, 9, None)], "src long, dst long, elabel string"))
    assert {tuple(r) for r in stats.weak_components(t).collect()} == {(1, 1), (2, 1), (3, 1), (4, 1), (8, 8), (9, 8)}
    assert {r.vid for r in stats.k_core(t, 2).collect()} == {1, 2, 3}


def test_delta_stream(spark, sf, tmp_path):
    from pyspark.sql import functions as F

    from subgraph_spark.streaming.edges import delta_stream

    t = tables.supplier_echo(spark, sf).written()
    p = PatternGraph.parse("a->b; b->c; a->c")
    t.edges.withColumn("k", F.pmod(F.hash("src", "dst"), F.lit(3))).repartition(3, "k").drop("k").write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(t.edges.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    delta_stream(stream, t.vertices, p, str(tmp_path / "store"), str(tmp_path / "out"), str(tmp_path / "ck")).awaitTermination()
    got = sorted((r.m0, r.m1, r.m2) for r in spark.read.parquet(str(tmp_path / "out")).collect())
    assert got == sorted((r.m0, r.m1, r.m2) for r in engines.enumerate(t, p).collect())
