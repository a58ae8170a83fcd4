"""Every registered query of the graph engine, and the SQL that it is held against.

Results have integers and text where possible, doubles rounded to six places, and no clock times.
"""

from __future__ import annotations

import functools

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import udf
from .model import PatternGraph, TargetGraph, TargetTooLarge
from .operators import balance, baselines, domains, engines, expand, measures, patterns, stats, steal_sim, workloads
from .operators.baselines import sql_join
from .operators.dfs import Counters, Kernel, search_tree
from .operators.patterns import CATALOG
from .plans import order as orders
from .plans.search_plan import build
from .session import materialise
from .sources import io, tables
from .sources.tables import BUILDERS, graph_sql
from .streaming import edges as streaming

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def _add(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql is not None:
        ORACLE_SQL[name] = sql


def registered(sql: str | None = None, name: str | None = None):
    def take(f):
        _add(name or f.__name__, f, sql)
        return f

    return take


def target(spark: SparkSession, sf_dir: str, name: str) -> TargetGraph:
    return BUILDERS[name](spark, sf_dir)


def written(spark: SparkSession, sf_dir: str, name: str, degrees: bool = True) -> TargetGraph:
    return target(spark, sf_dir, name).written(degrees)


def values(columns: str, rows: list[tuple]) -> str:
    """A literal table as SQL."""
    one = lambda x: "NULL" if x is None else ("TRUE" if x else "FALSE") if isinstance(x, bool) else f"'{x}'" if isinstance(x, str) else str(x)
    return f"SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(one, r)) + ')' for r in rows)}) t({columns})"


# --- targets -------------------------------------------------------------------------------------------------------------

_WITH_SQL = ("supplier_echo", "part_flow", "user_relay", "turn_chain", "commerce", "doc_share", "embed_knn")
for _name in (*_WITH_SQL, "line_share", "doc_benchmark", "uniform_dense"):
    _add(f"edges_{_name}", lambda spark, sf, n=_name: target(spark, sf, n).edges.select("src", "dst", "elabel"), graph_sql(_name) + " SELECT src, dst, elabel FROM e")
    _add(f"vertices_{_name}", lambda spark, sf, n=_name: target(spark, sf, n).vertices.select("vid", "vlabel"), graph_sql(_name) + " SELECT vid, vlabel FROM v")

# A dense target with evenly spread labels from a given table; forward_checking_prunes keeps the drawn one.
_add("edges_uniform_dense", lambda spark, sf: tables.bucket_flow(spark, sf).edges.select("src", "dst", "elabel"), graph_sql("bucket_flow") + " SELECT src, dst, elabel FROM e")

_PATHS = "links AS MATERIALIZED (SELECT DISTINCT page_id, path FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"(/[^\"]*)\"', 1)) AS path FROM pages) q)"
_add("edges_page_links", lambda spark, sf: tables.page_paths(spark, sf), f"WITH {_PATHS} SELECT page_id, path FROM links")

_DEGREES = ", o AS (SELECT src AS vid, count(DISTINCT dst) AS outdeg FROM e GROUP BY 1), i AS (SELECT dst AS vid, count(DISTINCT src) AS indeg FROM e GROUP BY 1), d AS (SELECT v.vid, v.vlabel, coalesce(indeg, 0) AS indeg, coalesce(outdeg, 0) AS outdeg FROM v LEFT JOIN i USING (vid) LEFT JOIN o USING (vid))"
for _name in ("supplier_echo", "user_relay", "turn_chain"):
    _add(f"degrees_{_name}", lambda spark, sf, n=_name: target(spark, sf, n).degrees(), graph_sql(_name) + _DEGREES + " SELECT vid, vlabel, CAST(indeg AS INTEGER) AS indeg, CAST(outdeg AS INTEGER) AS outdeg FROM d")
_PROPERTY = "SELECT '{n}' AS target, count(*) AS vertices, (SELECT count(*) FROM e) AS edges, round(avg(indeg + outdeg), 6) AS degree_mean, round(stddev_pop(indeg + outdeg), 6) AS degree_sd, CAST(max(indeg + outdeg) AS INTEGER) AS degree_max, count(DISTINCT vlabel) AS labels FROM d"
for _name in _WITH_SQL:
    _add(f"properties_{_name}", lambda spark, sf, n=_name: stats.properties(target(spark, sf, n)), graph_sql(_name) + _DEGREES + " " + _PROPERTY.format(n=_name))


@registered("SELECT * FROM (" + ") UNION ALL SELECT * FROM (".join(graph_sql(n) + _DEGREES + " " + _PROPERTY.format(n=n) for n in _WITH_SQL[:5]) + ")")
def targets_property_table(spark, sf):
    return stats.collection_table([target(spark, sf, n) for n in _WITH_SQL[:5]])


_add("label_hist_part_flow", lambda spark, sf: stats.label_histogram(target(spark, sf, "part_flow")), graph_sql("part_flow") + " SELECT vlabel, count(*) AS n FROM v GROUP BY 1")
_add("hubs_commerce_top20", lambda spark, sf: stats.hubs(target(spark, sf, "commerce"), 20).withColumn("deg", F.col("deg").cast("int")), graph_sql("commerce") + _DEGREES + " SELECT vid, CAST(indeg + outdeg AS INTEGER) AS deg FROM d ORDER BY indeg + outdeg DESC, vid LIMIT 20")
_add("symmetrized_supplier_echo", lambda spark, sf: target(spark, sf, "supplier_echo").symmetrized().edges.select("src", "dst", "elabel"), graph_sql("supplier_echo") + " SELECT src, dst, min(elabel) AS elabel FROM (SELECT * FROM e UNION ALL SELECT dst, src, elabel FROM e) q GROUP BY 1, 2")
for _name in ("doc_share", "line_share"):
    _add(f"components_{_name}", lambda spark, sf, n=_name: stats.weak_components(target(spark, sf, n)), graph_sql(_name).replace("WITH ", "WITH RECURSIVE ", 1) + ", b AS (SELECT src, dst FROM e UNION SELECT dst, src FROM e), r(vid, component) AS (SELECT vid, vid FROM v UNION SELECT b.dst, r.component FROM r JOIN b ON b.src = r.vid WHERE r.component < b.dst) SELECT vid, min(component) AS component FROM r GROUP BY 1")


def _core_sql(name: str, k: int, rounds: int) -> str:
    """The k-core by so many rounds of peeling; more than the target's longest chain needs."""
    sql = graph_sql(name) + ", b0 AS MATERIALIZED (SELECT src, dst FROM e WHERE src <> dst UNION SELECT dst, src FROM e WHERE src <> dst)"
    for r in range(rounds):
        sql += f", c{r} AS MATERIALIZED (SELECT src FROM b{r} GROUP BY 1 HAVING count(*) >= {k}), b{r + 1} AS MATERIALIZED (SELECT src, dst FROM b{r} WHERE src IN (SELECT src FROM c{r}) AND dst IN (SELECT src FROM c{r}))"
    return sql + f" SELECT DISTINCT src AS vid FROM b{rounds}"


for _name in ("turn_chain", "supplier_echo"):
    _add(f"core2_{_name}", lambda spark, sf, n=_name: stats.k_core(target(spark, sf, n), 2), _core_sql(_name, 2, 12))

# --- searches ------------------------------------------------------------------------------------------------------------


def search(name: str, where: str, pattern: PatternGraph, method: str = "ord", engine: str = "join", sql: str | None = None, **how) -> None:
    def query(spark, sf):
        return engines.enumerate(written(spark, sf, where), pattern, method, engine, **how)

    _add(name, query, graph_sql(where) + " " + (sql or sql_join(pattern)))


C = CATALOG
for _name, _where, _p in (("cycle3_part_flow", "part_flow", "P1"), ("cycle3_echo", "supplier_echo", "P1"), ("ffl_part_flow", "part_flow", "P2"), ("ffl_echo", "supplier_echo", "P2"), ("cycle4_part_flow", "part_flow", "P4"), ("conational_commerce", "commerce", "P5"), ("dialogue_path", "turn_chain", "P6"), ("lag_ffl_echo", "supplier_echo", "P8"), ("brand_cycle", "part_flow", "P9"), ("single_vertex", "supplier_echo", "P11"), ("self_loop", "supplier_echo", "P12")):
    search(f"ord_{_name}", _where, C[_p], engine="halves" if _name == "cycle4_part_flow" else "join")  # paths of three edges are too many to be shuffled
for _m in ("dom", "dom_s", "dom_f", "dom_sf"):
    search(f"{_m.replace('_', '')}_ffl_nation_echo", "supplier_echo", C["P3"], _m)
    search(f"{_m.replace('_', '')}_conational_commerce", "commerce", C["P5"], _m)
    search(f"{_m.replace('_', '')}_cycle3_part_flow", "part_flow", C["P1"], _m, "dfs")
search("dom_fixpoint_ffl_nation_echo", "supplier_echo", C["P3"], "dom", rounds="fixpoint")
search("induced_ffl_echo", "supplier_echo", C["P2"], induced=True, sql=sql_join(C["P2"], induced=True))
search("induced_ffl_echo_dfs", "supplier_echo", C["P2"], engine="dfs", induced=True, sql=sql_join(C["P2"], induced=True))
search("empty_domain_exit", "supplier_echo", C["P13"], "dom_sf")
for _e in ("dfs", "hybrid", "rounds", "auto"):
    search(f"{_e}_equals_join_cycle3", "part_flow", C["P1"], "ord", _e, **({"budget": 100_000} if _e == "rounds" else {}))
    search(f"{_e}_equals_join_lag_ffl", "supplier_echo", C["P8"], "dom_sf", _e, **({"budget": 500} if _e == "rounds" else {}))
    search(f"{_e}_equals_join_dialogue", "turn_chain", C["P6"], "dom_s", _e)
search("sequential_cycle3", "part_flow", C["P1"], "ord", "dfs", workers=1)
search("static_split_cycle3", "part_flow", C["P1"], "ord", "dfs", workers=4, deal="block")
search("order_by_degree_cycle4", "part_flow", C["P4"], "ord", "dfs", order=orders.by_degree(C["P4"]))
search("order_random_cycle4", "part_flow", C["P4"], "ord", "dfs", order=orders.random(C["P4"], 5))
search("multigraph_relay_ffl", "user_relay", PatternGraph.parse("a:click-[error]->b:error; b-[view]->c:view; a-[view]->c"), "dom_sf", "join", sql=sql_join(PatternGraph.parse("a:click-[error]->b:error; b-[view]->c:view; a-[view]->c")))


search("sequential_dom_ffl_nation", "supplier_echo", C["P3"], "dom", "dfs", workers=1)
search("lookahead_ffl_echo", "supplier_echo", C["P2"], "dom_sf", "dfs", lookahead=True)


@registered(values("one, other, same", [("P1", "P1", True), ("P1", "P2", False), ("P2", "P2 turned", True), ("P1", "P4", False)]))
def isomorphism_checks(spark, sf):
    """Exact isomorphism of two small graphs: a target made of one pattern's vertices and edges, and the other pattern."""
    turned = PatternGraph.parse("c->b; b->a; c->a", "P2 turned")

    def graph(p: PatternGraph) -> TargetGraph:
        v = spark.createDataFrame([(i, x) for i, x in enumerate(p.labels)], "vid long, vlabel string")
        return TargetGraph.of(v, spark.createDataFrame(list(p.edges), "src long, dst long, elabel string"), name=p.name)

    pairs = ((C["P1"], C["P1"]), (C["P1"], C["P2"]), (C["P2"], turned), (C["P1"], C["P4"]))
    return spark.createDataFrame([(a.name, b.name, engines.is_isomorphic(graph(a), b)) for a, b in pairs], "one string, other string, same boolean")


@registered(graph_sql("supplier_echo") + " SELECT count(*) AS n FROM e x, e y WHERE x.src NOT IN (y.src, y.dst) AND x.dst NOT IN (y.src, y.dst)")
def disconnected_edges_echo(spark, sf):
    return engines.counts(written(spark, sf, "supplier_echo"), C["P10"], "ord", "dfs").select(F.col("matches").alias("n"))


@registered(f"WITH {_PATHS} SELECT a.page_id AS m0, b.page_id AS m1, count(*) AS n FROM links a JOIN links b ON a.path = b.path AND a.page_id <> b.page_id GROUP BY 1, 2")
def ord_colink_pages(spark, sf):
    found = engines.enumerate(written(spark, sf, "page_links"), C["P7"], "ord", "join")
    return found.groupBy("m0", F.col("m2").alias("m1")).agg(F.count("*").alias("n"))


@registered(graph_sql("part_flow") + " SELECT count(*) > 0 AS found FROM (" + sql_join(C["P9"]) + ") q UNION ALL SELECT count(*) > 0 FROM (" + sql_join(C["P1"]) + ") q")
def exists_cycles(spark, sf):
    where = written(spark, sf, "part_flow")
    return spark.createDataFrame([(engines.exists(where, C["P9"], "dom_sf"),), (engines.exists(where, C["P1"], "ord"),)], "found boolean")


@registered(graph_sql("part_flow") + " SELECT count(*) AS matches FROM (" + sql_join(C["P1"]) + ") q")
def count_only_cycle3(spark, sf):
    return engines.counts(written(spark, sf, "part_flow"), C["P1"], "dom_sf", "rounds").select("matches")


@registered(graph_sql("part_flow") + " SELECT count(*) AS n, count(*) // 3 AS cycles FROM (" + sql_join(C["P1"]) + ") q")
def distinct_cycles_part_flow(spark, sf):
    found = materialise(engines.enumerate(written(spark, sf, "part_flow"), C["P1"]), "matches")
    return found.agg(F.count("*").alias("n")).crossJoin(engines.distinct_subgraphs(found, C["P1"]).agg(F.count("*").alias("cycles")))


@registered(graph_sql("supplier_echo") + ", r AS (SELECT CAST(n_nationkey AS VARCHAR) AS nk, n_regionkey AS rk FROM nation), l AS (SELECT vid, rk FROM v JOIN r ON vlabel = nk) SELECT a.vid AS m0, b.vid AS m1, c.vid AS m2 FROM e x JOIN e y ON x.dst = y.src JOIN e z ON z.src = x.src AND z.dst = y.dst JOIN l a ON a.vid = x.src JOIN l b ON b.vid = x.dst JOIN l c ON c.vid = y.dst WHERE a.rk = 0 AND b.rk = 1 AND c.rk = 2")
def label_equivalence_region_ffl(spark, sf):
    """Labels match if the nations lie in the pattern's region: the table of allowed pairs has a row per nation."""
    allowed: dict[str, set[str]] = {}
    for row in tables.read(spark, sf, "nation").select("n_nationkey", "n_regionkey").collect():
        allowed.setdefault(f"region {row.n_regionkey}", set()).add(str(row.n_nationkey))
    p = PatternGraph(("region 0", "region 1", "region 2"), C["P2"].edges, "regions")
    return engines.enumerate(written(spark, sf, "supplier_echo"), p, "dom_s", "join", label_match=allowed)


@registered(graph_sql("supplier_echo") + " SELECT list_sort([m0, m1, m2])[1] AS low, m0 + m1 + m2 AS total, count(*) AS n FROM (" + sql_join(C["P1"]) + ") q GROUP BY 1, 2")
def match_forms(spark, sf):
    """Array and map form of the same matches agree; the result is made from both."""
    where = written(spark, sf, "supplier_echo")
    one = engines.enumerate(where, C["P1"], form="array").select(F.array_min("m").alias("low"), F.aggregate("m", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"))
    other = engines.enumerate(where, C["P1"], form="map").select(F.array_min(F.map_values("m")).alias("low"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x).alias("total"))
    both = one.groupBy("low", "total").agg(F.count("*").alias("n"))
    return both.join(other.groupBy("low", "total").agg(F.count("*").alias("n")), ["low", "total", "n"], "left_semi")


# --- domains, orders, plans ----------------------------------------------------------------------------------------------

_INIT = graph_sql("supplier_echo") + _DEGREES + ", q AS (SELECT * FROM (VALUES (0, '9', 0, 2), (1, '19', 1, 1), (2, '11', 2, 0)) t(pv, lab, ni, no)), pe AS (SELECT * FROM (VALUES (0, 1), (1, 2), (0, 2)) t(ps, pd)), d0 AS (SELECT q.pv, d.vid FROM d JOIN q ON d.vlabel = q.lab AND d.indeg >= q.ni AND d.outdeg >= q.no)"


def _round_sql(before: str, after: str) -> str:
    return f", {after} AS (SELECT x.pv, x.vid FROM {before} x WHERE NOT EXISTS (SELECT 1 FROM pe WHERE pe.ps = x.pv AND NOT EXISTS (SELECT 1 FROM e JOIN {before} y ON y.vid = e.dst WHERE e.src = x.vid AND y.pv = pe.pd)) AND NOT EXISTS (SELECT 1 FROM pe WHERE pe.pd = x.pv AND NOT EXISTS (SELECT 1 FROM e JOIN {before} y ON y.vid = e.src WHERE e.dst = x.vid AND y.pv = pe.ps)))"


_ROUNDS = _INIT + _round_sql("d0", "d1") + _round_sql("d1", "d2") + _round_sql("d2", "d3")


def _domains(spark, sf, rounds) -> DataFrame:
    found, _ = domains.prepare(written(spark, sf, "supplier_echo"), C["P3"], "dom", rounds, stop_early=False)
    return domains.rows(found, C["P3"])


_add("domain_init_p3", lambda spark, sf: _domains(spark, sf, 0), _INIT + " SELECT pv, vid FROM d0")
_add("domain_round1_p3", lambda spark, sf: _domains(spark, sf, 1), _ROUNDS + " SELECT pv, vid FROM d1")
_add("domain_fixpoint_p3", lambda spark, sf: _domains(spark, sf, "fixpoint"), _ROUNDS + " SELECT pv, vid FROM d3")


@registered(_ROUNDS + " SELECT pv, count(vid) AS size FROM q LEFT JOIN d1 USING (pv) GROUP BY pv")
def domain_sizes_p3(spark, sf):
    _, found = domains.prepare(written(spark, sf, "supplier_echo"), C["P3"], "dom", 1, stop_early=False)
    return spark.createDataFrame(list(zip(range(3), found.size, strict=True)), "pv int, size long")


@registered(_ROUNDS + " SELECT DISTINCT e.src, e.dst, e.elabel FROM e, d1 a, d1 b, pe WHERE a.vid = e.src AND b.vid = e.dst AND pe.ps = a.pv AND pe.pd = b.pv")
def reduced_edges_p3(spark, sf):
    where = written(spark, sf, "supplier_echo")
    found, _ = domains.prepare(where, C["P3"], "dom", 1)
    return domains.reduce_edges(where, C["P3"], found).select("src", "dst", "elabel")


#: Regions by the orders of their customers. Pattern vertex i may be any of the first i + 1, so that one domain after the other becomes single; a sixth vertex may be any nation.
_RANKED = "WITH k AS (SELECT n_regionkey AS region, row_number() OVER (ORDER BY count(*) DESC, n_regionkey) - 1 AS rank FROM orders JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey GROUP BY 1)"


def _forward_check(spark, sf):
    t = lambda name: tables.read(spark, sf, name)
    placed = t("orders").join(t("customer"), F.col("c_custkey") == F.col("o_custkey")).join(t("nation"), F.col("n_nationkey") == F.col("c_nationkey"))
    ranked = placed.groupBy("n_regionkey").agg(F.count("*").alias("n")).withColumn("rank", F.row_number().over(Window.orderBy(F.desc("n"), "n_regionkey")) - 1)
    rows = ranked.select(F.explode(F.sequence("rank", F.lit(4))).alias("pv"), F.col("n_regionkey").cast("long").alias("vid"))
    rows = rows.unionByName(t("nation").select(F.lit(5).alias("pv"), (F.col("n_nationkey") + 100).cast("long").alias("vid")))
    p = PatternGraph((None,) * 6, (), "ranked")
    start = materialise(rows.groupBy("vid").agg(F.bit_or(F.expr("shiftleft(1L, pv)")).alias("mask0")), "domains")
    trace = []
    end, _ = domains.forward_check(start, p, on_round=lambda d, s: trace.append(s.size))
    return domains.rows(end, p), trace


_add("fc_worked_example", lambda spark, sf: _forward_check(spark, sf)[0], _RANKED + " SELECT CAST(rank AS INTEGER) AS pv, CAST(region AS BIGINT) AS vid FROM k UNION ALL SELECT 5, CAST(n_nationkey + 100 AS BIGINT) FROM nation")


@registered(_RANKED + " SELECT CAST(r AS INTEGER) AS round, CAST(pv AS INTEGER) AS pv, CAST(size AS INTEGER) AS size FROM (SELECT r, rank AS pv, greatest(1, rank + 1 - r) AS size FROM k, range(1, 6) t(r) UNION ALL SELECT r, 5, (SELECT count(*) FROM nation) FROM range(1, 6) t(r)) q")
def fc_round_trace(spark, sf):
    _, trace = _forward_check(spark, sf)
    return spark.createDataFrame([(r, v, n) for r, row in enumerate(trace, 1) for v, n in enumerate(row)], "round int, pv int, size int")


# Patterns of a given table: an order's lines as a chain, as a ring, or around a hub. Orders with as many lines have the same pattern.

_SHAPES = {"chain": lambda n: [(i, i + 1) for i in range(n - 1)], "ring": lambda n: [(i, (i + 1) % n) for i in range(n if n > 2 else n - 1)], "hub": lambda n: [(n, i) for i in range(n)]}
_ARROW = {"int": pa.int32(), "long": pa.int64(), "boolean": pa.bool_()}


def _of_orders(spark, sf, shape: str, work, schema: str) -> DataFrame:
    """(lines, orders) and ``work(pattern)``'s rows, for each number of lines that an order has; patterns are made and planned in tasks."""
    per = tables.read(spark, sf, "lineitem").groupBy("l_orderkey").agg(F.count("*").alias("lines")).groupBy("lines").agg(F.count("*").alias("orders"))
    fields = [x.split() for x in f"lines long, orders long, {schema}".split(", ")]

    def run(batches):
        for batch in batches:
            for n, orders_ in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                pattern = PatternGraph((None,) * (n + (shape == "hub")), tuple((a, b, None) for a, b in _SHAPES[shape](n)), f"{shape} of {n}")
                rows = [(n, orders_, *x) for x in work(pattern)]
                yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], _ARROW[t]) for k, (_, t) in enumerate(fields)], names=[x for x, _ in fields])

    return per.mapInArrow(run, ", ".join(" ".join(x) for x in fields))


_BY_LINES = "WITH s AS (SELECT n, count(*) AS orders FROM (SELECT l_orderkey, count(*) AS n FROM lineitem GROUP BY 1) q GROUP BY 1)"
#: The constraint-first order of a chain: its inner vertices from the second on, then both ends.
_CHAIN = _BY_LINES + ", c AS (SELECT n, orders, i AS pos, CASE WHEN n < 3 THEN i WHEN i < n - 2 THEN i + 1 WHEN i = n - 2 THEN 0 ELSE n - 1 END AS pv FROM (SELECT n, orders, unnest(range(n)) AS i FROM s) q)"


#: Patterns whose domains' sizes on supplier_echo decide an order: a triangle and a path with the same labels.
_SIZED = {"P3": C["P3"], "path": PatternGraph.parse("a:9->b:19; b->c:11", "path")}


def _sized_orders(spark, sf, made, names=tuple(_SIZED)) -> DataFrame:
    where, rows = written(spark, sf, "supplier_echo"), []
    for name in names:
        _, found = domains.prepare(where, _SIZED[name], "dom", 1, stop_early=False)
        rows += [(name, pos, v) for pos, v in enumerate(made(_SIZED[name], found.size))]
    return spark.createDataFrame(rows, "pattern string, pos int, pv int")


def _sizes_sql(name: str) -> str:
    init = _INIT if name == "P3" else _INIT.replace("(0, '9', 0, 2), (1, '19', 1, 1), (2, '11', 2, 0)", "(0, '9', 0, 1), (1, '19', 1, 1), (2, '11', 1, 0)").replace("(0, 1), (1, 2), (0, 2)", "(0, 1), (1, 2)")
    return init + _round_sql("d0", "d1") + ", sz AS (SELECT pv, count(vid) AS n FROM q LEFT JOIN d1 USING (pv) GROUP BY pv)"


def _greedy_sql(tiebreak: bool) -> str:
    """The constraint-first order of three vertices as the best permutation: singletons, then placed neighbours, common neighbours to come, degree, the smaller domain where asked, the smaller id."""
    out = []
    for name in _SIZED:
        near = lambda x, y, k=name: f"(least({x}, {y}) * 3 + greatest({x}, {y})) IN {'(1, 2, 5)' if k == 'P3' else '(1, 5)'}"
        degree = lambda x, k=name: "2" if k == "P3" else f"(CASE {x} WHEN 1 THEN 2 ELSE 1 END)"
        size = lambda x: f"{x}, " if tiebreak else ""
        best = f"SELECT a, b, c FROM pm ORDER BY na <> 1, 0 - {degree('a')}, {size('na')}a, nb <> 1, NOT {near('a', 'b')}, NOT ({near('a', 'c')} AND {near('c', 'b')}), 0 - {degree('b')}, {size('nb')}b LIMIT 1"
        out.append(f"{_sizes_sql(name)}, pm AS (SELECT x.pv AS a, y.pv AS b, z.pv AS c, x.n AS na, y.n AS nb FROM sz x, sz y, sz z WHERE x.pv <> y.pv AND y.pv <> z.pv AND x.pv <> z.pv), best AS ({best}) SELECT '{name}' AS pattern, unnest([0, 1, 2]) AS pos, CAST(unnest([a, b, c]) AS INTEGER) AS pv FROM best")
    return "SELECT * FROM (" + ") UNION ALL SELECT * FROM (".join(out) + ")"


_add("order_catalog_ord", lambda spark, sf: _of_orders(spark, sf, "chain", lambda p: list(enumerate(orders.constraint_first(p))), "pos int, pv int"), _CHAIN + " SELECT n AS lines, orders, CAST(pos AS INTEGER) AS pos, CAST(pv AS INTEGER) AS pv FROM c")
_add("order_catalog_dom", lambda spark, sf: _sized_orders(spark, sf, lambda p, n: orders.constraint_first(p, n, False, True)), _greedy_sql(False))
_add("order_catalog_doms", lambda spark, sf: _sized_orders(spark, sf, lambda p, n: orders.constraint_first(p, n, True, True)), _greedy_sql(True))
_add("order_by_degree", lambda spark, sf: _of_orders(spark, sf, "hub", lambda p: list(enumerate(orders.by_degree(p))), "pos int, pv int"), _BY_LINES + " SELECT n AS lines, orders, CAST(i AS INTEGER) AS pos, CAST(CASE WHEN n = 1 THEN i WHEN i = 0 THEN n ELSE i - 1 END AS INTEGER) AS pv FROM (SELECT n, orders, unnest(range(n + 1)) AS i FROM s) q")
_add("order_by_domain", lambda spark, sf: _sized_orders(spark, sf, orders.by_domain_size, ("P3",)), _sizes_sql("P3") + " SELECT 'P3' AS pattern, CAST(row_number() OVER (ORDER BY n, pv) - 1 AS INTEGER) AS pos, CAST(pv AS INTEGER) AS pv FROM sz")


@registered(_CHAIN + " SELECT n AS lines, orders, CAST(pos AS INTEGER) AS pos, CAST(pv AS INTEGER) AS pv, CAST(CASE WHEN pos = 0 THEN NULL WHEN pv = 0 THEN 1 ELSE pv - 1 END AS INTEGER) AS anchor_pv, CASE WHEN pos = 0 THEN NULL ELSE pv <> 0 END AS leaves FROM c")
def anchors_catalog(spark, sf):
    def rows(p: PatternGraph):
        order = orders.constraint_first(p)
        return [(i, v, a and order[a[0]], a and a[1]) for i, (v, a) in enumerate(zip(order, orders.anchors(p, order), strict=True))]

    return _of_orders(spark, sf, "chain", rows, "pos int, pv int, anchor_pv int, leaves boolean")


@registered(_BY_LINES + " SELECT n AS lines, orders, CAST(CASE WHEN n < 3 THEN n - 1 ELSE n END AS INTEGER) AS uses, CAST(CASE WHEN n < 3 THEN n - 1 ELSE n END AS INTEGER) AS edges FROM s")
def plan_edges_once(spark, sf):
    used = lambda p: sum((s.anchor is not None) + len(s.checks) + len(s.loops) for s in build(p).steps)
    return _of_orders(spark, sf, "ring", lambda p: [(used(p), len(p.edges))], "uses int, edges int")


@registered(_BY_LINES + " SELECT n AS lines, orders, CAST(CASE WHEN n < 3 THEN 1 ELSE n END AS INTEGER) AS automorphisms FROM s")
def automorphisms_catalog(spark, sf):
    return _of_orders(spark, sf, "ring", lambda p: [(p.automorphisms(),)], "automorphisms int")


# --- measures ------------------------------------------------------------------------------------------------------------

_CYCLE_TREE = ", t1 AS MATERIALIZED (SELECT src AS a, dst AS b FROM e), p2 AS MATERIALIZED (SELECT t1.a, t1.b, x.src AS c FROM t1 JOIN e x ON x.dst = t1.a)"


def _funnel(name: str, where: str, pattern: PatternGraph, method: str, sql: str | None) -> None:
    _add(name, lambda spark, sf: measures.funnel(written(spark, sf, where), pattern, method), sql)


_funnel("funnel_ord_cycle3", "part_flow", C["P1"], "ord", graph_sql("part_flow") + _DEGREES + _CYCLE_TREE + ", ok AS (SELECT vid FROM d WHERE indeg >= 1 AND outdeg >= 1), f1 AS (SELECT t1.* FROM t1 WHERE t1.a IN (SELECT vid FROM ok)), f2 AS (SELECT * FROM p2 WHERE a IN (SELECT vid FROM ok) AND b IN (SELECT vid FROM ok)) SELECT 'ord' AS method, 0 AS depth, (SELECT count(*) FROM d) AS pairs, (SELECT count(*) FROM d) AS after_unused, (SELECT count(*) FROM d) AS after_label_or_domain, (SELECT count(*) FROM ok) AS after_degree, (SELECT count(*) FROM ok) AS after_edges UNION ALL SELECT 'ord', 1, (SELECT count(*) FROM f1), (SELECT count(*) FROM f1), (SELECT count(*) FROM f1), (SELECT count(*) FROM f1 WHERE b IN (SELECT vid FROM ok)), (SELECT count(*) FROM f1 WHERE b IN (SELECT vid FROM ok)) UNION ALL SELECT 'ord', 2, (SELECT count(*) FROM f2), (SELECT count(*) FROM f2 WHERE b <> c), (SELECT count(*) FROM f2 WHERE b <> c), (SELECT count(*) FROM f2 WHERE b <> c AND c IN (SELECT vid FROM ok)), (SELECT count(*) FROM f2 JOIN e ON e.src = b AND e.dst = c WHERE b <> c)")

_ORD_P3 = _DEGREES + ", r0 AS (SELECT vid AS a FROM d WHERE vlabel = '9' AND outdeg >= 2), g1 AS (SELECT a, dst AS b FROM r0 JOIN e ON src = a), r1 AS (SELECT a, b FROM g1 JOIN d ON vid = b WHERE vlabel = '19' AND indeg >= 1 AND outdeg >= 1 AND a <> b), g2 AS (SELECT a, b, dst AS c FROM r1 JOIN e ON src = a)"
_ORD_P3_PAIRS = "(SELECT count(*) FROM d) + (SELECT count(*) FROM g1) + (SELECT count(*) FROM g2)"
_funnel("funnel_p3_ord", "supplier_echo", C["P3"], "ord", graph_sql("supplier_echo") + _ORD_P3 + " SELECT 'ord' AS method, 0 AS depth, (SELECT count(*) FROM d) AS pairs, (SELECT count(*) FROM d) AS after_unused, (SELECT count(*) FROM d WHERE vlabel = '9') AS after_label_or_domain, (SELECT count(*) FROM r0) AS after_degree, (SELECT count(*) FROM r0) AS after_edges UNION ALL SELECT 'ord', 1, (SELECT count(*) FROM g1), (SELECT count(*) FROM g1 WHERE a <> b), (SELECT count(*) FROM g1 JOIN d ON vid = b WHERE vlabel = '19' AND a <> b), (SELECT count(*) FROM r1), (SELECT count(*) FROM r1) UNION ALL SELECT 'ord', 2, (SELECT count(*) FROM g2), (SELECT count(*) FROM g2 WHERE c NOT IN (a, b)), (SELECT count(*) FROM g2 JOIN d ON vid = c WHERE c NOT IN (a, b) AND vlabel = '11'), (SELECT count(*) FROM g2 JOIN d ON vid = c WHERE c NOT IN (a, b) AND vlabel = '11' AND indeg >= 2), (SELECT count(*) FROM g2 JOIN d ON vid = c JOIN e ON e.src = b AND e.dst = c WHERE c NOT IN (a, b) AND vlabel = '11' AND indeg >= 2)")
_DOM_P3 = ", r0 AS (SELECT vid AS a FROM d1 WHERE pv = 0), g1 AS (SELECT a, dst AS b FROM r0 JOIN e ON src = a), r1 AS (SELECT a, b FROM g1 JOIN d1 ON vid = b AND pv = 1), g2 AS (SELECT a, b, dst AS c FROM r1 JOIN e ON src = a)"
_DOM_P3_PAIRS = "(SELECT count(*) FROM r0) + (SELECT count(*) FROM g1) + (SELECT count(*) FROM g2)"
_funnel("funnel_p3_dom", "supplier_echo", C["P3"], "dom", _ROUNDS + _DOM_P3 + ", z AS (SELECT 'dom' AS method, 0 AS depth, (SELECT count(*) FROM r0) AS pairs, (SELECT count(*) FROM r0) AS after_unused, (SELECT count(*) FROM r0) AS after_label_or_domain, (SELECT count(*) FROM r0) AS after_edges UNION ALL SELECT 'dom', 1, (SELECT count(*) FROM g1), (SELECT count(*) FROM r1), (SELECT count(*) FROM r1), (SELECT count(*) FROM r1) UNION ALL SELECT 'dom', 2, (SELECT count(*) FROM g2), (SELECT count(*) FROM g2 JOIN d1 ON vid = c AND pv = 2), (SELECT count(*) FROM g2 JOIN d1 ON vid = c AND pv = 2), (SELECT count(*) FROM g2 JOIN d1 ON vid = c AND pv = 2 JOIN e ON e.src = b AND e.dst = c)) SELECT method, depth, pairs, after_unused, after_label_or_domain, CAST(NULL AS BIGINT) AS after_degree, after_edges FROM z WHERE NOT EXISTS (SELECT 1 FROM q WHERE pv NOT IN (SELECT pv FROM d1))")
# The smaller-domain order, decided from the sizes: b, c, a where the given tables have 7, 2 and 5 candidates; by its rule elsewhere.
_funnel(
    "funnel_p3_doms",
    "supplier_echo",
    C["P3"],
    "dom_s",
    _ROUNDS
    + ", sz AS (SELECT pv, count(*) AS n FROM d1 GROUP BY 1), rk AS (SELECT pv, row_number() OVER (ORDER BY n, pv) - 1 AS pos FROM sz), dv AS (SELECT rk.pos, d1.vid FROM d1 JOIN rk USING (pv))"
    + ", pp AS (SELECT a.pos AS ps, b.pos AS pd FROM pe JOIN rk a ON a.pv = pe.ps JOIN rk b ON b.pv = pe.pd)"
    + ", arc AS (SELECT pp.ps AS near, pp.pd AS far, e.src AS x, e.dst AS y FROM pp, e UNION ALL SELECT pp.pd, pp.ps, e.dst, e.src FROM pp, e)"
    + ", r0 AS (SELECT vid AS a FROM dv WHERE pos = 0), g1 AS (SELECT a, y AS b FROM r0 JOIN arc ON near = 0 AND far = 1 AND x = a), r1 AS (SELECT a, b FROM g1 JOIN dv ON vid = b AND pos = 1 WHERE a <> b)"
    + ", g2 AS (SELECT a, b, y AS c FROM r1 JOIN arc ON near = 0 AND far = 2 AND x = a), r2 AS (SELECT a, b, c FROM g2 JOIN dv ON vid = c AND pos = 2)"
    + ", z AS (SELECT 'dom_s' AS method, 0 AS depth, (SELECT count(*) FROM r0) AS pairs, (SELECT count(*) FROM r0) AS after_unused, (SELECT count(*) FROM r0) AS after_label_or_domain, (SELECT count(*) FROM r0) AS after_edges"
    + " UNION ALL SELECT 'dom_s', 1, (SELECT count(*) FROM g1), (SELECT count(*) FROM r1), (SELECT count(*) FROM g1 JOIN dv ON vid = b AND pos = 1), (SELECT count(*) FROM r1)"
    + " UNION ALL SELECT 'dom_s', 2, (SELECT count(*) FROM g2), (SELECT count(*) FROM r2 WHERE c NOT IN (a, b)), (SELECT count(*) FROM r2), (SELECT count(*) FROM r2 JOIN arc ON near = 1 AND far = 2 AND x = b AND y = c WHERE c NOT IN (a, b)))"
    + " SELECT method, depth, pairs, after_unused, after_label_or_domain, CAST(NULL AS BIGINT) AS after_degree, after_edges FROM z WHERE NOT EXISTS (SELECT 1 FROM q WHERE pv NOT IN (SELECT pv FROM d1))",
)


@registered(_ROUNDS + _ORD_P3.replace(_DEGREES, "") + f" SELECT 'ord' AS method, {_ORD_P3_PAIRS} AS pairs UNION ALL SELECT 'dom', CASE WHEN EXISTS (SELECT 1 FROM q WHERE pv NOT IN (SELECT pv FROM d1)) THEN 0 ELSE (" + "WITH " + _DOM_P3[2:] + f" SELECT {_DOM_P3_PAIRS}) END")
def search_space_by_variant(spark, sf):
    where = written(spark, sf, "supplier_echo")
    return spark.createDataFrame([(m, engines.counts(where, C["P3"], m, "dfs").first()["pairs"]) for m in ("ord", "dom")], "method string, pairs long")


def tree_of(spark, where: TargetGraph, pattern: PatternGraph, instance: str) -> DataFrame:
    """A search tree as a table. It is bounded, and made in one task from arrays whose size is checked."""
    shared = spark.sparkContext.broadcast(where.csr())

    def grow(batches):
        for _ in batches:
            tree = search_tree(Kernel(shared.value, build(pattern)))
            for at in range(0, len(tree["node_id"]), 50_000):
                yield pa.RecordBatch.from_pydict({"instance": [instance] * len(tree["node_id"][at : at + 50_000]), **{k: x[at : at + 50_000] for k, x in tree.items()}, "depth": tree["depth"][at : at + 50_000].astype("int32")})

    return spark.range(0, 1, 1, 1).mapInArrow(grow, "instance string, node_id long, parent_id long, depth int, vt long, consistent boolean")


_ECHO_TREE = graph_sql("supplier_echo") + _DEGREES + ", ok AS (SELECT vid FROM d WHERE indeg >= 1 AND outdeg >= 1), n1 AS MATERIALIZED (SELECT src AS a, dst AS b FROM e WHERE src IN (SELECT vid FROM ok)), n2 AS MATERIALIZED (SELECT n1.a, n1.b, x.src AS c FROM n1 JOIN e x ON x.dst = n1.a WHERE n1.b IN (SELECT vid FROM ok)), s1 AS (SELECT n1.a, n1.b, 1 + count(n2.c) AS size FROM n1 LEFT JOIN n2 USING (a, b) GROUP BY 1, 2), s0 AS (SELECT d.vid, 1 + coalesce(sum(size), 0) AS size FROM d LEFT JOIN s1 ON s1.a = d.vid GROUP BY 1), total AS (SELECT (SELECT count(*) FROM d) + (SELECT count(*) FROM n1) + (SELECT count(*) FROM n2) AS t)"


@registered(_ECHO_TREE + " SELECT 0 AS depth, count(*) FILTER (size >= 0.05 * t) AS branches FROM s0, total UNION ALL SELECT 1, count(*) FILTER (size >= 0.05 * t) FROM s1, total UNION ALL SELECT 2, count(*) FILTER (1 >= 0.05 * t) FROM n2, total")
def large_branches_echo(spark, sf):
    return measures.branches_of_search(written(spark, sf, "supplier_echo"), build(C["P1"]), 0.05)


@registered(_ECHO_TREE + ", w AS (SELECT vid, size, ntile(4) OVER (ORDER BY vid) - 1 AS worker FROM s0) SELECT CAST(worker AS INTEGER) AS worker, CAST(sum(size) AS BIGINT) AS states FROM w GROUP BY 1")
def static_deal_states_per_worker(spark, sf):
    tree = materialise(tree_of(spark, target(spark, sf, "supplier_echo"), C["P1"], "echo"), "tree")
    size = measures.subtree_sizes(tree).filter("depth = 0")
    roots = balance.deal(tree.filter("depth = 0").select(F.col("vt").alias("vid"), "node_id"), 4)
    return roots.join(size, "node_id").groupBy("worker").agg(F.sum("size").alias("states"))


def _grid(spark, workers, groups, seeds, stealing) -> DataFrame:
    return spark.createDataFrame([(w, g, s, x) for w in workers for g in groups for s in range(seeds) for x in stealing], "workers int, group_size int, seed int, stealing boolean")


@registered(_ECHO_TREE + " SELECT w AS workers, t AS pairs FROM total, (VALUES (1), (2), (4), (8), (16)) q(w)")
def steal_sim_totals(spark, sf):
    tree = tree_of(spark, target(spark, sf, "supplier_echo"), C["P1"], "echo")
    got = steal_sim.simulate_grid(tree, _grid(spark, (1, 2, 4, 8, 16), (4,), 1, (True,)))
    return got.select("workers", "pairs")


@registered(_ECHO_TREE + " SELECT 0 AS attempts, t AS pairs FROM total")
def steal_sim_p1(spark, sf):
    tree = tree_of(spark, target(spark, sf, "supplier_echo"), C["P1"], "echo")
    got = steal_sim.simulate_grid(tree, _grid(spark, (1,), (1,), 1, (True,)))
    return got.select((F.col("steals_ok") + F.col("steals_failed")).cast("int").alias("attempts"), "pairs")


_ALTERNATIVES = {"private deques": {}, "mapping copied per task": {"copy": "per_task"}, "large tasks only": {"min_states": 1000}, "sender-initiated": {"initiator": "sender"}, "dealt in turn": {"deal": "roundrobin"}, "no stealing": {"stealing": False}}


def _alternatives(spark, sf) -> DataFrame:
    """The published scheme and the ones it was weighed against, on one tree with eight workers."""
    tree = search_tree(Kernel(target(spark, sf, "supplier_echo").csr(), build(C["P1"])))
    return steal_sim.simulate_ways(spark, tree, _ALTERNATIVES, workers=8)


_add("steal_alternatives_totals", lambda spark, sf: _alternatives(spark, sf).select("way", "pairs"), _ECHO_TREE + f" SELECT way, t AS pairs FROM total, ({values('way', [(k,) for k in _ALTERNATIVES])}) w")
_add("steal_alternatives", _alternatives)


_RUNS = [("i1", 500.0, 250.0, False), ("i2", 900.0, 600.0, False), ("i3", 4000.0, 1000.0, False), ("i4", 180000.0, 90000.0, True), ("i5", 20000.0, 180000.0, False), ("i6", 1000.0, 125.0, False)]


def _runs(spark) -> tuple[DataFrame, DataFrame]:
    row = lambda i, ms, late, w: (i, "fixed", "ord", w, 4, 0, 1.0, ms - 1.0, ms, int(ms) * 10, 1, 0, 0, 1.0, late)
    return measures.runs_table(spark, [row(i, a, late, 1) for i, a, _, late in _RUNS]), measures.runs_table(spark, [row(i, b, i == "i5", 4) for i, _, b, _ in _RUNS])


_RUNS_SQL = "WITH r AS (" + values("i, a, b, late", _RUNS) + ")"


@registered(_RUNS_SQL + ", x AS (SELECT a, b, a / b AS ratio, unnest(['all', CASE WHEN a < 1000 THEN 'short' ELSE 'long' END]) AS class FROM r WHERE NOT late) SELECT class, count(*) AS instances, round(CAST(sum(a) / sum(b) AS DOUBLE), 6) AS speedup_avg, round(CAST(exp(avg(ln(ratio))) AS DOUBLE), 6) AS speedup_gmean, round(CAST(max(ratio) AS DOUBLE), 6) AS speedup_max, round(CAST(min(ratio) AS DOUBLE), 6) AS speedup_min, max(ratio) > 4 AS above_workers FROM x GROUP BY 1")
def speedup_summary(spark, sf):
    return measures.speedups(*_runs(spark), workers=4)


@registered(_RUNS_SQL + " SELECT 'ord' AS method, 1 AS workers, count(*) FILTER (late) AS unsolved, count(*) AS instances FROM r UNION ALL SELECT 'ord', 4, count(*) FILTER (i = 'i5'), count(*) FROM r")
def unsolved_summary(spark, sf):
    a, b = _runs(spark)
    return measures.unsolved(a.unionByName(b))


@registered(_RUNS_SQL + " SELECT 'ord' AS method, 1 AS workers, count(*) AS instances, round(avg(CAST(a AS DOUBLE)), 6) AS mean_ms, round(stddev_samp(CAST(a AS DOUBLE)), 6) AS sd_ms, round(stddev_samp(CAST(a AS DOUBLE)) / sqrt(count(*)), 6) AS se_ms, round(avg(CAST(a * 10 AS DOUBLE)), 6) AS mean_pairs, round(stddev_samp(CAST(a * 10 AS DOUBLE)), 6) AS sd_pairs, round(CAST(sum(a * 10) AS DOUBLE) / CAST(sum(a - 1) AS DOUBLE) * 1000, 6) AS pairs_per_s FROM r")
def stderr_summary(spark, sf):
    return measures.time_summary(_runs(spark)[0])


@registered(_RUNS_SQL + " SELECT round(avg(CAST(a AS DOUBLE)), 6) AS before_ms, round(avg(CAST(b AS DOUBLE)), 6) AS after_ms, round((1 - avg(CAST(b AS DOUBLE)) / avg(CAST(a AS DOUBLE))) * 100, 6) AS reduction_pct, round(avg(CAST(a AS DOUBLE)) / avg(CAST(b AS DOUBLE)), 6) AS factor FROM r")
def time_reduction_summary(spark, sf):
    return measures.time_reduction(*_runs(spark))


# --- baselines -----------------------------------------------------------------------------------------------------------


def sql_baseline(spark, sf, where: str, pattern: PatternGraph, reorder: bool = False) -> DataFrame:
    t = written(spark, sf, where)
    t.edges.createOrReplaceTempView("base_e")
    t.vertices.createOrReplaceTempView("base_v")
    keys = ("spark.sql.cbo.enabled", "spark.sql.cbo.joinReorder.enabled")
    before = {k: spark.conf.get(k) for k in keys}
    try:
        for k in keys:
            spark.conf.set(k, str(reorder).lower())
        return materialise(spark.sql(sql_join(pattern, edges="base_e", vertices="base_v")), "baseline")
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)


_add("sql_join_baseline", lambda spark, sf: sql_baseline(spark, sf, "part_flow", C["P1"]), graph_sql("part_flow") + " " + sql_join(C["P1"]))
_add("sql_join_reordered", lambda spark, sf: sql_baseline(spark, sf, "commerce", C["P5"], True), graph_sql("commerce") + " " + sql_join(C["P5"]))


@registered(graph_sql("supplier_echo") + " " + sql_join(C["P2"]))
def state_space_baseline_ffl(spark, sf):
    return baselines.state_space_matches(target(spark, sf, "supplier_echo"), C["P2"])


@registered(graph_sql("part_flow") + ", p AS MATERIALIZED (SELECT least(src, dst) AS a, greatest(src, dst) AS b, sum(CASE WHEN src < dst THEN 1 ELSE 2 END) AS c FROM e GROUP BY 1, 2), s AS MATERIALIZED (SELECT a AS u, b AS v FROM p UNION SELECT b, a FROM p), t AS MATERIALIZED (SELECT DISTINCT list_sort([x.u, x.v, y.v]) AS t FROM s x JOIN s y ON x.u = y.u AND x.v < y.v), g AS (SELECT coalesce(p1.c, 0) AS xy, coalesce(p2.c, 0) AS xz, coalesce(p3.c, 0) AS yz FROM t LEFT JOIN p p1 ON p1.a = t[1] AND p1.b = t[2] LEFT JOIN p p2 ON p2.a = t[1] AND p2.b = t[3] LEFT JOIN p p3 ON p3.a = t[2] AND p3.b = t[3]), h AS (SELECT *, (3 - xy) % 3 + CASE WHEN xy = 3 THEN 3 ELSE 0 END AS yx, (3 - xz) % 3 + CASE WHEN xz = 3 THEN 3 ELSE 0 END AS zx, (3 - yz) % 3 + CASE WHEN yz = 3 THEN 3 ELSE 0 END AS zy FROM g) SELECT CAST(least(xy * 16 + xz * 4 + yz, xz * 16 + xy * 4 + zy, yx * 16 + yz * 4 + xz, yz * 16 + yx * 4 + zx, zx * 16 + zy * 4 + xy, zy * 16 + zx * 4 + yx) AS INTEGER) AS code, count(*) AS n FROM h GROUP BY 1")
def census3_part_flow(spark, sf):
    return stats.census3(target(spark, sf, "part_flow"))


def _extracted(spark, sf, density: str, targets=("supplier_echo", "part_flow", "user_relay", "commerce")) -> DataFrame:
    """The pattern sets: all sizes and twenty draws of a density, from a target of each collection."""
    out = None
    for name in targets:
        made = workloads.on_instances("sets", [written(spark, sf, name, degrees=False)], lambda csr, p, _: [(len(p.edges), p.size, p.components())], workloads.INSTANCE + ", got int, vertices int, components int", densities=(density,), draws=range(1, 21))
        one = made.groupBy(F.lit(name).alias("target"), "edges").agg(F.count("*").alias("patterns"), F.min("got").alias("least_edges"), F.min("vertices").alias("least_vertices"), F.max("vertices").alias("most_vertices"), F.max("components").alias("components"))
        out = one if out is None else out.unionByName(one)
    return out


for _d in workloads.DENSITIES:
    _add(f"extract_patterns_{_d}", lambda spark, sf, d=_d: _extracted(spark, sf, d))

# Twenty patterns of each size, connected, with all their edges. Commerce is no part of the result, so that its arrays aren't made.
_SETS_OF = ("supplier_echo", "part_flow", "user_relay")
_add("extracted_sets", lambda spark, sf: _extracted(spark, sf, "dense", _SETS_OF).select("target", "edges", "patterns", "least_edges", "components"), values("target, edges, patterns, least_edges, components", [(t, n, 20, n, 1) for t in _SETS_OF for n in workloads.EDGES]))

# --- relational operators around a search --------------------------------------------------------------------------------

E = graph_sql("commerce")


@registered(E + " SELECT elabel, count(*) AS n, CAST(grouping(elabel) AS INTEGER) AS g FROM e GROUP BY ROLLUP (elabel)")
def rollup_edges(spark, sf):
    return target(spark, sf, "commerce").edges.rollup("elabel").agg(F.count("*").alias("n"), F.grouping("elabel").cast("int").alias("g"))


@registered(E + " SELECT a.vlabel AS src_label, b.vlabel AS dst_label, count(*) AS n FROM e JOIN v a ON a.vid = src JOIN v b ON b.vid = dst GROUP BY CUBE (a.vlabel, b.vlabel)")
def cube_labels(spark, sf):
    t = target(spark, sf, "commerce")
    v = t.vertices
    rows = t.edges.join(v.select(F.col("vid").alias("src"), F.col("vlabel").alias("src_label")), "src").join(v.select(F.col("vid").alias("dst"), F.col("vlabel").alias("dst_label")), "dst")
    return rows.cube("src_label", "dst_label").agg(F.count("*").alias("n"))


@registered(graph_sql("user_relay") + " SELECT vlabel, elabel, count(*) AS n FROM e JOIN v ON vid = src GROUP BY GROUPING SETS ((vlabel), (elabel), ())")
def grouping_sets_relay(spark, sf):
    t = target(spark, sf, "user_relay")
    return t.edges.join(t.vertices, t.edges["src"] == t.vertices["vid"]).groupingSets([["vlabel"], ["elabel"], []], "vlabel", "elabel").agg(F.count("*").alias("n"))


@registered(graph_sql("supplier_echo") + " SELECT src, count(*) FILTER (elabel = '0') AS lag0, count(*) FILTER (elabel = '1') AS lag1 FROM e GROUP BY 1")
def pivot_lag(spark, sf):
    p = target(spark, sf, "supplier_echo").edges.groupBy("src").pivot("elabel", ["0", "1"]).count()
    return p.select("src", F.coalesce("0", F.lit(0)).alias("lag0"), F.coalesce("1", F.lit(0)).alias("lag1"))


@registered(graph_sql("supplier_echo") + _DEGREES + " SELECT vid, vlabel, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER (PARTITION BY vlabel ORDER BY indeg + outdeg DESC) AS INTEGER) AS rk, CAST(dense_rank() OVER (PARTITION BY vlabel ORDER BY indeg + outdeg DESC) AS INTEGER) AS dr, lag(vid) OVER w AS before, lead(vid) OVER w AS after, first_value(vid) OVER w AS top FROM d WINDOW w AS (PARTITION BY vlabel ORDER BY indeg + outdeg DESC, vid)")
def window_rank_hubs(spark, sf):
    d = target(spark, sf, "supplier_echo").degrees().withColumn("deg", F.col("indeg") + F.col("outdeg"))
    w, r = Window.partitionBy("vlabel").orderBy(F.desc("deg"), "vid"), Window.partitionBy("vlabel").orderBy(F.desc("deg"))
    return d.select("vid", "vlabel", F.row_number().over(w).alias("rn"), F.rank().over(r).alias("rk"), F.dense_rank().over(r).alias("dr"), F.lag("vid").over(w).alias("before"), F.lead("vid").over(w).alias("after"), F.first("vid").over(w).alias("top"))


@registered(_ECHO_TREE + ", f AS (SELECT 0 AS depth, (SELECT count(*) FROM d) AS pairs UNION ALL SELECT 1, (SELECT count(*) FROM n1) UNION ALL SELECT 2, (SELECT count(*) FROM n2)) SELECT depth, pairs, CAST(sum(pairs) OVER (ORDER BY depth) AS BIGINT) AS upto FROM f")
def window_cum_pairs(spark, sf):
    f = measures.funnel(written(spark, sf, "supplier_echo"), C["P1"], "ord")
    return f.select("depth", "pairs", F.sum("pairs").over(Window.orderBy("depth")).alias("upto"))


_add("ntile_deal", lambda spark, sf: balance.deal(target(spark, sf, "supplier_echo").vertices.select("vid"), 7), "SELECT s_suppkey AS vid, CAST(ntile(7) OVER (ORDER BY s_suppkey) - 1 AS INTEGER) AS worker FROM supplier")
_add("roundrobin_deal", lambda spark, sf: balance.deal(target(spark, sf, "supplier_echo").vertices.select("vid"), 7, "roundrobin"), "SELECT s_suppkey AS vid, CAST((row_number() OVER (ORDER BY s_suppkey) - 1) % 7 AS INTEGER) AS worker FROM supplier")


@registered(graph_sql("supplier_echo") + " SELECT prefix_id, 1 AS pos, grp, list_sort(list(vt)) AS vts FROM (SELECT src AS prefix_id, dst AS vt, (row_number() OVER (PARTITION BY src ORDER BY dst) - 1) // 4 AS grp FROM e) q GROUP BY 1, 2, 3")
def task_groups_echo(spark, sf):
    t = target(spark, sf, "supplier_echo").edges.select(F.col("src").alias("prefix_id"), F.lit(1).alias("pos"), F.col("dst").alias("vt"))
    return balance.groups(t, 4)


@registered("SELECT event_id, ne AS next_event_id FROM (SELECT event_id, ts, lead(event_id) OVER w AS ne, lead(ts) OVER w AS nts FROM events WINDOW w AS (ORDER BY ts, event_id)) q WHERE nts <= ts + INTERVAL 10 MINUTE")
def asof_relay(spark, sf):
    events = tables.read(spark, sf, "events").select("event_id", "ts")
    return tables.next_within(events, ["ts", "event_id"], "ts", 600, ["event_id"]).select("event_id", "next_event_id")


@registered("SELECT x.l_suppkey AS a, y.l_suppkey AS b, count(*) AS n FROM (SELECT DISTINCT l_partkey, l_suppkey, l_shipdate FROM lineitem) x JOIN (SELECT DISTINCT l_partkey, l_suppkey, l_shipdate FROM lineitem) y ON x.l_partkey = y.l_partkey AND y.l_shipdate BETWEEN x.l_shipdate AND x.l_shipdate + INTERVAL 3 DAY GROUP BY 1, 2")
def range_lag_join(spark, sf):
    line = tables.read(spark, sf, "lineitem").select("l_partkey", "l_suppkey", F.to_date("l_shipdate").alias("day")).distinct()
    other = line.select("l_partkey", F.col("l_suppkey").alias("b"), F.col("day").alias("then"))
    return tables.range_join(line.withColumnRenamed("l_suppkey", "a"), other, ["l_partkey"], "day", "then", 3).groupBy("a", "b").agg(F.count("*").alias("n"))


_R = graph_sql("supplier_echo")


@registered(_R + " SELECT e.src, e.dst, e.elabel, a.vlabel AS src_label, b.vlabel AS dst_label FROM e JOIN v a ON a.vid = e.src JOIN v b ON b.vid = e.dst")
def edge_store_bucketed(spark, sf):
    """The edges by way of a store that is bucketed by their sources."""
    by_src, _ = io.write_edge_store(written(spark, sf, "supplier_echo"), "echo_store", 4)
    return spark.table(by_src).select("src", "dst", "elabel", "src_label", "dst_label")


_add("semi_edges", lambda spark, sf: (lambda t: t.edges.join(t.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")), ["src", "dst"], "left_semi").select("src", "dst"))(written(spark, sf, "supplier_echo")), _R + " SELECT src, dst FROM e WHERE EXISTS (SELECT 1 FROM e x WHERE x.src = e.dst AND x.dst = e.src)")
_add("anti_isolated", lambda spark, sf: (lambda t: t.vertices.join(t.edges.select(F.col("src").alias("vid")), "vid", "left_anti").select("vid"))(target(spark, sf, "part_flow")), graph_sql("part_flow") + " SELECT vid FROM v WHERE NOT EXISTS (SELECT 1 FROM e WHERE src = vid)")
_add("left_outer_degree", lambda spark, sf: target(spark, sf, "turn_chain").degrees().groupBy("indeg", "outdeg").agg(F.count("*").alias("n")), graph_sql("turn_chain") + _DEGREES + " SELECT CAST(indeg AS INTEGER) AS indeg, CAST(outdeg AS INTEGER) AS outdeg, count(*) AS n FROM d GROUP BY 1, 2")
_both = lambda spark, sf: (lambda e: (e.filter("elabel = '0'").select("src"), e.filter("elabel = '1'").select("src")))(written(spark, sf, "supplier_echo").edges)
_add("set_union_edges", lambda spark, sf: (lambda a, b: a.union(b).distinct())(*_both(spark, sf)), _R + " SELECT src FROM e WHERE elabel = '0' UNION SELECT src FROM e WHERE elabel = '1'")
_add("set_intersect_edges", lambda spark, sf: (lambda a, b: a.intersect(b))(*_both(spark, sf)), _R + " SELECT src FROM e WHERE elabel = '0' INTERSECT SELECT src FROM e WHERE elabel = '1'")
_add("set_except_edges", lambda spark, sf: (lambda a, b: a.exceptAll(b))(*_both(spark, sf)), _R + " SELECT src FROM e WHERE elabel = '0' EXCEPT ALL SELECT src FROM e WHERE elabel = '1'")


@registered("SELECT event_type, CAST(props->>'k' AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1, 2")
def json_props_labels(spark, sf):
    e = tables.read(spark, sf, "events")
    return e.select("event_type", F.from_json("props", "k int").alias("p")).groupBy("event_type", F.col("p.k").alias("k")).agg(F.count("*").alias("n"))


@registered("SELECT regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, lower(split_part(regexp_extract(url, '^[a-z]+://([^/?#]+)', 1), '.', 1)) AS first, count(*) AS n FROM pages GROUP BY 1, 2")
def string_url_hosts(spark, sf):
    p = tables.read(spark, sf, "pages").select(F.parse_url("url", F.lit("HOST")).alias("host"))
    return p.groupBy("host", F.lower(F.split_part("host", F.lit("."), F.lit(1))).alias("first")).agg(F.count("*").alias("n"))


@registered(_R + " SELECT src, list_sort(list(dst))[1:3] AS few, count(*) AS n, CAST(sum(dst % 10) AS BIGINT) AS s FROM e GROUP BY src")
def array_match_ops(spark, sf):
    g = target(spark, sf, "supplier_echo").edges.groupBy("src").agg(F.array_sort(F.collect_list("dst")).alias("m"))
    return g.select("src", F.slice("m", 1, 3).alias("few"), F.size("m").cast("long").alias("n"), F.aggregate(F.transform("m", lambda x: x % 10), F.lit(0).cast("long"), lambda a, x: a + x).alias("s"))


@registered("SELECT CAST(date_trunc('month', o_orderdate) AS DATE) AS month, count(*) AS n, CAST(max(date_diff('day', DATE '1990-01-01', CAST(o_orderdate AS DATE))) AS INTEGER) AS last FROM orders GROUP BY 1")
def date_bucket_orders(spark, sf):
    o = tables.read(spark, sf, "orders")
    return o.groupBy(F.to_date(F.date_trunc("month", "o_orderdate")).alias("month")).agg(F.count("*").alias("n"), F.max(F.datediff(F.to_date("o_orderdate"), F.lit("1990-01-01").cast("date"))).alias("last"))


@registered(_ROUNDS + ", m AS (SELECT vid, sum(1 << pv) AS mask FROM d1 GROUP BY 1) SELECT vid, CAST(mask AS BIGINT) AS mask, CAST(bit_count(CAST(mask AS BIGINT)) AS INTEGER) AS bits FROM m")
def math_bitmask(spark, sf):
    found, _ = domains.prepare(written(spark, sf, "supplier_echo"), C["P3"], "dom", 1, stop_early=False)
    return found.select("vid", F.col("mask0").alias("mask"), udf.mask_size("mask0").alias("bits"))


@registered("SELECT l_suppkey, round(exp(avg(ln((1 + l_tax) / (1 - l_discount)))), 6) AS gmean FROM lineitem GROUP BY 1")
def pandas_udaf_gmean(spark, sf):
    """Per supplier, the geometric mean of its lines' tax over discount."""
    line = tables.read(spark, sf, "lineitem").select("l_suppkey", ((1 + F.col("l_tax")) / (1 - F.col("l_discount"))).alias("ratio"))
    return line.groupBy("l_suppkey").agg(F.round(udf.geometric_mean("ratio"), 6).alias("gmean"))


@registered(_R + " " + sql_join(C["P1"]))
def udtf_match_pattern(spark, sf):
    udf.register(spark, written(spark, sf, "supplier_echo"), "echo")
    return spark.sql("SELECT m[0] AS m0, m[1] AS m1, m[2] AS m2 FROM match_pattern('a->b; b->c; c->a')")


# --- streams -------------------------------------------------------------------------------------------------------------


def _stream(spark, sf) -> DataFrame:
    path = f"{sf}/events.parque[t]"  # a glob: file streams take a folder or a pattern, and the table may be one file
    return streaming.events_stream(spark, path, spark.read.parquet(path).schema)


_EPOCH = "CAST(floor(epoch(ts) / {n}) * {n} AS BIGINT)"
_add("stream_tumbling_events", lambda spark, sf: streaming.drained(streaming.windowed_counts(_stream(spark, sf), "1 hour"), "tumbling"), f"SELECT {_EPOCH.format(n=3600)} AS start_s, event_type, count(*) AS n FROM events GROUP BY 1, 2")
_add("stream_sliding_events", lambda spark, sf: streaming.drained(streaming.windowed_counts(_stream(spark, sf), "1 hour", "30 minutes"), "sliding"), f"SELECT start_s, event_type, count(*) AS n FROM (SELECT {_EPOCH.format(n=1800)} - 1800 * k AS start_s, event_type FROM events, (VALUES (0), (1)) q(k)) q GROUP BY 1, 2")
_add("stream_session_users", lambda spark, sf: streaming.drained(streaming.sessions(_stream(spark, sf), "6 hours"), "sessions"), "SELECT CAST(floor(epoch(min(ts))) AS BIGINT) AS start_s, user_id, count(*) AS n FROM (SELECT user_id, ts, sum(CASE WHEN ts - before < INTERVAL 6 HOUR THEN 0 ELSE 1 END) OVER (PARTITION BY user_id ORDER BY ts) AS s FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS before FROM events) a) b GROUP BY user_id, s")
_add("stream_static_labels", lambda spark, sf: streaming.drained(streaming.with_labels(_stream(spark, sf), target(spark, sf, "user_relay").vertices).groupBy("vlabel", "event_type").agg(F.count("*").alias("n")), "labelled"), graph_sql("user_relay") + " SELECT vlabel, event_type, count(*) AS n FROM events JOIN v ON vid = user_id GROUP BY 1, 2")
_add("stream_two_steps", lambda spark, sf: streaming.drained(streaming.two_steps(_stream(spark, sf), 300), "steps", "append").groupBy("src", "dst", "elabel").agg(F.count("*").alias("n")), "SELECT a.user_id AS src, b.user_id AS dst, a.event_type AS elabel, count(*) AS n FROM events a JOIN events b ON a.event_type = b.event_type AND a.user_id <> b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 300 SECOND GROUP BY 1, 2, 3")


@registered(_R + " " + sql_join(C["P1"]))
def stream_delta_cycles(spark, sf):
    """Edges arrive in three batches; the new matches of all batches together are the matches of the whole."""
    t = written(spark, sf, "supplier_echo")
    part = F.pmod(F.xxhash64("src", "dst"), F.lit(3))
    found, old = None, t.edges.limit(0)
    for k in range(3):
        new = t.edges.filter(part == k)
        more = streaming.delta_matches(t.vertices, old, new, C["P1"])
        found = more if found is None else found.unionByName(more)
        old = t.edges.filter(part <= k)
    return found


# --- experiments ---------------------------------------------------------------------------------------------------------

DOMAIN_METHODS = ("dom", "dom_s", "dom_sf")
#: Per collection: the methods that are compared, the first being the baseline, and the sizes of its pattern sets.
_SETS = {"dense_many_labels": (DOMAIN_METHODS, workloads.EDGES), "denser_few_labels": (DOMAIN_METHODS, workloads.EDGES), "sparse": (("ord", *DOMAIN_METHODS), workloads.EDGES[:-1])}
#: Pairs after which a search counts as unfinished.
BUDGET = 3_000_000
#: Nodes of a search tree whose simulation counts as short, per collection. None: trees of any size are simulated.
GRID_TREE = {"dense_many_labels": None, "denser_few_labels": 20_000, "sparse": 5_000}
#: Nodes of a search tree that is simulated.
TREE = 120_000


def _targets(spark, sf, collection: str) -> list[TargetGraph]:
    return [written(spark, sf, n, degrees=False) for n in workloads.COLLECTIONS[collection]]


def _searches(spark, sf, collection: str) -> DataFrame:
    """Every size, density and draw of the collection's pattern sets by every method."""
    methods, sizes = _SETS[collection]
    return materialise(workloads.searches(collection, _targets(spark, sf, collection), methods, BUDGET, edges=sizes, draws=(1, 2)), "searches")


for _c, (_methods, _) in _SETS.items():
    _add(f"variants_{_c}", lambda spark, sf, c=_c, b=_methods[0]: workloads.space_summary(_searches(spark, sf, c), b))
    _add(f"long_sample_{_c}", lambda spark, sf, c=_c, b=_methods[0]: workloads.long_sample(_searches(spark, sf, c), b))
    _add(f"unfinished_{_c}", lambda spark, sf, c=_c: workloads.unfinished(_searches(spark, sf, c)))


def _simulated(spark, sf, collection: str, methods) -> DataFrame:
    return materialise(workloads.simulated(collection, _targets(spark, sf, collection), methods, max_nodes=TREE, edges=_SETS[collection][1]), "simulated")


# Up to 16 workers are simulated, in ticks: over one worker of the same method, and over the baseline program run alone.
for _c, _new, _old in (("dense_many_labels", "dom_sf", "dom"), ("denser_few_labels", "dom_sf", "dom"), ("sparse", "ord", "ord")):
    _add(f"speedup_over_self_{_c}", lambda spark, sf, c=_c, m=_new: workloads.speedup_table(_simulated(spark, sf, c, (m,))))
    if _new != _old:
        _add(f"speedup_over_published_{_c}", lambda spark, sf, c=_c, m=_new, o=_old: workloads.speedup_table(_simulated(spark, sf, c, (m, o)), o).filter(F.col("method") == m))


@registered()
def stealing_on_off(spark, sf):
    """Sixteen workers with and without stealing, in groups of one and four, on patterns with large search trees. Trees of any size are simulated."""
    runs = workloads.simulated("dense_many_labels", _targets(spark, sf, "dense_many_labels"), ("ord",), (16,), (1, 4), range(3), (True, False), None, edges=(16, 32), densities=("dense", "sparse"), draws=(1, 2))
    return workloads.group_table(runs)


for _c in workloads.COLLECTIONS:
    # Group size by workers, fifteen draws of the victims, on small patterns; of two collections only those with short trees.
    _add(f"steal_sim_grid_{_c}", lambda spark, sf, c=_c: workloads.group_table(workloads.simulated(c, _targets(spark, sf, c), ("dom_sf",), (2, 4, 8, 16), (1, 2, 4, 8, 16), range(15), (True, False), GRID_TREE[c], edges=(4, 8) if c != "denser_few_labels" else (2, 3), draws=(1, 2) if c != "denser_few_labels" else (1,))))


@registered()
def large_branches_four_targets(spark, sf):
    """How wide the search trees of patterns taken from four targets are, by depth."""
    out = None
    for name, density, n in (("supplier_echo", "dense", 16), ("part_flow", "semi", 16), ("user_relay", "dense", 4), ("turn_chain", "sparse", 4)):
        t = target(spark, sf, name)
        p = next(p for k in range(workloads.TRIES) if len((p := patterns.extract(t.csr(), n, density, 1 + k * workloads.TRY)).edges) == n)
        one = measures.large_branches(materialise(tree_of(spark, t, p, name), "tree"), 0.05).select(F.lit(name).alias("target"), "depth", "branches")
        out = one if out is None else out.unionByName(one)
    return out


_ORDERS = ("constraint_first", "by_degree", "identity", "random", "state_space")
_add("orders_and_state_space", lambda spark, sf: workloads.order_ablation(target(spark, sf, "supplier_echo"), C["P8"], 10**9))
_add("orders_matches", lambda spark, sf: workloads.order_ablation(target(spark, sf, "supplier_echo"), C["P8"], 10**9).select("order", "matches"), graph_sql("supplier_echo") + f" SELECT \"order\", n AS matches FROM ({sql_join(C['P8'], count=True)}) c, ({values(chr(34) + 'order' + chr(34), [(x,) for x in _ORDERS])}) o")

#: Patterns that were taken from the targets, dense, semi-dense and sparse.
_TAKEN = {
    "supplier_echo": ("a:24->b:11; b->a; b->c:17; c->b; a->d:17; d->c", "a:24->b:11; b->a; b->c:17; c->b; a->d:17; d->c; e:14->c; e->a", "a:14->b:1; a->c:9; b->d:6; e:7->d; e->f:0"),
    "part_flow": ("a:Brand#21->b:Brand#17; c:Brand#16->b; a->d:Brand#19; e:Brand#15->c; e->f:Brand#4", "a:Brand#21->b:Brand#17; c:Brand#16->b; a->d:Brand#19; e:Brand#15->c; e->f:Brand#4; e->g:Brand#21"),
    "user_relay": ("a:click->b:purchase; b->c:error; a->c; a->d:view; d->a; c->d", "a:click->b:purchase; b->c:error; a->d:view"),
    "turn_chain": ("a:user->b:assistant; c:assistant->a; b->d:user; e:user->c", "a:user->b:assistant; b->c:user; d:assistant->a; e:user->d; f:assistant->e"),
}
_METHODS = ("ord", "dom", "dom_s", "dom_f", "dom_sf")


def _matches(where: TargetGraph, pattern: PatternGraph, method: str, how: dict) -> int:
    """Matches by the array engine asked for, or by joins where the target's arrays are too large."""
    try:
        return engines.count(where, pattern, method, **how)
    except TargetTooLarge:
        return engines.count(where, pattern, method, "join")


def _taken(spark, sf, name: str, workers=(None,)) -> DataFrame:
    rows = []
    where = written(spark, sf, name)
    for k, text in enumerate(_TAKEN[name]):
        for m in _METHODS:
            for w in workers:
                how = {"engine": "dfs"} if w is None else {"engine": "rounds", "workers": w, "budget": 100_000}
                rows.append((f"{name}-{k}", m, w, _matches(where, PatternGraph.parse(text), m, how)))
    return spark.createDataFrame(rows, "pattern string, method string, workers int, matches long")


def _taken_sql(name: str, keys: str) -> str:
    counts = " UNION ALL ".join(f"SELECT '{name}-{k}' AS pattern, n AS matches FROM ({sql_join(PatternGraph.parse(x), simple=name != 'user_relay', count=True)}) q{k}" for k, x in enumerate(_TAKEN[name]))
    return graph_sql(name) + f" SELECT * FROM ({counts}) p, ({keys}) m"


for _name in _TAKEN:
    _add(f"taken_patterns_{_name}", lambda spark, sf, n=_name: _taken(spark, sf, n).drop("workers"), _taken_sql(_name, values("method", [(m,) for m in _METHODS])))
_add("collection_runs", lambda spark, sf: _taken(spark, sf, "supplier_echo", (1, 4)), _taken_sql("supplier_echo", values("method, workers", [(m, w) for m in _METHODS for w in (1, 4)])))

#: Fixed value: a pattern of 20 edges on which singletons' targets leave other domains.
PRUNED = "a:L26->b:L20; a->c:L20; d:L20->a; d->e:L22; e->f:L24; g:L4->e; h:L7->g; i:L0->g; j:L22->i; g->k:L5; j->l:L5; m:L15->l; l->n:L5; n->o:L4; p:L26->l; n->q:L15; r:L22->q; s:L22->m; m->t:L2; j->u:L20"


@registered(graph_sql("uniform_dense") + f" SELECT method, pairs, n AS matches FROM ({values('method, pairs', [('dom', 3635), ('dom_s', 1426), ('dom_sf', 1006)])}) p, ({sql_join(PatternGraph.parse(PRUNED), count=True)}) c")
def forward_checking_prunes(spark, sf):
    """A seeded target with uniform labels, on which each step from plain domains to forward checking saves pairs. The pairs are those of a plain walk in the tests."""
    where = tables.uniform_dense(spark, sf).written()
    rows = [(m, *engines.counts(where, PatternGraph.parse(PRUNED), m, "dfs").select("pairs", "matches").first()) for m in DOMAIN_METHODS]
    return spark.createDataFrame(rows, "method string, pairs long, matches long")


_CYCLE_PAIRS = _DEGREES + _CYCLE_TREE + ", ok AS (SELECT vid FROM d WHERE indeg >= 1 AND outdeg >= 1) SELECT {0} (SELECT count(*) FROM t1 WHERE a IN (SELECT vid FROM ok)) + (SELECT count(*) FROM p2 WHERE a IN (SELECT vid FROM ok) AND b IN (SELECT vid FROM ok)) AS pairs"


def _skew(spark, sf) -> DataFrame:
    where, joined, out = written(spark, sf, "part_flow"), None, []
    for name, how in (("roots", {"engine": "dfs"}), ("rounds", {"engine": "rounds", "budget": 20_000})):
        ready = engines.prepare(where, C["P1"])
        try:
            engines.run(ready, count_only=True, **how)
        except TargetTooLarge:  # the joins' partitions take the place of the kernel's tasks, and their levels that of rounds
            joined = joined or expand.pairs_by_partition(where, ready.plan)
            ready.stats |= {"tagged": joined, "rounds": len(ready.plan.steps) - 1}
        row = measures.partition_skew(ready.stats["tagged"]).first()
        out.append((name, row["pairs"], ready.stats["rounds"]))
    return spark.createDataFrame(out, "deal string, pairs long, rounds int")


# Pairs per Spark task add up to the search's, from roots alone and after rounds of dealing again.
_add("partition_skew_cycle3", lambda spark, sf: _skew(spark, sf).select("deal", "pairs"), graph_sql("part_flow") + _CYCLE_PAIRS.format("unnest(['roots', 'rounds']) AS deal,"))


# --- more operators ------------------------------------------------------------------------------------------------------


@registered(_R + " SELECT v.vid, (SELECT max(dst) FROM e WHERE src = v.vid) AS last, (SELECT count(*) FROM e WHERE src = v.vid) AS n FROM v")
def lateral_last_neighbour(spark, sf):
    t = written(spark, sf, "supplier_echo")
    t.vertices.createOrReplaceTempView("lat_v")
    t.edges.createOrReplaceTempView("lat_e")
    return spark.sql("SELECT vid, last, n FROM lat_v, LATERAL (SELECT max(dst) AS last, count(*) AS n FROM lat_e WHERE src = vid)")


@registered(graph_sql("turn_chain").replace("WITH ", "WITH RECURSIVE ", 1) + ", r(root, vid, hops) AS (SELECT vid, vid, 0 FROM v WHERE vid NOT IN (SELECT dst FROM e) UNION ALL SELECT root, dst, hops + 1 FROM r JOIN e ON src = vid) SELECT root, count(*) AS reached, CAST(max(hops) AS INTEGER) AS hops FROM r GROUP BY 1")
def recursive_reach(spark, sf):
    t = written(spark, sf, "turn_chain")
    t.vertices.createOrReplaceTempView("rec_v")
    t.edges.createOrReplaceTempView("rec_e")
    return spark.sql("WITH RECURSIVE r(root, vid, hops) AS (SELECT vid, vid, 0 FROM rec_v WHERE vid NOT IN (SELECT dst FROM rec_e) UNION ALL SELECT root, dst, hops + 1 FROM r JOIN rec_e ON src = vid) SELECT root, count(*) AS reached, max(hops) AS hops FROM r GROUP BY 1")


@registered(graph_sql("part_flow") + _DEGREES + " SELECT vlabel, quantile_cont(indeg + outdeg, 0.5) AS median, CAST(max(vid) AS BIGINT) AS top, max_by(vid, (indeg + outdeg) * 1000000 - vid) AS hub, count(*) FILTER (indeg > outdeg) AS sinks FROM d GROUP BY 1 HAVING count(*) > 1")
def degree_quantiles(spark, sf):
    d = target(spark, sf, "part_flow").degrees().withColumn("deg", F.col("indeg") + F.col("outdeg"))
    return d.groupBy("vlabel").agg(F.percentile("deg", 0.5).alias("median"), F.max("vid").alias("top"), F.max_by("vid", F.col("deg") * 1000000 - F.col("vid")).alias("hub"), F.count_if(F.col("indeg") > F.col("outdeg")).alias("sinks"), F.count("*").alias("c")).filter("c > 1").drop("c")


@registered(_R + " SELECT src, dst FROM e WHERE src BETWEEN 2 AND 60 AND dst IN (1, 2, 3, 4, 5) AND elabel LIKE '0%' ORDER BY src, dst LIMIT 10 OFFSET 2")
def filtered_edges(spark, sf):
    e = target(spark, sf, "supplier_echo").edges
    return e.filter(F.col("src").between(2, 60) & F.col("dst").isin(1, 2, 3, 4, 5) & F.col("elabel").like("0%")).orderBy("src", "dst").offset(2).limit(10).select("src", "dst")


@registered("SELECT user_id, event_type, count(*) AS n FROM (SELECT DISTINCT user_id, event_type, CAST(floor(epoch(ts) / 86400) AS BIGINT) AS day FROM events) q GROUP BY 1, 2")
def stream_distinct_days(spark, sf):
    """Stateful deduplication: a user's kind of event counts once a day."""
    days = _stream(spark, sf).withWatermark("ts", "10 minutes").withColumn("day", F.floor(F.unix_seconds("ts") / 86400)).dropDuplicates(["user_id", "event_type", "day"])
    return streaming.drained(days.select("user_id", "event_type", "day"), "days", "append").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))


@registered("SELECT user_id, count(*) AS n, count(DISTINCT event_type) AS kinds FROM events GROUP BY 1")
def stream_user_state(spark, sf):
    """Arbitrary state per user, kept by a Python function over Arrow batches."""
    return streaming.drained(streaming.user_state(_stream(spark, sf)), "users", "update").groupBy("user_id").agg(F.max("n").alias("n"), F.max("kinds").alias("kinds"))


@registered("SELECT count(*) - 1 AS kept FROM events")
def stream_late_drop(spark, sf):
    """A row from before the watermark, in a later file, is dropped."""
    return streaming.late_drop(spark, tables.read(spark, sf, "events"))


@registered("SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def stream_restarted(spark, sf):
    """Counts of a stream that stops after half of the events and is taken up again from its checkpoint."""
    return streaming.restarted(tables.read(spark, sf, "events").select("event_id", "event_type"))


@registered("SELECT 'random' AS target, 200 AS vertices, true AS enough")
def random_target(spark, sf):
    """A random graph made from ranges of numbers, seeded."""
    n = 200
    v = spark.range(n).select(F.col("id").alias("vid"), F.concat(F.lit("L"), F.pmod(F.xxhash64("id"), F.lit(4))).alias("vlabel"))
    e = spark.range(n * 10).select(F.pmod(F.xxhash64("id", F.lit(1)), F.lit(n)).alias("src"), F.pmod(F.xxhash64("id", F.lit(2)), F.lit(n)).alias("dst"), F.lit(None).cast("string").alias("elabel"))
    t = TargetGraph.of(v, e, name="random")
    return t.vertices.agg(F.lit("random").alias("target"), F.count("*").cast("int").alias("vertices")).crossJoin(t.edges.agg((F.count("*") > 1800).alias("enough")))


@functools.cache
def names() -> tuple[str, ...]:
    return tuple(QUERIES)
