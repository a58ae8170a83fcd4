"""Searches against permutations, over all methods and engines."""

import itertools

import numpy as np
import pytest

from subgraph_spark import catalog
from subgraph_spark.model import PatternGraph, TargetGraph, TargetTooLarge, edges_between, random_graph
from subgraph_spark.operators import baselines, domains, engines, expand, halves, measures, patterns, steal_sim
from subgraph_spark.operators.dfs import Counters, Kernel, search_tree
from subgraph_spark.plans.search_plan import METHODS, build

P = PatternGraph.parse
V, E = "vid long, vlabel string", "src long, dst long, elabel string"


def made(spark, vertices, edges, simple=False):
    return TargetGraph.of(spark.createDataFrame(vertices, V), spark.createDataFrame(edges, E), simple)


def brute(vertices, edges, p, induced=False):
    labels, by = dict(vertices), edges_between(edges)
    have = {(s, d) for s, d, _ in p.edges}
    out = set()
    for image in itertools.permutations(labels, p.size):
        ok = all(x is None or labels[image[i]] == x for i, x in enumerate(p.labels))
        ok = ok and all((image[s], image[d]) in by and (x is None or x in by[image[s], image[d]]) for s, d, x in p.edges)
        if ok and induced:
            ok = all((image[a], image[b]) not in by for a in range(p.size) for b in range(p.size) if (a, b) not in have)
        if ok:
            out.add(image)
    return out


SHAPES = [P("a->b; b->c; c->a"), P("a:L0->b; b-[e1]->c; a->c"), P("a->b; c->d:L1"), P("a->a; a->b"), P("a->b; b->a; a->c:L0"), P("a")]


@pytest.mark.parametrize("seed", range(2))
@pytest.mark.parametrize("p", SHAPES, ids=range(len(SHAPES)))
def test_kernel_against_permutations(spark, seed, p):
    vertices, edges = random_graph(7, 22, 2, seed)
    t = made(spark, vertices, edges)
    expected = brute(vertices, edges, p)
    for induced in (False, True):
        kernel, c = Kernel(t.csr(), build(p), None, induced), Counters()
        place = np.argsort(kernel.plan.order)
        got = [tuple(x) for _, b in kernel.run(kernel.seeds(None, c), c) for x in t.csr().vids[b][:, place].tolist()]
        assert len(got) == len(set(got)) and set(got) == (brute(vertices, edges, p, True) if induced else expected)
    pairs, found = baselines.state_space(t.csr(), p)
    assert set(found) == expected and pairs >= len(found)


@pytest.mark.parametrize("method", METHODS)
@pytest.mark.parametrize("engine", ["join", "dfs", "hybrid", "rounds"])
def test_methods_and_engines_agree(spark, method, engine):
    vertices, edges = random_graph(8, 26, 2, 3)
    t = made(spark, vertices, edges).written()
    for p in (SHAPES[1], SHAPES[4]):
        how = {"budget": 7, "group_size": 2} if engine == "rounds" else {}
        got = [tuple(r) for r in engines.enumerate(t, p, method, engine, **how).collect()]
        assert len(got) == len(set(got)) and set(got) == brute(vertices, edges, p)


def test_pairs_do_not_depend_on_tasks_groups_or_budgets(spark):
    t = made(spark, *random_graph(12, 60, 2, 5)).written()
    p = SHAPES[0]
    counts = {tuple(engines.counts(t, p, "ord", e, **how).select("pairs", "matches").first()) for e, how in (("dfs", {"workers": 1}), ("dfs", {}), ("rounds", {"budget": 5, "group_size": 1}), ("rounds", {"budget": 40, "group_size": 8}), ("hybrid", {}))}
    assert len(counts) == 1
    funnel = measures.funnel(t, p).collect()
    assert sum(r.pairs for r in funnel) == counts.pop()[0]
    assert all(r.pairs >= r.after_unused >= r.after_label_or_domain >= r.after_degree >= r.after_edges for r in funnel)


def test_forward_checking(spark):
    p = PatternGraph((None,) * 5)

    def run(sets):
        rows = [(v, sum(1 << i for i, s in enumerate(sets) if v in s)) for v in set().union(*sets)]
        d, sizes = domains.forward_check(spark.createDataFrame(rows, "vid long, mask0 long"), PatternGraph((None,) * len(sets)))
        return sizes.size, {tuple(r) for r in domains.rows(d, PatternGraph((None,) * len(sets))).collect()}

    size, rows = run([{0}, {4}, {0, 3, 7}, {2, 8, 9}, {0, 4, 7}])
    assert size == (1, 1, 1, 3, 1) and rows == {(0, 0), (1, 4), (2, 3), (3, 2), (3, 8), (3, 9), (4, 7)}
    assert run([{1}, {1, 2}, {2, 3}, {3, 4}])[0] == (1, 1, 1, 1)
    assert 0 in run([{5}, {5}, {1, 2}])[0]
    assert p.size == 5


def test_domains_shrink_and_keep_every_match(spark):
    vertices, edges = random_graph(10, 40, 2, 9)
    t, p = made(spark, vertices, edges).written(), SHAPES[1]
    at = [{tuple(r) for r in domains.rows(domains.prepare(t, p, "dom", k)[0], p).collect()} for k in (0, 1, 2, "fixpoint")]
    assert at[0] >= at[1] >= at[2] >= at[3]
    assert all((i, v) in at[3] for m in brute(vertices, edges, p) for i, v in enumerate(m))


def test_more_than_one_mask_word(spark):
    n = 70
    path = [(i, i + 1, None) for i in range(n - 1)]
    t = made(spark, [(i, "x") for i in range(n)], path)
    p = PatternGraph(("x",) * n, tuple(path))
    assert domains.words(p) == 2
    for method in ("ord", "dom_sf"):
        assert engines.counts(t, p, method, "dfs").first()["matches"] == 1


def test_small_cases(spark):
    star = made(spark, [(i, None) for i in range(7)], [(0, i, None) for i in range(1, 7)])
    p = P("c->x; c->y; c->z")
    found = engines.enumerate(star, p, "ord", "dfs")
    assert found.count() == 120 and engines.distinct_subgraphs(found, p).count() == 20 == 120 // p.automorphisms()
    full = made(spark, [(i, None) for i in range(5)], [(a, b, None) for a in range(5) for b in range(5) if a != b])
    assert engines.count(full, SHAPES[0]) == 60
    parallel = made(spark, [(0, "a"), (1, "b")], [(0, 1, "x"), (0, 1, "y")])
    assert engines.enumerate(parallel, P("a->b")).count() == 1 and engines.enumerate(parallel, P("a-[y]->b")).count() == 1
    assert engines.enumerate(parallel, P("a->b; b->c; c->d")).count() == 0
    empty = made(spark, [(0, "a")], [])
    for method in METHODS:
        assert engines.enumerate(empty, P("a->b"), method).count() == 0
    assert engines.enumerate(empty, P("a"), "ord").collect()[0].m0 == 0
    loop = made(spark, [(0, "a"), (1, "a")], [(0, 0, None), (0, 1, None)])
    for method in METHODS:
        assert [r.m0 for r in engines.enumerate(loop, P("a->a"), method).collect()] == [0]
    assert engines.is_isomorphic(full, PatternGraph((None,) * 5, tuple((a, b, None) for a in range(5) for b in range(5) if a != b)))
    assert not engines.is_isomorphic(full, P("a->b"))


def test_guards(spark):
    t = made(spark, [(i, None) for i in range(50)], [(0, 1, None)]).written()
    with pytest.raises(expand.CrossJoinTooLarge):
        engines.enumerate(t, PatternGraph((None, None)), max_cross=100)
    with pytest.raises(TargetTooLarge):
        t.csr(10)
    assert engines.enumerate(t, P("a->b"), "ord", "auto", max_bytes=10).count() == 1
    got = engines.counts(t, PatternGraph((None,) * 3), "ord", "dfs", time_limit_s=0.0).first()
    assert got["timed_out"]


def test_simulator(spark):
    vertices, edges = random_graph(20, 120, 1, 4)
    kernel = Kernel(made(spark, vertices, edges).csr(), build(SHAPES[0]))
    tree = search_tree(kernel)
    args = (tree["parent_id"], tree["depth"], tree["consistent"])
    total = len(tree["node_id"])
    for workers, group in itertools.product((1, 2, 5, 16), (1, 4, 16)):
        for stealing in (True, False):
            got = steal_sim.simulate(*args, workers, group, 1, stealing)
            assert sum(got.states) == total and got.makespan >= total / workers
            if not stealing:
                assert got.steals_ok == 0
            if workers == 1:
                assert got.steals_ok == got.steals_failed == 0
    # One heavy root among light ones: stealing shortens the run and evens out the states.
    parent, depth, good = [-1] * 16, [0] * 16, [True] * 16
    parent += [0] * 200
    depth += [1] * 200
    good += [True] * 200
    for i in range(200):
        parent += [16 + i] * 5
        depth += [2] * 5
        good += [False] * 5
    a = [np.array(x) for x in (parent, depth, good)]
    on, off = steal_sim.simulate(*a, 8, 4, 1), steal_sim.simulate(*a, 8, 4, 1, False)
    # (One victim answers one request a group, so eight workers do not share it evenly.)
    assert on.makespan < off.makespan and on.spread < off.spread and on.steals_ok > 0
    assert steal_sim.simulate(*a, 8, 4, 1, copy="per_task").cells_copied > on.cells_copied
    assert sum(steal_sim.simulate(*a, 8, 4, 1, initiator="sender").states) == len(parent)


@pytest.mark.parametrize("density", ["dense", "semi", "sparse"])
def test_extracted_patterns_match(spark, density):
    t = made(spark, *random_graph(30, 200, 3, 8)).written()
    csr = t.csr()
    for n in (4, 8):
        p = patterns.extract(csr, n, density, 2)
        assert len(p.edges) == n and p.components() == 1
        assert engines.exists(t, p, "dom_sf")
    assert patterns.density_class(patterns.extract(csr, 12, "dense", 2)) > patterns.density_class(patterns.extract(csr, 12, "sparse", 2))


def test_long_tables_with_small_files_are_not_broadcast(spark):
    from subgraph_spark.session import materialise

    before = {k: spark.conf.get(k, None) for k in ("spark.sql.autoBroadcastJoinThreshold", "spark.sql.adaptive.autoBroadcastJoinThreshold")}
    try:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "10m")
        spark.conf.unset("spark.sql.adaptive.autoBroadcastJoinThreshold")
        a, b = (materialise(spark.range(2_000_000).repartition(2)) for _ in range(2))
        plan = a.join(b, "id")._jdf.queryExecution().executedPlan().toString()
        assert "Broadcast" not in plan
        assert spark.conf.get("spark.sql.adaptive.autoBroadcastJoinThreshold") == str(10 << 20)
        few = materialise(spark.range(10))
        assert "Broadcast" in a.join(few, "id")._jdf.queryExecution().executedPlan().toString()
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def test_joins_of_a_domain_method_take_the_cheaper_order(spark):
    """Two groups around two hubs: by the smaller domain first, every a of a hub meets every b of it."""
    rows = [(1 + i % 2, 10 + i, "x") for i in range(60)] + [(1 + i % 2, 100 + i, "y") for i in range(80)] + [(10 + i % 60, 1000 + i, "u") for i in range(300)] + [(100 + i % 80, 1000 + i, "w") for i in range(300)]
    label = lambda v: "h" if v < 3 else "a" if v < 100 else "b" if v < 1000 else "o"
    vertices = [(v, label(v)) for v in sorted({v for e in rows for v in e[:2]})]
    t = TargetGraph.of(spark.createDataFrame(vertices, "vid long, vlabel string"), spark.createDataFrame(rows, "src long, dst long, elabel string")).written()
    p = PatternGraph.parse("o:o; a:a->o; b:b->o; h:h->a; h->b")
    ready = engines.prepare(t, p, "dom_s")
    assert [p.labels[v] for v in ready.plan.order][:2] == ["h", "a"]
    assert engines.run(ready, "join", count_only=True).first()["matches"] == 300
    assert [p.labels[v] for v in ready.plan.order][0] == "o"
    given = engines.prepare(t, p, "dom_s", order=[3, 1, 2, 0])
    assert engines.run(given, "join", count_only=True).first()["matches"] == 300 and given.plan.order == [3, 1, 2, 0]


def test_branches_of_a_search_need_no_bounded_tree(spark, monkeypatch):
    from subgraph_spark import catalog

    vertices, edges = random_graph(14, 60, 2, 3)
    t = made(spark, vertices, edges)
    for text in ("a->b; b->c; c->a", "a:L0->b; b-[e1]->c"):
        plan = build(P(text))
        tree = search_tree(Kernel(t.csr(), plan))
        table = spark.createDataFrame([tuple(map(int, r)) for r in zip(tree["node_id"], tree["parent_id"], tree["depth"])], "node_id long, parent_id long, depth int")
        assert {tuple(r) for r in measures.branches_of_search(t, plan, 0.02).collect()} == {tuple(r) for r in measures.large_branches(table, 0.02).collect()}
    monkeypatch.setattr(catalog, "search_tree", lambda *_: 1 / 0)
    assert len(catalog.QUERIES["large_branches_echo"](spark, "/root/testdata/sf0.001").collect()) == 3


def test_pairs_per_partition_without_arrays(spark, monkeypatch):
    from subgraph_spark import catalog

    sf = "/root/testdata/sf0.001"
    expected = {tuple(r) for r in catalog.QUERIES["partition_skew_cycle3"](spark, sf).collect()}
    monkeypatch.setattr(engines, "allowed_bytes", lambda _: 1)
    assert {tuple(r) for r in catalog.QUERIES["partition_skew_cycle3"](spark, sf).collect()} == expected


def test_taken_patterns_without_arrays(spark, monkeypatch):
    from subgraph_spark import catalog

    monkeypatch.setattr(engines, "allowed_bytes", lambda _: 1)
    monkeypatch.setattr(catalog, "_METHODS", ("ord", "dom_s"))
    found = {}
    for r in catalog.QUERIES["taken_patterns_turn_chain"](spark, "/root/testdata/sf0.001").collect():
        found.setdefault(r.pattern, set()).add(r.matches)
    monkeypatch.undo()
    t = catalog.target(spark, "/root/testdata/sf0.001", "turn_chain")
    csr = t.csr()
    for k, text in enumerate(catalog._TAKEN["turn_chain"]):
        c = Counters()
        kernel = Kernel(csr, build(P(text)))
        list(kernel.run(kernel.seeds(), c))
        assert found[f"turn_chain-{k}"] == {c.matches}


@pytest.mark.parametrize("text", ["a->b; b->c; c->a", "a->b; b->c; c->d; d->a", "b->c:L1; d->a; a:L0->b; c->d", "a->b; b->c; c->d:L1; d->e; e->a"])
def test_halves_of_cycles(spark, text):
    """Mapped and held arrays, blocks that split a root's paths, loops in the target."""
    vertices, edges = random_graph(8, 34, 2, 11)
    t, p = made(spark, vertices, [*edges, (0, 0, "e0"), (3, 3, "e1")]).written(degrees=False), P(text)
    expected = brute(vertices, edges, p)
    for max_bytes, block in ((0, 3), (1 << 30, 1 << 19)):
        got = [tuple(r) for r in halves.search(t, p, [f"m{v}" for v in range(p.size)], 3, max_bytes, block).collect()]
        assert expected and len(got) == len(set(got)) and set(got) == expected
    assert {tuple(r) for r in engines.enumerate(t, p, engine="halves").collect()} == expected
    assert engines.count(t, p, engine="halves") == len(expected)


def test_halves_refuse_other_searches(spark):
    t = made(spark, *random_graph(5, 12, 2, 1))
    assert [halves.cycle(P(x)) for x in ("a->b; b->a", "a->b; b->c; a->c", "a->b; b->a; c->d; d->c", "a->b; b-[e]->c; c->a", "a->c; c->b; b->a")] == [None] * 4 + [[0, 1, 2]]
    for p, how in ((P("a->b; b->c"), {}), (SHAPES[0], {"induced": True}), (SHAPES[0], {"method": "dom"})):
        with pytest.raises(ValueError):
            engines.enumerate(t, p, engine="halves", **how)


def test_four_cycles_shuffle_no_paths(spark, sf):
    plan = catalog.QUERIES["ord_cycle4_part_flow"](spark, sf)._jdf.queryExecution().toString()
    assert "Join" not in plan and "Exchange" not in plan
