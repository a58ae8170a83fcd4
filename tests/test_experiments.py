"""Experiments: domains over arrays, whole pattern sets, simulated runs, look-ahead, the pruning target."""

import json

import numpy as np
import pytest
from pyspark.sql import functions as F

from subgraph_spark import catalog
from subgraph_spark.model import Csr, PatternGraph, TargetGraph, random_graph
from subgraph_spark.operators import array_domains, balance, domains, engines, expand, patterns, stats, steal_sim, workloads
from subgraph_spark.operators.dfs import Counters, Kernel, search_tree, task_tree
from subgraph_spark.plans.search_plan import build
from subgraph_spark.sources import array_files, tables

V, E = "vid long, vlabel string", "src long, dst long, elabel string"


@pytest.fixture(scope="module")
def uniform(spark, sf):
    return tables.uniform_dense(spark, sf).written()


def test_array_domains_equal_table_domains(spark):
    vertices, edges = random_graph(12, 50, 3, 5)
    t = TargetGraph.of(spark.createDataFrame(vertices, V), spark.createDataFrame(edges, E), simple=False).written()
    csr = t.csr()
    for text in ("a:L0->b; b-[e1]->c; a->c", "a->a; a->b:L1", "a:L0->b:L1; b->c:L2; c->a; d:L0->b"):
        p = PatternGraph.parse(text)
        for method, rounds in (("dom", 0), ("dom", 1), ("dom", "fixpoint"), ("dom_sf", 1)):
            table, sizes = domains.prepare(t, p, method, rounds)
            masks, own = array_domains.prepare(csr, p, method, rounds)
            got = {(i, int(csr.vids[v])) for i in range(p.size) for v in np.flatnonzero(array_domains._bits(masks, i))}
            assert own == sizes.size and got == {tuple(r) for r in domains.rows(table, p).collect()}


def plain_walk(vertices, edges, p, method):
    """Pairs and matches of a domain method, in plain Python: domains, one round, singletons, order, depth-first."""
    label, out, into = dict(vertices), {}, {}
    for s, d in edges:
        out.setdefault(s, set()).add(d)
        into.setdefault(d, set()).add(s)
    dom = [{v for v in label if label[v] == p.labels[i] and len(out.get(v, ())) >= p.out_degree(i) and len(into.get(v, ())) >= p.in_degree(i)} for i in range(p.size)]
    dom = [{v for v in dom[i] if all(out.get(v, set()) & dom[d] for s, d, _ in p.edges if s == i) and all(into.get(v, set()) & dom[s] for s, d, _ in p.edges if d == i)} for i in range(p.size)]
    done = set()
    while method == "dom_sf" and all(dom):
        new = {i: next(iter(x)) for i, x in enumerate(dom) if len(x) == 1 and i not in done}
        if not new:
            break
        done |= new.keys()
        dom = [x - {v for j, v in new.items() if j != i} for i, x in enumerate(dom)]
    steps = build(p, method, [len(x) for x in dom]).steps
    pairs = matches = 0

    def extend(image):
        nonlocal pairs, matches
        if len(image) == p.size:
            matches += 1
            return
        step = steps[len(image)]
        near = dom[step.pv] if step.anchor is None else (out if step.anchor.out else into).get(image[step.anchor.pos], set())
        for v in near:
            pairs += 1
            if v in dom[step.pv] and v not in image and all((v in out.get(image[c.pos], ())) if c.out else (image[c.pos] in out.get(v, ())) for c in step.checks):
                extend([*image, v])

    extend([])
    return pairs, matches


def test_forward_checking_prunes(spark, sf, uniform):
    p = PatternGraph.parse(catalog.PRUNED)
    vertices = [tuple(r) for r in uniform.vertices.collect()]
    edges = [(r.src, r.dst) for r in uniform.edges.collect()]
    got = {r.method: (r.pairs, r.matches) for r in catalog.QUERIES["forward_checking_prunes"](spark, sf).collect()}
    assert got == {m: plain_walk(vertices, edges, p, m) for m in ("dom", "dom_s", "dom_sf")}
    assert got["dom_sf"][0] < got["dom_s"][0] < got["dom"][0]


def test_searches_on_whole_pattern_sets(uniform):
    methods = ("ord", "dom", "dom_s", "dom_f", "dom_sf")
    rows = workloads.searches("uniform", [uniform], methods, 2_000_000, edges=(4, 8, 16), draws=(1, 2)).collect()
    assert len(rows) == 3 * 3 * 2 * len(methods)
    for name in {r.instance for r in rows}:
        mine = {r.method: r for r in rows if r.instance == name}
        finished = {r.matches for r in mine.values() if not r.cut}
        assert len(finished) <= 1 and all(x >= 1 for x in finished)
        assert all(r.pairs < 2_100_000 and r.peak_mb > 0 and r.total_ms >= r.match_ms for r in mine.values())
        if not mine["ord"].cut and not mine["dom"].cut:
            assert mine["dom"].pairs <= mine["ord"].pairs
    one = rows[0]
    labels, edges = json.loads(one.pattern)
    p = PatternGraph(tuple(labels), tuple(map(tuple, edges)))
    assert p.components() == 1 and len(p.edges) == one.edges
    again = workloads.prepared(uniform.csr(), p, one.method)
    counters, left = workloads.explored(again, 2_000_000)
    assert (counters.pairs, counters.matches, left) == (one.pairs, one.matches, one.cut)


def test_summaries_count_what_is_unfinished(uniform):
    found = workloads.searches("uniform", [uniform], ("dom", "dom_sf"), 300, edges=(8, 16)).cache()
    summary = workloads.space_summary(found).collect()
    assert sum(r.instances for r in summary if r.method == "dom") == 6
    for method in ("dom", "dom_sf"):
        cut = found.filter((F.col("method") == method) & F.col("cut")).count()
        assert sum(r.unfinished for r in summary if r.method == method) == cut == workloads.unfinished(found).filter(F.col("method") == method).first().unfinished
    assert any(r.unfinished for r in summary)


def test_simulated_runs(uniform):
    found = {(r.instance, r.method): r for r in workloads.searches("uniform", [uniform], ("ord", "dom_sf"), 10**9, edges=(4, 8), draws=(1,)).collect()}
    runs = workloads.simulated("uniform", [uniform], ("ord", "dom_sf"), (1, 2, 4, 16), (1, 4), (0, 1), (True, False), 200_000, edges=(4, 8))
    rows = runs.collect()
    assert all(r.pairs >= 0 for r in rows)
    for r in rows:
        assert r.pairs == found[r.instance, r.method].pairs and r.makespan >= r.pairs / r.workers
        assert r.stealing or r.steals_ok == 0
    table = {(r.method, r.workers, r["class"]): r for r in workloads.speedup_table(runs.filter("stealing and group_size = 4 or workers = 1")).collect()}
    assert table["ord", 1, "all"].speedup_avg == 1.0 and table["ord", 4, "all"].speedup_avg > 1.2
    over = workloads.speedup_table(runs.filter("stealing"), "ord").filter("method = 'dom_sf' and workers = 1 and class = 'all'").first()
    assert over.speedup_avg > 1
    grid = workloads.group_table(runs.filter("workers > 1")).collect()
    assert {(r.workers, r.group_size, r.stealing) for r in grid} == {(w, g, x) for w in (2, 4, 16) for g in (1, 4) for x in (True, False)}


@pytest.mark.parametrize("seed", range(3))
def test_look_ahead_keeps_matches_and_saves_pairs(uniform, seed):
    csr = uniform.csr()
    p = patterns.extract(csr, 8, "semi", seed)
    plain = workloads.prepared(csr, p, "dom_s")
    ahead = Kernel(plain.csr, plain.plan, lookahead=True)
    found = []
    for kernel in (plain, ahead):
        c = Counters()
        rows = [x for kind, b in kernel.run(kernel.seeds(None, c), c) for x in map(tuple, b.tolist())]
        found.append((c.pairs, sorted(rows)))
    assert found[0][1] == found[1][1] and found[1][0] <= found[0][0]


def test_core_of_a_long_chain(spark):
    chain = [(i, i + 1, None) for i in range(200)]
    ring = [(1000 + i, 1000 + (i + 1) % 5, None) for i in range(5)]
    t = TargetGraph.of(spark.createDataFrame([(v, "x") for e in (*chain, *ring) for v in e[:2]], V).distinct(), spark.createDataFrame(chain[:60] + ring, E))
    assert {r.vid for r in stats.k_core(t, 2).collect()} == {1000 + i for i in range(5)}
    assert stats.k_core(t, 3).count() == 0


def test_order_is_chosen_by_estimated_pairs(uniform):
    p = PatternGraph.parse(catalog.PRUNED)
    ready = engines.prepare(uniform, p, "dom")
    assert expand.cheaper(uniform, ready.plan, ready.domains).method in ("dom", "dom_s")
    got = engines.run(ready, "auto", count_only=True, max_bytes=1).first()
    assert got["matches"] == 16


def test_allowance_and_advice(spark, uniform):
    assert engines.allowed_bytes(spark) >= 64 << 20
    roots = spark.createDataFrame([(i, 100) for i in range(30)], "root long, pairs long")
    assert balance.advise(roots, 1000) == 3 and balance.advise(roots, 1) == 30 and balance.advise(roots) == 1


def test_mapped_arrays_equal_held_ones(spark, uniform):
    odd = TargetGraph.of(spark.createDataFrame([(5, "x"), (-7, None), (900, "y"), (6, "x")], V), spark.createDataFrame([(5, 900, "e"), (900, 5, None), (6, 6, "e"), (-7, 5, "e"), (5, 77, "e"), (None, 5, "e")], E))
    none = TargetGraph.of(spark.createDataFrame([], V), spark.createDataFrame([], E))
    rng = np.random.default_rng(3)
    for t in (uniform, odd.written(), none):
        held, mapped = t.csr(), array_files.write(t).open()
        for name in ("vids", "vlabel", "out_ptr", "out_to", "in_ptr", "in_to"):
            assert getattr(held, name).tolist() == getattr(mapped, name).tolist()
        assert held.label_code == mapped.label_code and mapped.keys is None
        s, d = rng.integers(0, max(1, held.n), (2, 500 if held.n else 0))
        assert held.has_edge(s, d).tolist() == mapped.has_edge(s, d).tolist()
    with pytest.raises(ValueError, match="labels"):
        mapped.has_edge(s, d, "e")


@pytest.mark.parametrize("density", workloads.DENSITIES)
def test_extracted_patterns_equal_the_plain_rule(uniform, density):
    """The frontier's smallest hash, found by looking through all of it."""
    csr = uniform.csr()
    got = patterns.extract(csr, 40, density, 7)

    def mark(key):
        x = (key + 7 * 0x9E3779B97F4A7C15) * 0xBF58476D1CE4E5B9 % 2**64
        return (x ^ x >> 31) * 0x94D049BB133111EB % 2**64 >> 1

    n, places, chosen = csr.n, {}, []
    edges = {k for k in csr.keys.tolist() if k // n != k % n}
    while len(chosen) < 40:
        ends = lambda k: (k // n in places) + (k % n in places)
        near = [k for k in edges - set(chosen) if ends(k)] if chosen else list(edges)
        closes = density == "dense" or density == "semi" and len(chosen) % 2 == 1
        key = min([k for k in near if chosen and (ends(k) == 2) == closes] or near, key=lambda k: (mark(k), k))
        chosen.append(key)
        for v in (key // n, key % n):
            places.setdefault(v, len(places))
    assert got.edges == tuple((places[k // n], places[k % n], None) for k in chosen)


def test_experiments_on_mapped_arrays(uniform):
    """Extraction, searches and simulations of targets whose arrays nobody holds."""
    how = {"edges": (4, 8), "draws": (1,)}
    plain = lambda df: sorted(tuple(v for k, v in r.asDict().items() if not k.endswith(("_ms", "_mb"))) for r in df.collect())
    assert len({array_files.opener(uniform, b)().keys is None for b in (0, 1 << 30)}) == 2
    for rows in (
        lambda b: workloads.on_instances("sets", [uniform], lambda csr, p, _: [(p.size, workloads.as_text(p))], workloads.INSTANCE + ", vertices int, pattern string", max_bytes=b, **how),
        lambda b: workloads.searches("uniform", [uniform], ("ord", "dom", "dom_s", "dom_f", "dom_sf"), 10**7, max_bytes=b, **how),
        lambda b: workloads.simulated("uniform", [uniform], ("ord", "dom_sf"), (1, 4), (1, 4), (0, 1), (True, False), 20_000, max_bytes=b, **how),
    ):
        assert plain(rows(0)) == plain(rows(1 << 30))


def test_a_hub_takes_no_mapping_for_each_neighbour():
    """A star's mappings are as many as the hub has leaves, at every depth: they are held as rows and candidates, with the same pairs and matches."""
    import tracemalloc

    leaves, k = 20_000, 40
    n = leaves + 1
    ptr = np.concatenate([[0], np.full(n, leaves)])
    csr = Csr(np.arange(n), np.zeros(n, np.int64), {"x": 0}, ptr, np.arange(1, n), np.concatenate([[0, 0], np.arange(1, n)]), np.zeros(leaves, np.int64), None, None, None)
    kernel = Kernel(csr, build(PatternGraph(("x",) * (k + 1), tuple((0, i + 1, None) for i in range(k))), "ord", order=range(k + 1)))
    counters = Counters()
    tracemalloc.start()
    left = [b.shape[1] for kind, b in kernel.run(kernel.seeds(np.array([0])), counters, 800_000, block=256) if kind == "todo"]
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert counters.pairs >= 800_000 and left == sorted(left) and len(left) > 30
    assert peak < 64 << 20  # whole mappings: 20,000 * 8 bytes * (1 + ... + 40) = 131 MB


def test_coded_masks_equal_plain_ones(spark, uniform, monkeypatch):
    csr = uniform.csr()
    for density, edges in (("dense", 20), ("sparse", 100)):
        p = patterns.extract(csr, edges, density, 3)
        plain = {m: array_domains.prepare(csr, p, m, "fixpoint") for m in ("dom", "dom_sf")}
        monkeypatch.setattr(array_domains, "PLAIN", 0)
        for m, (masks, sizes) in plain.items():
            coded, own = array_domains.prepare(csr, p, m, "fixpoint")
            assert isinstance(coded, array_domains.Coded) and own == sizes and coded[:].tolist() == masks.tolist() and coded.copy()[:, 0].tolist() == masks[:, 0].tolist()
            assert array_domains.sizes(p, coded) == sizes
        found = {m: (None if k is None else (c := Counters(), sorted(x for _, b in k.run(k.seeds(None, c), c, 200_000) for x in b.tolist()))[0].pairs) for m, k, _ in workloads.kernels(csr, p, ("dom", "dom_f", "dom_s"))}
        monkeypatch.undo()
        again = {m: (None if k is None else (c := Counters(), sorted(x for _, b in k.run(k.seeds(None, c), c, 200_000) for x in b.tolist()))[0].pairs) for m, k, _ in workloads.kernels(csr, p, ("dom", "dom_f", "dom_s"))}
        assert found == again


def test_patterns_of_mapped_arrays_share_first_edges(spark, uniform):
    csr = uniform.csr()
    firsts = workloads.first_edges(spark, array_files.opener(uniform, 0), (1, 2, 7))
    assert firsts == {s: patterns.first_edge(csr, s) for s in (1, 2, 7)}
    assert all(patterns.extract(csr, 9, "semi", s, first=k) == patterns.extract(csr, 9, "semi", s) for s, k in firsts.items())


def test_task_trees_equal_recorded_ones(uniform):
    csr = uniform.csr()
    for p in (patterns.extract(csr, 8, "sparse", 2), patterns.extract(csr, 16, "dense", 5), PatternGraph((next(iter(csr.label_code)),), ())):
        kernel = Kernel(csr, build(p, "ord"))
        tree = search_tree(kernel)
        recorded = steal_sim.tasks_of(tree["parent_id"], tree["depth"], tree["consistent"])
        for block in (50, 1 << 18):
            own = task_tree(kernel, len(tree["node_id"]), block)
            k = len(own.depth)  # a recorded tree's last level generates nothing, and is no part of the tasks
            assert (own.roots, own.last, own.root_at.tolist()) == (recorded.roots, recorded.last, recorded.root_at.tolist())
            inner = own.depth + 1 < own.last
            assert own.depth.tolist() == recorded.depth[:k].tolist() and own.generated.tolist() == recorded.generated[:k].tolist()
            assert own.first[inner].tolist() == recorded.first[:k][inner].tolist() and own.kids[inner].tolist() == recorded.kids[:k][inner].tolist()
            for how in ((16, 1, 3), (16, 4, 3, False), (5, 2, 1)):
                assert steal_sim.simulate_tasks(own, *how) == steal_sim.simulate_tasks(recorded, *how)
        with pytest.raises(ValueError, match="nodes"):
            task_tree(kernel, len(tree["node_id"]) - 1)


def test_stealing_on_and_off_with_very_many_roots(spark, monkeypatch):
    """A target whose vertices alone are more than 60,000: no instance is left out."""
    vertices, edges = random_graph(30, 120, 5, 6)
    vertices += [(i, "L9") for i in range(1000, 71_000)]
    t = TargetGraph.of(spark.createDataFrame(vertices, V), spark.createDataFrame(edges, E)).written(False)
    monkeypatch.setattr(catalog, "_targets", lambda *_: [t])
    rows = {(r.group_size, r.stealing): r for r in catalog.QUERIES["stealing_on_off"](spark, "").collect()}
    assert set(rows) == {(g, x) for g in (1, 4) for x in (True, False)}
    assert all(r.runs == 2 * 2 * 2 * 3 and r.makespan >= 70_030 / 16 for r in rows.values())


def test_grid_of_trees_with_more_than_5000_nodes(spark, monkeypatch):
    """Directed rings of nine, alike in labels: a tree has a root and a path for every vertex. No instance of the grid is left out."""
    vertices = [(i, "L0") for i in range(130 * 9)]
    edges = [(i, i - i % 9 + (i % 9 + 1) % 9, None) for i in range(130 * 9)]
    t = TargetGraph.of(spark.createDataFrame(vertices, V), spark.createDataFrame(edges, E)).written(False)
    monkeypatch.setattr(catalog, "_targets", lambda *_: [t])
    rows = {(r.workers, r.group_size, r.stealing): r for r in catalog.QUERIES["steal_sim_grid_dense_many_labels"](spark, "").collect()}
    assert set(rows) == {(w, g, x) for w in (2, 4, 8, 16) for g in (1, 2, 4, 8, 16) for x in (True, False)}
    assert all(r.runs == 2 * 3 * 2 * 15 and r.makespan >= 130 * 9 * 5 / r.workers for r in rows.values())


def test_arrays_of_middle_size_are_mapped(uniform, monkeypatch):
    monkeypatch.setattr(TargetGraph, "array_bytes", lambda *_: 28 << 20)  # supplier_echo at 60 times sf0.1
    assert array_files.are_mapped(array_files.opener(uniform))


def test_labels_of_arrays(spark):
    v = [(7, "b"), (-1, None), (3, "a"), (9, "b")]
    e = [(7, 3, "x"), (7, 3, None), (7, 3, "y"), (3, 9, "y"), (9, 7, None), (3, 77, "gone")]
    csr = TargetGraph.of(spark.createDataFrame(v, V), spark.createDataFrame(e, E), simple=False).csr()
    assert csr.vids.tolist() == [-1, 3, 7, 9] and csr.label_code == {None: 0, "a": 1, "b": 2} and csr.vlabel.tolist() == [0, 1, 2, 2]
    assert {x: k.tolist() for x, k in csr.label_keys.items()} == {"x": [2 * 4 + 1], "y": [1 * 4 + 3, 2 * 4 + 1]}
