"""Orders, anchors, plans: worked cases, no Spark."""

import pytest

from subgraph_spark.model import PatternGraph
from subgraph_spark.operators.patterns import CATALOG
from subgraph_spark.plans import order as O
from subgraph_spark.plans.search_plan import METHODS, build

SHAPES = {"H9a": [(0, 1), (0, 2), (0, 3), (1, 2)], "H9b": [(0, 1), (0, 3), (1, 3), (0, 2), (2, 4), (2, 5)], "H9c": [(0, 1), (0, 2), (0, 3), (2, 4)], "H9e": [(0, 1), (1, 2)]}


def shape(name):
    edges = SHAPES[name]
    return PatternGraph((None,) * (1 + max(map(max, edges))), tuple((a, b, None) for a, b in edges))


@pytest.mark.parametrize("name, expected", [("H9a", [0, 1, 2, 3]), ("H9b", [0, 1, 3, 2, 4, 5]), ("H9c", [0, 2, 1, 3, 4]), ("H9e", [1, 0, 2])])
def test_constraint_first(name, expected):
    assert O.constraint_first(shape(name)) == expected


def test_direction_does_not_matter_to_the_order():
    p = shape("H9b")
    turned = PatternGraph(p.labels, tuple((d, s, x) for s, d, x in p.edges))
    assert O.constraint_first(p) == O.constraint_first(turned)


def test_singletons_and_sizes():
    assert O.constraint_first(shape("H9e"), (5, 5, 1), singletons_first=True) == [2, 1, 0]
    assert O.constraint_first(CATALOG["P3"], (7, 2, 5), True, True) == [1, 2, 0]
    assert O.constraint_first(CATALOG["P3"], (7, 2, 5), False, True) == [0, 1, 2]
    assert O.by_degree(shape("H9b")) == [0, 2, 1, 3, 4, 5]
    assert O.by_domain_size(CATALOG["P3"], (7, 2, 5)) == [1, 2, 0]


def test_scores():
    near = shape("H9b").adjacency()
    assert O.w_m(near, {0}, 1) == 1 and O.w_n(near, {0}, 1) == 1 and O.w_n(near, {0}, 2) == 0


@pytest.mark.parametrize("p", CATALOG.values(), ids=CATALOG)
@pytest.mark.parametrize("method", METHODS)
def test_every_edge_is_used_once(p, method):
    plan = build(p, method, [3] * p.size)
    assert sorted(plan.order) == list(range(p.size))
    assert sum((s.anchor is not None) + len(s.checks) + len(s.loops) for s in plan.steps) == len(p.edges)
    assert all(s.anchor is None or s.anchor.pos < s.pos for s in plan.steps)
    assert all(c.pos < s.pos for s in plan.steps for c in s.checks)
    if p.components() == 1:
        assert [s.pos for s in plan.steps if s.anchor is None] == [0]
    assert plan.explain(10.0).count("\n") == p.size


def test_both_directions_give_one_anchor_and_one_check():
    steps = build(PatternGraph.parse("a->b; b->a")).steps
    assert steps[1].anchor.out and len(steps[1].checks) == 1 and not steps[1].checks[0].out


def test_parse():
    p = PatternGraph.parse("a:9->b:19; b-[x]->c; a->c; d")
    assert p.labels == ("9", "19", None, None) and p.edges == ((0, 1, None), (1, 2, "x"), (0, 2, None))
    with pytest.raises(ValueError):
        PatternGraph(())
    with pytest.raises(ValueError):
        PatternGraph((None,), ((0, 1, None),))


def test_automorphisms():
    assert [CATALOG[k].automorphisms() for k in ("P1", "P2", "P4", "P7", "P10")] == [3, 1, 4, 2, 2]
