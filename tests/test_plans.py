"""Compilation, shapes, orders and bounds of the worked examples; no Spark."""

import math
from itertools import product

import pytest

from congraph.operators.shares import HashTrie, SortedTrie
from congraph.plans.compile import compile_multi, compile_pattern, query
from congraph.plans.cover import agm_bound, fd_bound, fractional_cover, integral_cover_bound, output_bound, prefix_bound, product_bound
from congraph.plans.order import order_variables
from congraph.plans.shape import classify, fd_graph, join_tree
from congraph.rules_algebra import PATTERNS as ALGEBRA
from congraph.rules_binding import PATTERNS as BINDER
from congraph.sources.files import _ident
from congraph.terms import depth, format_pattern, occurrences, parse_pattern

TRIANGLE = query("xyz", [("R", "xy"), ("S", "yz"), ("T", "zx")])


def atoms(cq):
    return [(a.sym, a.vars) for a in cq.atoms]


@pytest.mark.parametrize("text", ["(f ?a (g ?a))", "a", "?x", "(f (g (h ?a)) b)"])
def test_round_trip_of_text(text):
    assert format_pattern(parse_pattern(text)) == text


@pytest.mark.parametrize("text", ["(f ?a", ")", "(f) x"])
def test_bad_text(text):
    with pytest.raises(ValueError):
        parse_pattern(text)


def test_compiled_examples():
    cq = compile_pattern("(f ?a (g ?a))")
    assert cq.head == ("root", "a") and atoms(cq) == [("f", ("root", "a", "_n0")), ("g", ("_n0", "a"))]
    cq = compile_pattern("(f (g ?a) (h ?a))")
    assert atoms(cq) == [("f", ("root", "_n0", "_n1")), ("g", ("_n0", "a")), ("h", ("_n1", "a"))]
    cq = compile_multi(["(f ?a ?b)", "(f ?a ?c)"])
    assert cq.head == ("root1", "root2", "a", "b", "c")
    assert atoms(cq) == [("f", ("root1", "a", "b")), ("f", ("root2", "a", "c"))]
    assert compile_pattern("?x").atoms == ()
    assert atoms(compile_pattern("(f ?a ?a)")) == [("f", ("root", "a", "a"))]


def test_stale_ids_need_a_join_for_each_nesting():
    cq = compile_pattern("(f (g ?a))", canonical=False)
    assert len(cq.same) == 1 and cq.atoms[0].vars[1] != cq.atoms[1].vars[0]


def test_shapes():
    assert classify(compile_pattern("(f (g ?a) (h ?a))")).cyclic
    assert not classify(compile_pattern("(f ?a (g ?a))")).cyclic
    assert classify(TRIANGLE).cyclic and not join_tree(TRIANGLE).acyclic
    assert classify(compile_pattern("(f ?a ?b)")).degenerate
    cyclic = {k for k, p in {**ALGEBRA, **BINDER}.items() if classify(compile_pattern(p)).cyclic}
    assert cyclic == {"A06", "A07", "A19", "A32", "B15"}
    for p in {**ALGEBRA, **BINDER}.values():
        cq = compile_pattern(p)
        shape = classify(cq)
        assert not (shape.linear and shape.cyclic)
        assert fd_graph(cq).is_acyclic()
        assert shape.depth == depth(parse_pattern(p))


def test_isolated_variables_are_in_the_head():
    for p in {**ALGEBRA, **BINDER}.values():
        cq = compile_pattern(p)
        constants = {a.vars[0] for a in cq.atoms if a.arity == 0}
        assert cq.isolated() - constants <= set(cq.head)


def test_orders():
    sizes = dict.fromkeys(("r0", "r1", "r2"), 100)
    assert order_variables(compile_pattern("(f ?a (g ?a))"), sizes)[0] in (("a",), ("_n0",))
    chain = order_variables(compile_pattern("(f (g (h ?a)))"), {"r0": 100, "r1": 100, "r2": 3}, batch=False)
    assert chain[0] == ("_n1",) and chain[1] == ("_n0",) and {*chain[2:]} == {("root",), ("a",)}
    strict = order_variables(compile_pattern("(f (g ?a) (h ?a))"), sizes, fd="strict")
    assert strict == [("a",), ("_n0",), ("_n1",), ("root",)]


def test_order_by_bound_keeps_prefixes_within_the_output():
    """The cyclic pattern on relations of unequal sizes: no prefix may exceed the lines, and none crosses what shares nothing."""
    cq = compile_pattern("(lane (home (payer ?l)) (home (vendor ?l)))")
    sizes = {a.alias: {"lane": 625, "home": 1600}.get(a.sym, 60_000) for a in cq.atoms}
    bound: list[str] = []
    for (v,) in order_variables(cq, sizes):
        assert not bound or any(v in a.vars and set(a.vars) & set(bound) for a in cq.atoms)
        bound.append(v)
        assert prefix_bound(cq, sizes, bound) <= 60_000 * 1.001
    paper = [v for g in order_variables(cq, sizes, policy="paper") for v in g]
    assert max(prefix_bound(cq, sizes, paper[: k + 1]) for k in range(len(paper))) > 60_000


def test_terms_of_any_depth():
    text = "o"
    for k in range(5000):
        text = f"(add {text} o{k})"
    found: dict = {}
    _ident(parse_pattern(text), found)
    assert len(found) == 10_001


@pytest.mark.parametrize("trie", [HashTrie, SortedTrie])
def test_tries_count_next_values(trie):
    rows = [(a, b, c) for a in range(3) for b in range(a + 1) for c in range(5)]
    t = trie(rows, 3)
    assert t.count(t.top) == 3
    for a in range(3):
        under = t.step(t.top, a)
        assert t.count(under) == a + 1 == len(list(t.values(under)))
        assert t.count(t.step(under, 0)) == 5
    assert t.step(t.top, 9) is None


def test_batching_lowers_rounds():
    cq = query("xyzw", [("R", "xya"), ("S", "azw")])
    sizes = {"r0": 9, "r1": 9}
    assert order_variables(cq, sizes) == [("a",), ("x", "y"), ("z", "w")]
    assert len(order_variables(cq, sizes, batch=False)) == 5


def test_bounds():
    n = {"r0": 100, "r1": 100, "r2": 100}
    assert agm_bound(TRIANGLE, n) == pytest.approx(1000)
    assert product_bound(TRIANGLE, n) == 1e6 and integral_cover_bound(TRIANGLE, n) == 1e4
    total, weights = fractional_cover([{"x", "y"}, {"y", "z"}, {"z", "x"}], [1, 1, 1], {"x", "y", "z"})
    assert total == pytest.approx(1.5) and weights == pytest.approx([0.5] * 3)
    cq = compile_pattern("(f (g ?a) (h ?a))")
    assert agm_bound(cq, n) == pytest.approx(1e4)
    assert fd_bound(cq, n, drop_root_only=True) == pytest.approx(1e3)
    assert fd_bound(cq, n) == pytest.approx(1e2)
    assert output_bound(compile_pattern("(f (g ?a))"), {"r0": 50, "r1": 50}, 9) == pytest.approx(50 * 3)
    assert agm_bound(TRIANGLE, n | {"r0": 0}) == 0
    assert agm_bound(TRIANGLE, n | {"r0": 1}) == pytest.approx(100)


def test_cover_equals_grid_search():
    edges, sizes = [{"x", "y"}, {"y", "z"}, {"z", "x"}, {"x"}], [10, 200, 30, 4]
    logs = [math.log(s) for s in sizes]
    got, _ = fractional_cover(edges, logs, {"x", "y", "z"})
    grid = [k / 4 for k in range(5)]
    best = min(sum(a * b for a, b in zip(w, logs)) for w in product(grid, repeat=4) if all(sum(x for x, e in zip(w, edges) if v in e) >= 1 for v in "xyz"))
    assert got == pytest.approx(best)


def test_occurrences():
    assert list(occurrences(parse_pattern("(f ?a (g ?a ?b))"))) == ["a", "a", "b"]
