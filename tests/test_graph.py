"""Graphs, closure and every strategy against the reference interpreter."""

import random

import pytest
from pyspark.sql import functions as F

from congraph.closure import components, insert_nodes, merge, rebuild
from congraph.graph import NODES, CongruenceGraph, graph_of
from congraph.incremental import MatchState, canonical_delta, weighted
from congraph.operators.extension import build_index
from congraph.operators.joins import NotAcyclic, reduced_join
from congraph.operators.match import compiled, explain, match, match_many, plan
from congraph.operators.shares import HashTrie, SortedTrie, local_join
from congraph.plans.compile import query
from congraph.reference import closure, reference_match
from congraph.saturate import saturate
from congraph.terms import differs, rule

PATTERNS = ["(f ?a (g ?a))", "(f (g ?a) (g ?b))", "(f (g ?a) (h ?a))", ["(f ?a ?b)", "(f ?a ?c)"], "(g (g ?a))", "(f ?a ?a)", "(f c0 ?b)"]


def random_graph(seed):
    r = random.Random(seed)
    nodes = {(f"c{k}", k, ()) for k in range(4)}
    for _ in range(18):
        s, n = r.choice([("f", 2), ("g", 1), ("h", 1)])
        nodes.add((s, r.randrange(12), tuple(r.randrange(12) for _ in range(n))))
    return closure(sorted(nodes), [(r.randrange(12), r.randrange(12)) for _ in range(2)])


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def running(n):
    return [("g", 100, (k,)) for k in range(n)] + [("f", 101, (k, 100)) for k in range(n)] + [(f"leaf{k}", k, ()) for k in range(n)]


@pytest.mark.parametrize("seed", [1, 2])
def test_strategies_agree_with_the_definition(spark, seed):
    nodes = random_graph(seed)
    g = graph_of(spark, nodes)
    g = CongruenceGraph(spark, relations={s: d.cache() for s, d in g.relations().items()})
    for p in PATTERNS:
        expected = sorted(reference_match(nodes, p))
        acyclic = plan(g, p).shape.cyclic is False
        for s in ("auto", "binary", "extension", "static", "topdown", "hybrid", *(("reduced",) if acyclic else ("shares",))):
            assert rows(match(g, p, strategy=s)) == expected, (p, s)


def test_cycles_and_bare_and_ground(spark):
    g = graph_of(spark, [("f", 5, (5,)), ("a", 5, ())])
    assert rows(match(g, "(f ?x)")) == [(5, 5)] and rows(match(g, "(f (f ?x))")) == [(5, 5)]
    assert rows(match(g, "(f a)")) == [(5,)] and rows(match(g, "?x")) == [(5, 5)]
    assert g.class_of_term("(f (f a))") == 5 and g.class_of_term("(f b)") is None
    assert rows(match(g, "(f b)")) == []
    assert rows(g.count_terms(3)) == [(5, 3)]


def test_rebuild_goes_up_in_rounds(spark):
    nodes = [("a", 0, ()), ("b", 1, ()), ("f", 2, (0,)), ("f", 3, (1,)), ("g", 4, (2,)), ("g", 5, (3,))]
    g = graph_of(spark, nodes)
    for pairs in ([(0, 1)], [(1, 0)]):
        built = rebuild(merge(g, spark.createDataFrame(pairs, "a long, b long")))
        assert sorted((r.sym, r.cls, tuple(r.args)) for r in built.nodes.collect()) == closure(nodes, [(0, 1)])
        assert built.violations().count() == 0
        assert dict(rows(built.find_map.select("id", "rep"))) == {1: 0, 3: 2, 5: 4}


def test_components_of_chains_and_stars(spark):
    edges = [(k, k + 1) for k in range(1, 9)] + [(20, k) for k in range(21, 26)] + [(7, 7)]
    got = dict(rows(components(spark.createDataFrame(edges, "a long, b long"))))
    assert got == {**{k: 1 for k in range(2, 10)}, **{k: 20 for k in range(21, 26)}}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_insertion_finds_known_nodes(spark):
    g = graph_of(spark, [("a", 0, ()), ("f", 1, (0,))])
    more = spark.createDataFrame([("f", 9, [0], 1), ("h", 10, [0], 1)], NODES.replace("cls long, args array<long>", "cls long, args array<long>"))
    out = rebuild(insert_nodes(g, more.select("sym", "cls", "args", "ver")))
    assert sorted((r.sym, r.cls, tuple(r.args)) for r in out.nodes.collect()) == [("a", 0, ()), ("f", 1, (0,)), ("h", 10, (0,))]


def test_save_and_load(spark, tmp_path):
    g = graph_of(spark, running(3))
    g.save(f"{tmp_path}/g")
    back = CongruenceGraph.load(spark, f"{tmp_path}/g")
    assert rows(match(back, "(f ?a (g ?a))")) == [(101, 0), (101, 1), (101, 2)]


def test_trie_levels(spark):
    df = spark.createDataFrame([(1, 2, 4), (1, 2, 6), (1, 3, 7), (8, 2, 4)], "x long, y long, z long")
    levels = build_index(df, ["x", "y", "z"])
    assert rows(levels[0]) == [(1, 2), (8, 1)] and rows(levels[1]) == [(1, 2, 2), (1, 3, 1), (8, 2, 1)]
    assert rows(levels[2]) == [(1, 2, 4), (1, 2, 6), (1, 3, 7), (8, 2, 4)]


@pytest.mark.parametrize("trie", [HashTrie, SortedTrie])
def test_local_join_of_the_hub(trie):
    edges = [(0, 0)] + [(0, k) for k in range(1, 5)] + [(k, 0) for k in range(1, 5)]
    got = list(local_join([(("x", "y"), edges), (("y", "z"), edges), (("z", "x"), edges)], "xyz", trie))
    assert len(got) == len(set(got)) == 13


def test_work_of_the_matchers(spark):
    n = 30
    g = graph_of(spark, running(n))
    watch, trace = [], []
    assert match(g, "(f ?a (g ?a))", strategy="topdown", visited=watch).count() == n
    assert watch[-1].get["visited"] == n * n
    assert match(g, "(f ?a (g ?a))", strategy="extension", trace=trace).count() == n
    assert all(df.count() <= n for _, _, df in trace)
    hub = spark.createDataFrame([(0, 0)] + [(0, k) for k in range(1, n + 1)] + [(k, 0) for k in range(1, n + 1)], "x long, y long")
    h = CongruenceGraph(spark, {"R": hub, "S": hub, "T": hub}, congruent=False)
    cq = query("xyz", [("R", "xy"), ("S", "yz"), ("T", "zx")])
    work = {}
    for s in ("extension", "static"):
        trace = []
        assert match(h, cq, strategy=s, trace=trace).count() == 3 * n + 1
        work[s] = sum(df.count() for _, _, df in trace)
    assert work["extension"] <= 10 * n < n * n < work["static"]


def test_the_baseline_joins_on_structure_only(spark):
    g = graph_of(spark, running(5))
    text = match(g, "(f ?a (g ?a))", strategy="topdown")._jdf.queryExecution().executedPlan().toString()
    joins = [x for x in text.splitlines() if "Join" in x]
    assert joins and all(x.count("[") >= 1 and "," not in x.split("[")[1].split("]")[0] for x in joins)


def test_reducer_refuses_cycles(spark):
    with pytest.raises(NotAcyclic):
        reduced_join(query("xyz", [("R", "xy"), ("S", "yz"), ("T", "zx")]), {})


def test_conditions(spark):
    g = graph_of(spark, running(4))
    assert rows(match(g, "(f ?a (g ?a))", where=[differs("?a", "leaf0")])) == [(101, 1), (101, 2), (101, 3)]
    assert match(g, "(f ?a (g ?a))", where=[differs("?a", "absent")]).count() == 4
    two = [differs("?a", "?b")]
    for s in ("extension", "binary", "topdown"):
        assert match(g, "(f ?a (g ?b))", strategy=s, where=two).count() == 12
        assert match(g, "(f ?a (g ?b))", strategy=s, where=two, pushdown=False).count() == 12


def test_sharing_and_explain(spark):
    g = graph_of(spark, running(3))
    assert [d.count() for d in match_many(g, ["(f ?a (g ?a))", "(g ?a)"])] == [3, 3]
    assert "strategy" in explain(g, "(f ?a (g ?a))") and compiled("(g ?a)").head == ("root", "a")


def test_incremental_equals_recomputation(spark):
    nodes = running(6)
    f = [(c, *a) for s, c, a in nodes if s == "f"]
    h = [(c, *a) for s, c, a in nodes if s == "g"]
    state = MatchState.empty(graph_of(spark, nodes), "(f ?a (g ?a))")
    make = lambda part, k: weighted(spark.createDataFrame(part, ", ".join(f"{c} long" for c in ["id", "a1", "a2"][:k])))
    state.advance({"f": make(f[:3], 3), "g": make(h[:4], 2)}, 0)
    assert state.matches.count() == 3
    state.advance({"f": make(f[3:], 3)}, 1)
    state.advance({"g": make(h[4:], 2)}, 2)
    assert state.advance({"g": make(h[4:], 2)}, 2) is None
    assert rows(state.matches) == [(101, k) for k in range(6)]
    state.advance({"g": make(h[:2], 2).withColumn("w", F.lit(-1).cast("long"))}, 3)
    assert rows(state.matches) == [(101, k) for k in range(2, 6)]
    change = canonical_delta(spark.createDataFrame([(1, 5), (2, 5)], "id long, a1 long"), spark.createDataFrame([(2, 1)], "id long, rep long"))
    assert rows(change) == [(2, 5, -1)]


def test_saturation(spark):
    rules = [rule("zero", "(add ?a zero)", "?a"), rule("swap", "(add ?a ?b)", "(add ?b ?a)")]
    g = graph_of(spark, [("zero", 0, ()), ("x", 1, ()), ("add", 2, (0, 1))])
    out = saturate(g, rules, 100, 4)
    assert out.stopped == "saturated" and out.graph.class_of_term("(add zero x)") == out.graph.class_of_term("x")
    assert out.graph.violations().count() == 0 and 0 < out.match_share < 1
