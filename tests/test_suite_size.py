"""What the suites do once instead of twice or for all nodes."""

from congraph.graph import CongruenceGraph, graph_of


def test_terms_are_parsed_on_all_cores_and_matches_written_once(spark, monkeypatch):
    from congraph import saturate
    from congraph.rules_algebra import RULES
    from congraph.sources.files import term_nodes_of

    terms = spark.createDataFrame([("(add (add x y) z)",), ("(add x zero)",), ("(mul x (add y z))",)], "value string").distinct()
    nodes = term_nodes_of(terms)
    assert "RoundRobinPartitioning" in nodes._jdf.queryExecution().executedPlan().toString()
    names = []
    monkeypatch.setattr(saturate, "cut", lambda df, name: names.append(name) or df)
    new, pairs = saturate._rules_once(CongruenceGraph(spark, nodes=nodes), RULES[:1], "binary")
    assert names == ["made"] and new.count() == 2 and pairs.count() == 1


def test_a_rebuild_looks_up_arguments_of_any_number(spark):
    from congraph.closure import merge, rebuild

    rows = [(c, k, []) for k, c in enumerate("abc")]
    rows += [("g", 10 + k, [k]) for k in range(3)] + [("f", 20 + k, [10 + k] * 6 + [2]) for k in range(2)] + [("h", 30 + k, [20 + k, 10 + k]) for k in range(2)]
    pairs = spark.createDataFrame([(0, 1)], "a long, b long")
    done = rebuild(merge(graph_of(spark, rows), pairs))
    assert {tuple(r) for r in done.find_map.collect()} == {(1, 0), (11, 10), (21, 20), (31, 30)}
    got = sorted((r.sym, r.cls, tuple(r.args)) for r in done.nodes.collect())
    assert got == sorted([("a", 0, ()), ("b", 0, ()), ("c", 2, ()), ("g", 10, (0,)), ("g", 12, (2,)), ("f", 20, (10,) * 6 + (2,)), ("h", 30, (20, 10))])
