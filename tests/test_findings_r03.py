"""What round 3's findings ask for, on small inputs that failed before."""

import random
import tracemalloc
from itertools import permutations

import numpy as np
import pytest

from congraph.operators.shares import HashTrie, SortedTrie, local_join


@pytest.mark.parametrize("trie", [HashTrie, SortedTrie])
def test_tries_are_arrays(trie):
    rng = np.random.default_rng(1)
    rows = list(zip(rng.integers(0, 1 << 60, 50_000).tolist(), rng.integers(0, 9, 50_000).tolist()))
    tracemalloc.start()
    made = trie(rows, 2)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    # Less than Python objects for each row would take.
    assert made.count(made.top) == len({a for a, _ in rows}) and peak < 150 * len(rows)


@pytest.mark.parametrize("trie", [HashTrie, SortedTrie])
def test_local_join_in_any_order_equals_all_pairs(trie, monkeypatch):
    from congraph.operators import shares

    monkeypatch.setattr(shares, "TRIED", 3)
    rng = random.Random(2)
    for n in (0, 1, 30):
        draw = lambda *most: [tuple(rng.randrange(-m, m) << 58 if m == 5 else rng.randrange(m) for m in most) for _ in range(n)]
        r, s, t = draw(5, 6), draw(6, 6), draw(6, 5, 3)
        expected = sorted((x, y, z, w) for x, y in set(r) for y2, z in set(s) for z2, x2, w in set(t) if (y, z, x) == (y2, z2, x2))
        for order in permutations("xyzw"):
            got = local_join([("xy", r), ("yz", s), ("zxw", t)], order, trie)
            assert sorted(tuple(g[order.index(v)] for v in "xyzw") for g in got) == expected


def test_a_cell_is_one_partition_of_columns_and_keeps_nulls(spark):
    from congraph.operators.match import match
    from congraph.graph import CongruenceGraph
    from congraph.plans.compile import query

    rng = random.Random(4)
    draw = lambda a, b: sorted({(rng.randrange(6), rng.choice([None, 0, -1, 1 << 60])) for _ in range(25)}, key=str)
    g = CongruenceGraph(spark, {"R": spark.createDataFrame(r := draw(6, 4), "x long, a long"), "S": spark.createDataFrame(s := draw(6, 4), "x long, b long")}, congruent=False)
    df = match(g, query("xab", [("R", "xa"), ("S", "xb")]), strategy="shares")
    plan = df._jdf.queryExecution().executedPlan().toString()
    # No sort of all rows by cell, and no cell as a table of one group.
    assert "MapInArrow" in plan and "FlatMapGroups" not in plan and "Sort" not in plan
    assert sorted(map(str, map(tuple, df.collect()))) == sorted(str((x, a, b)) for x, a in r for y, b in s if x == y)


def test_pairs_of_a_node_and_its_child_are_compared_in_blocks(spark, monkeypatch):
    from congraph.graph import graph_of
    from congraph.operators import crossed, topdown
    from congraph.operators.match import match

    monkeypatch.setattr(topdown, "MANY", 10)
    for name, value in (("SIDE_ROWS", 4), ("FEW", 6), ("BLOCK", 3), ("PAIRS", 6)):
        monkeypatch.setattr(crossed, name, value)
    rng = random.Random(6)
    nodes = {("f", 100 + rng.randrange(3), (rng.randrange(7), 10 + rng.randrange(3), rng.randrange(7))) for _ in range(60)}
    nodes |= {("g", 10 + rng.choice([0, 0, 0, 1, 2]), (rng.randrange(7), rng.randrange(7))) for _ in range(40)}
    g = graph_of(spark, sorted(nodes), congruent=False)
    for p in ("(f ?a (g ?a ?b) ?c)", "(f ?a (g ?b ?a) ?b)", "(f ?a (g ?b ?b) ?b)", "(f ?a (g ?a ?a) ?a)"):
        expected = sorted(map(tuple, match(g, p, strategy="binary").collect()))
        for strategy in ("topdown", "topdown_eager"):
            df = match(g, p, strategy=strategy)
            assert "MapInArrow" in df._jdf.queryExecution().executedPlan().toString()
            assert expected and sorted(map(tuple, df.collect())) == expected
