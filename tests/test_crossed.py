"""All combinations below two children, compared in blocks."""

import os
import random

import numpy as np
import pytest

from congraph.graph import graph_of
from congraph.operators.match import match


def test_blocks_find_what_every_pair_does(monkeypatch):
    from congraph.operators import crossed

    monkeypatch.setattr(crossed, "BLOCK", 3)
    monkeypatch.setattr(crossed, "PAIRS", 6)
    monkeypatch.setattr(crossed, "NODES", 2)
    rng = random.Random(3)
    draw = lambda n, most: np.array([rng.randrange(most) for _ in range(n)], np.int64)
    for n in (0, 1, 40):
        a, b, c, x, d, y = draw(n, 5), draw(n, 6), draw(30, 6), draw(30, 9), draw(25, 5), draw(25, 9)
        expected = sorted((i, j, k) for i in range(n) for j in range(30) for k in range(25) if a[i] == c[j] and b[i] == d[k] and x[j] == y[k])
        assert sorted(zip(*[v.tolist() for v in crossed._matches(a, b, c, x, d, y)])) == expected


def test_search_below_two_children_equals_the_joins(spark):
    rng = random.Random(5)
    nodes = [("k", 100 + i, [rng.randrange(4), 10 + rng.randrange(3), rng.randrange(6)]) for i in range(12)]
    nodes += [("p", rng.randrange(4), [rng.randrange(6)]) for _ in range(9)] + [("q", 10 + rng.randrange(3), [rng.randrange(6), rng.randrange(4)]) for _ in range(9)]
    g = graph_of(spark, sorted({(s, c, tuple(a)) for s, c, a in nodes}), congruent=False)
    for p in ("(k (p ?l) (q ?l ?m) ?m)", "(k (p ?l) (q ?l (p ?l)) ?x)"):
        expected = sorted(map(tuple, match(g, p, strategy="binary").collect()))
        for strategy in ("topdown", "topdown_eager"):
            df = match(g, p, strategy=strategy)
            # Combinations are compared in a task, they are not rows of a join.
            assert "MapInArrow" in df._jdf.queryExecution().executedPlan().toString()
            assert sorted(map(tuple, df.collect())) == expected


@pytest.mark.skipif(not os.path.isdir("/root/testdata/sf0.001"), reason="given tables are absent")
def test_the_cycle_equals_its_sql(spark):
    from test_findings_r02 import same_as_sql

    for name in ("w03_cyclic_topdown", "w03_cyclic_topdown_eager"):
        same_as_sql(spark, name)
