"""The registered suite queries against the reference interpreter, on a small table with large keys."""

from decimal import Decimal

import pytest

import __spark_entry__ as entry
from congraph import rules_algebra, rules_binding
from congraph.graph import term_nodes
from congraph.reference import closure, reference_match
from congraph.terms import Var, as_pattern, variables


def found(nodes, pattern, conditions=()):
    """Assignments (root, variables..) that meet the conditions."""
    names = ["root", *variables(as_pattern(pattern))]
    constants = {s: c for s, c, args in nodes if not args}
    for m in reference_match(nodes, pattern):
        at = dict(zip(names, m))
        if all(at[c.over[0]] != (constants.get(c.constant) if c.constant else at[c.over[1]]) for c in conditions):
            yield at


def one_round(terms, rules):
    ids, nodes, pairs = {}, set(), []
    for t in term_nodes(terms):
        args = tuple(ids[a] for a in t.args)
        ids[t] = len(ids)
        nodes.add((t.sym, ids[t], args))
    start, made = sorted(nodes), {}

    def build(p, at):
        if isinstance(p, Var):
            return at[p.name]
        args = tuple(build(a, at) for a in p.args)
        own = made.setdefault((p.sym, args), 1_000_000 + len(made))
        nodes.add((p.sym, own, args))
        return own

    for r in rules:
        pairs += [(at["root"], build(r.right, at)) for at in found(start, r.left, r.conditions)]
    return closure(sorted(nodes), pairs)


LINES = [(9, "10.50", "0.00", "0.08"), (9, "10.50", "0.10", "0.02"), (5000, "7.00", "0.10", "0.08"), (5001, "99999.99", "0.05", "0.00"), (2, "1.00", "0.01", "0.01")]
PARTS = [(2, "Brand#1", "red old box"), (70, "Brand#1", "red new box"), (71, "Brand#2", "one"), (9000, "Brand#3", "dim red lid")]


@pytest.mark.parametrize("name", ["algebra", "binder"])
def test_suite_counts_every_row(spark, tmp_path, name):
    lines = [(k, *map(Decimal, x)) for k, *x in LINES]
    spark.createDataFrame(lines, "l_orderkey long, l_extendedprice decimal(14,2), l_discount decimal(14,2), l_tax decimal(14,2)").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame(PARTS, "p_partkey long, p_brand string, p_name string").write.parquet(f"{tmp_path}/part.parquet")
    if name == "algebra":
        rules, patterns, query = rules_algebra, rules_algebra.PATTERNS | {"DEEP": rules_algebra.DEEP}, "w12_algebra_suite"
        made = ["(mul (mul p{} (sub one d{})) (add one t{}))".format(*(x.replace(".", "_") for x in r)) for _, *r in LINES]
    else:
        rules, patterns, query = rules_binding, rules_binding.PATTERNS, "w13_binder_suite"
        made = [f"(app (lam v_{b} (app (var v_{b}) w_{t.split()[-1]})) w_{t.split()[0]})" for b, t in ((b.replace("#", "_"), t) for _, b, t in PARTS)]
    nodes = one_round([*rules.STARTS, "zero", "one", "true", "false", *made], rules.RULES)
    conditions = {r.name: r.conditions for r in rules.RULES}
    expected = {k: sum(1 for _ in found(nodes, p, conditions.get(k, ()))) for k, p in patterns.items()}
    assert {r.pattern: r.n for r in entry.queries()[query](spark, str(tmp_path)).collect()} == expected


def test_a_chain_of_over_a_million_orders(spark, tmp_path):
    n = (1 << 20) + 100
    orders = spark.range(n + 3).selectExpr("id o_orderkey", f"case when id < {n} then 1 else 2 end o_custkey")
    orders.write.parquet(f"{tmp_path}/orders.parquet")
    assert entry.queries()["w15_associativity"](spark, str(tmp_path)).first().n == n - 2 + 1


def test_tree_search_counts(spark, tmp_path):
    """Classes of pages hold one node each, so both patterns can be counted node by node."""
    from congraph.sources.markup import page_nodes, tree_search

    pages = ["<ul><li><a>x</a></li><li><a>x</a></li><li>y</li></ul>", "<p>a</p><p>a</p><p>a</p>", None, "<div><br><br><li><a>q</a><b>z</b></li></div>"]
    spark.createDataFrame([(k, h) for k, h in enumerate(pages)], "page_id long, html string").write.parquet(f"{tmp_path}/pages.parquet")
    nodes = {}
    for h in pages:
        nodes.update(page_nodes(h or ""))
    twice = sum(sym == "cons" and nodes[args[1]][0] == "cons" and nodes[args[1]][1][0] == args[0] for sym, args in nodes.values())
    linked = sum(sym == "el_li" and nodes[args[0]][0] == "cons" and nodes[nodes[args[0]][1][0]][0] == "el_a" for sym, args in nodes.values())
    for strategy in ("extension", "binary", "topdown"):
        got = {r.pattern: r.n for r in tree_search(spark, str(tmp_path), strategy).collect()}
        assert got == {"(cons ?a (cons ?a ?rest))": twice, "(el_li (cons (el_a ?x) ?r))": linked} and twice > 2 and linked == 2
