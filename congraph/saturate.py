"""Rewriting to saturation: all rules are matched on one snapshot, applied, and the graph is rebuilt."""

from __future__ import annotations

import time
from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from congraph.checkpoints import cut
from congraph.closure import merge, rebuild
from congraph.graph import CongruenceGraph
from congraph.intern import hash_id
from congraph.operators.match import match
from congraph.terms import Pattern, Rule, Var

#: Rules whose matches one plan holds; more would make the plan itself large.
RULES_IN_PLAN = 4


def node_id(sym: str, args: list) -> object:
    """Id of a new node: a function of symbol and arguments, so equal new nodes are one and retries agree."""
    return hash_id("node", F.lit(sym), F.lit(len(args)), *args)


def apply_rule(rule: Rule, matches: DataFrame) -> DataFrame:
    """sym, cls, args, a, b: of each match a row for every node to add and one for the pair of classes to merge, the rest
    null; right sides are built from the leaves up."""
    made: list[tuple[str, str, list[str]]] = []
    df = matches

    def build(p: Pattern) -> str:
        nonlocal df
        if isinstance(p, Var):
            return p.name
        args = [build(a) for a in p.args]
        name = f"_r{len(made)}"
        df = df.withColumn(name, node_id(p.sym, [F.col(a) for a in args]))
        made.append((p.sym, name, args))
        return name

    top = build(rule.right)
    none = {"sym": F.lit(None).cast("string"), "cls": F.lit(None).cast("long"), "args": F.lit(None).cast("array<long>"), "a": F.lit(None).cast("long"), "b": F.lit(None).cast("long")}
    row = lambda **given: F.struct(*[c.alias(n) for n, c in (none | given).items()])
    rows = [row(sym=F.lit(sym), cls=F.col(name), args=F.array(*args) if args else F.array().cast("array<long>")) for sym, name, args in made]
    return df.select(F.inline(F.array(*rows, row(a=F.col("root"), b=F.col(top)))))


def _rules_once(graph: CongruenceGraph, rules: Sequence[Rule], strategy: str) -> tuple[DataFrame, DataFrame]:
    """Written nodes and pairs of a few rules; matches come once, both are read off them."""
    made = None
    for r in rules:
        one = apply_rule(r, match(graph, r.left, strategy=strategy, where=r.conditions))
        made = one if made is None else made.unionByName(one)
    made = cut(made, "made")
    return made.where("sym is not null").select("sym", "cls", "args"), made.where("a <> b").select("a", "b")


@dataclass
class Saturation:
    graph: CongruenceGraph
    iterations: int = 0
    stopped: str = "limit"
    nodes: list[int] = field(default_factory=list)
    match_s: float = 0.0
    total_s: float = 0.0

    @property
    def match_share(self) -> float:
        """Share of matching in the run time."""
        return self.match_s / self.total_s if self.total_s else 0.0


def saturate(graph: CongruenceGraph, rules: Sequence[Rule], node_limit: int = 10_000, iter_limit: int = 5, strategy: str = "binary") -> Saturation:
    """Stops at the iteration limit, when nothing changes, or once the rebuilt graph holds node_limit nodes."""
    out, began = Saturation(graph), time.time()
    n = graph.nodes.count()
    for _ in range(iter_limit):
        t = time.time()
        # Everything is evaluated on the snapshot before anything is applied; a few rules share a plan.
        nodes = pairs = None
        for k in range(0, len(rules), RULES_IN_PLAN):
            some, merges = _rules_once(out.graph, rules[k : k + RULES_IN_PLAN], strategy)
            nodes = some if nodes is None else nodes.unionByName(some)
            pairs = merges if pairs is None else pairs.unionByName(merges)
        pairs, nodes = pairs.distinct(), nodes.distinct()
        out.match_s += time.time() - t
        grown = out.graph.nodes.select("sym", "cls", "args", "ver").unionByName(nodes.withColumn("ver", F.lit(out.graph.version + 1)))
        # A new node that the graph has under another class meets it in the rebuild.
        g = CongruenceGraph(graph.spark, nodes=cut(grown.dropDuplicates(["sym", "cls", "args"]), "grown"), find_map=out.graph.find_map, congruent=False, version=out.graph.version)
        g = rebuild(merge(g, pairs))
        m = g.nodes.count()
        changed = m != n or g.nodes.select("sym", "cls", "args").exceptAll(out.graph.nodes.select("sym", "cls", "args")).take(1)
        out.graph, out.iterations, n = g, out.iterations + 1, m
        out.nodes.append(m)
        if not changed:
            out.stopped = "saturated"
            break
        if m >= node_limit:
            out.stopped = "nodes"
            break
    out.total_s = time.time() - began
    return out
