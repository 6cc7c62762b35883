"""The baseline: top-down search that follows structure and tests repeated variables afterwards.

Every occurrence of a variable is a column of its own; only class ids lead from a node to its children. A
fence, or a count where one is asked for, stands between the search and the equality tests, as Catalyst would
otherwise make the tests join keys and turn the baseline into the join matcher.
"""

from __future__ import annotations

import uuid
from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from congraph.graph import CongruenceGraph
from congraph.operators.crossed import class_pairs, crossed, paired
from congraph.plans.compile import ConjunctiveQuery
from congraph.terms import App, Var, variables


def spread(spark: SparkSession) -> int:
    """Partitions for a relation whose rows may each lead to many."""
    return max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))


def barrier(frame: DataFrame, visited: list[Observation] | None = None) -> DataFrame:
    """frame, with a count that filters do not pass; visited: gets the counter."""
    watch = Observation(f"visited_{uuid.uuid4().hex}")
    if visited is not None:
        visited.append(watch)
    return frame.observe(watch, F.count(F.lit(1)).alias("visited"))


def tested(frame: DataFrame, tests: list[tuple[str, str]], visited: list[Observation] | None = None) -> DataFrame:
    """frame where both columns of each test are equal, tested on its rows and never before them. Without a counter, a column
    that Catalyst may not move a filter past does what a count would, and the rows stay in compiled code."""
    if not tests:
        return frame if visited is None else barrier(frame, visited)
    equal = reduce(Column.__and__, [F.col(x) == F.col(y) for x, y in tests])
    if visited is not None:
        return barrier(frame, visited).where(equal)
    return frame.withColumn("_fence", F.monotonically_increasing_id()).where(equal & (F.col("_fence") >= 0)).drop("_fence")


def topdown_match(graph: CongruenceGraph, cq: ConjunctiveQuery, check: str = "late", visited: list[Observation] | None = None) -> DataFrame:
    """check `late`: equality at the end; `eager`: once the second occurrence is bound. visited: gets the counters.

    Each further root of a multi-pattern starts a search of its own: `late` takes all pairs of its nodes and the matches so
    far, `eager` begins with the nodes that hold a bound variable where the pattern has it, if the root has one.
    """
    if check not in ("late", "eager"):
        raise ValueError(check)
    roots = [h for h in cq.head if h.startswith("root")]
    if visited is None and len(cq.patterns) == 1 and (parted := _parted(cq.patterns[0])):
        df, seen = _crossed_search(graph, cq.patterns[0], roots[0], parted, check)
    elif visited is None and len(cq.patterns) == 1 and (found := _paired_search(graph, cq.patterns[0], roots[0], check)):
        df, seen = found
    else:
        df, seen = _search(graph, cq.patterns, roots, check, visited)
    # What an eager search has tested is equal already.
    df = tested(df, [(columns[0], c) for columns in seen.values() for c in columns[1:]] if check == "late" else [], visited)
    return df.select(*roots, *[F.col(seen[v][0]).alias(v) for v in cq.head if v not in roots])


def _parted(p: App) -> tuple[int, int, str] | None:
    """Places of p's two applications and a variable that both hold: the search takes all pairs of what is below them."""
    inner = [k for k, a in enumerate(p.args) if isinstance(a, App)]
    if len(inner) != 2:
        return None
    below = [variables(p.args[k]) for k in inner]
    both = [v for v in below[0] if v in below[1]]
    return (*inner, both[0]) if both else None


def _crossed_search(graph: CongruenceGraph, p: App, root: str, parted: tuple[int, int, str], check: str) -> tuple[DataFrame, dict[str, list[str]]]:
    """The search of a pattern whose root holds two applications with a variable in common: what is below each is searched on
    its own, and all pairs under a root's node are compared. Columns of each occurrence, by variable."""
    i, j, shared = parted
    names = [f"t{k}" for k in range(len(p.args))]
    top = graph.rel(p.sym, len(p.args)).toDF(root, *names)
    left, lseen = _search(graph, [p.args[i]], [names[i]], check, None, "l")
    right, rseen = _search(graph, [p.args[j]], [names[j]], check, None, "r")
    size = graph.sizes([(p.sym, len(p.args))])[p.sym, len(p.args)]
    df = crossed(top, left, right, (names[i], names[j]), (lseen[shared][0], rseen[shared][0]), size)
    seen: dict[str, list[str]] = {}
    for a, c in zip(p.args, names):
        if isinstance(a, Var):
            seen.setdefault(a.name, []).append(c)
    for some in (lseen, rseen):
        for v, columns in some.items():
            seen.setdefault(v, []).extend(columns)
    if check == "eager":
        df = tested(df, [(columns[0], c) for columns in seen.values() for c in columns[1:]])
    return df, seen


#: Combinations of nodes and what is below them from which tasks compare them in blocks.
MANY = 10**9


def _paired_search(graph: CongruenceGraph, p: App, root: str, check: str) -> tuple[DataFrame, dict[str, list[str]]] | None:
    """The search of a pattern whose root holds variables and one application of variables, one of which both hold, where there
    are so many combinations that making each a row takes too long: all of them are compared in blocks. None: any other."""
    inner = [k for k, a in enumerate(p.args) if isinstance(a, App)]
    if len(inner) != 1:
        return None
    below = p.args[inner[0]]
    shared = next((a.name for a in p.args if isinstance(a, Var) and a in below.args), None)
    if shared is None or any(isinstance(a, App) for a in below.args):
        return None
    kinds = [(p.sym, len(p.args)), (below.sym, len(below.args))]
    sizes = graph.sizes(kinds)
    if sizes[kinds[0]] * sizes[kinds[1]] < MANY:
        return None
    names, lower = [f"t{k}" for k in range(len(p.args))], [f"l{k}" for k in range(len(below.args))]
    on = names[inner[0]]
    top, side = graph.rel(*kinds[0]).toDF(root, *names), graph.rel(*kinds[1]).toDF(on, *lower)
    classes = class_pairs(top, side, on)
    pairs, cells = classes.agg(F.sum("_pairs"), F.sum(F.col("_p").cast("long") * F.col("_q"))).first()
    if (pairs or 0) < MANY:
        return None
    seen: dict[str, list[str]] = {}
    for a, c in zip((*p.args, *below.args), (*names, *lower)):
        if isinstance(a, Var):
            seen.setdefault(a.name, []).append(c)
    upper, under = (next(c for c in seen[shared] if c in some) for some in (names, lower))
    df = paired(top, side, on, (upper, under), classes, cells)
    if check == "eager":
        df = tested(df, [(columns[0], c) for columns in seen.values() for c in columns[1:]])
    return df, seen


def _search(graph: CongruenceGraph, patterns: Sequence[App], roots: Sequence[str], check: str, visited: list[Observation] | None, prefix: str = "x") -> tuple[DataFrame, dict[str, list[str]]]:
    """(rows of the search, columns of each occurrence by variable); an eager one has tested them, a late one not yet."""
    df: DataFrame | None = None
    seen: dict[str, list[str]] = {}
    n = 0

    def visit(p: App, column: str) -> None:
        """Joins the nodes of p's symbol to the class in column, then goes down from left to right."""
        nonlocal df, n
        arity = len(p.args)
        names = []
        for _ in p.args:
            names.append(f"{prefix}{n}")
            n += 1
        rel = graph.rel(p.sym, arity).toDF(column, *names)
        held = {a.name: c for a, c in reversed(list(zip(p.args, names))) if isinstance(a, Var) and a.name in seen}
        if df is None:
            # Few files or one class may lead to N^2 rows: all cores take part from the start.
            df = rel.repartition(spread(graph.spark))
        elif column in df.columns:
            df = df.join(rel, column)
        elif check == "eager" and held:
            name, at = next((a.name, held[a.name]) for a in p.args if isinstance(a, Var) and a.name in held)
            df = df.join(rel, F.col(seen[name][0]) == F.col(at))
        else:
            df = df.crossJoin(rel)
        for a, c in zip(p.args, names):
            if isinstance(a, Var):
                seen.setdefault(a.name, []).append(c)
                if check == "eager" and len(seen[a.name]) > 1:
                    df = tested(df, [(seen[a.name][0], c)], visited)
        for a, c in zip(p.args, names):
            if isinstance(a, App):
                visit(a, c)

    for p, root in zip(patterns, roots):
        visit(p, root)
    return df, seen


def enumerated(graph: CongruenceGraph, cq: ConjunctiveQuery) -> int:
    """Rows that the late search enumerates before its tests, what `visited` observes. They follow from the nodes of each class
    and the ways below them, counted from the leaves up, so none of the rows is made: there may be N^2 of them."""

    def ways(p: App) -> DataFrame:
        df = graph.rel(p.sym, len(p.args)).withColumn("_w", F.lit(1).cast("long"))
        for k, a in enumerate(p.args, 1):
            if isinstance(a, App):
                below = ways(a).select(F.col("id").alias(f"a{k}"), F.col("_w").alias("_b"))
                df = df.join(below, f"a{k}").withColumn("_w", F.col("_w") * F.col("_b")).drop("_b")
        return df.groupBy("id").agg(F.sum("_w").alias("_w"))

    out = 1
    for p in cq.patterns:
        out *= ways(p).agg(F.sum("_w")).first()[0] or 0
    return out
