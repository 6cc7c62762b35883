"""Matching of patterns over a congruence graph by any strategy."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from congraph.checkpoints import cut
from congraph.graph import CongruenceGraph
from congraph.operators.atoms import Frames, atom_frames, fold_constants, frame_of, project_head, push_conditions, test_of
from congraph.operators.extension import PrefixIndex, extension_join, ordered_join
from congraph.operators.joins import binary_join, cartesian_match, distinct_keys, hybrid_join, reduced_join, scan
from congraph.operators.shares import shares_join
from congraph.operators.topdown import barrier, topdown_match
from congraph.plans.compile import Atom, ConjunctiveQuery, compile_multi, compile_pattern
from congraph.plans.order import least_rows_order, order_variables
from congraph.plans.planner import MatchPlan, choose, explain_match
from congraph.terms import App, Cond, Pattern, Var, as_pattern, format_pattern


def compiled(pattern: Pattern | str | Sequence[Pattern | str] | ConjunctiveQuery, where: Sequence[Cond] = (), canonical: bool = True) -> ConjunctiveQuery:
    if isinstance(pattern, ConjunctiveQuery):
        return replace(pattern, conditions=(*pattern.conditions, *where))
    if isinstance(pattern, (list, tuple)):
        return compile_multi(pattern, canonical, where)
    return compile_pattern(as_pattern(pattern), canonical, where)


def _sizes(graph: CongruenceGraph, cq: ConjunctiveQuery) -> dict[str, int]:
    found = graph.sizes([(a.sym, a.arity) for a in cq.atoms])
    return {a.alias: found[a.sym, a.arity] for a in cq.atoms}


def plan(graph: CongruenceGraph, pattern, strategy: str = "auto", where: Sequence[Cond] = (), **options) -> MatchPlan:
    cq = compiled(pattern, where)
    return choose(cq, _sizes(graph, cq), strategy, **options)


def explain(graph: CongruenceGraph, pattern, **options) -> str:
    return explain_match(plan(graph, pattern, **options))


def _empty(graph: CongruenceGraph, cq: ConjunctiveQuery) -> DataFrame:
    return graph.spark.createDataFrame([], ", ".join(f"`{v}` long" for v in cq.head))


def match(graph: CongruenceGraph, pattern, strategy: str = "auto", where: Sequence[Cond] = (), pushdown: bool = True, policy: str = "bound", fd: str = "soft", batch: bool = True, order: Sequence[str] | None = None, index: PrefixIndex | None = None, frames: Frames | None = None, hint: str | None = None, tree: Sequence[int] | None = None, cells: int = 64, trie: str = "hash", trace: list | None = None, visited: list | None = None, counted: dict[str, int] | None = None) -> DataFrame:
    """Root and variable columns of every match; one pattern, a list of them (a multi-pattern) or a query.

    frames: relations by atom alias instead of the graph's own; counted: rows of those that the graph lacks. order: an explicit
    order of variables.
    """
    cq = compiled(pattern, where)
    if not cq.atoms:
        every = graph.nodes.select("cls").distinct()
        df = every.select(F.col("cls").alias("root"), F.col("cls").alias(cq.head[1]))
        for c in cq.conditions:
            df = df.where(test_of(graph, c))
        return df
    if strategy in ("topdown", "topdown_eager"):
        df = topdown_match(graph, cq, "eager" if strategy == "topdown_eager" else "late", visited)
        for c in cq.conditions:
            df = df.where(test_of(graph, c))
        return df if graph.congruent else df.distinct()
    if frames is None and tree is None and strategy in ("binary", "shares") and order is None:
        cq = graph.unfolded(cq)
    if frames is None and strategy in ("extension", "static", "hybrid", "shares"):
        # These read each relation several times: for its prefixes, their counts and as a filter, or for its parts.
        graph.store([(a.sym, a.arity) for a in cq.atoms])
    sizes = _sizes(graph, replace(cq, atoms=tuple(a for a in cq.atoms if a.alias not in (counted or {})))) | (counted or {})
    unique = graph.congruent and cq.keyed or set(cq.head) == set(cq.vars)
    frames = frames or atom_frames(graph, cq)
    cq, frames, possible = fold_constants(graph, cq, frames)
    if not possible or any(sizes[a.alias] == 0 for a in cq.atoms):
        return _empty(graph, cq)
    if not cq.atoms:
        return _empty(graph, cq)
    late = list(cq.conditions)
    if pushdown:
        frames, late = push_conditions(graph, cq, frames)
    distinct = None
    prescribed = order is not None
    if not cq.keyed and len(cq.atoms) > 2 and policy == "bound" and strategy in ("auto", "extension", "static", "shares"):
        # Bounds do not tell orders apart where nothing depends on anything; numbers of values do.
        distinct = distinct_keys(cq, frames)
        order = order or least_rows_order(cq, sizes, distinct)
    chosen = choose(cq, sizes, strategy, policy="given" if order else policy, fd=fd, batch=batch, given=order)
    waiting = list(late)

    def after(df: DataFrame, bound: list[str]) -> DataFrame:
        for c in list(waiting):
            if pushdown and set(c.over) <= set(bound):
                df = df.where(test_of(graph, c))
                waiting.remove(c)
        return df

    if chosen.strategy == "scan":
        df = scan(cq, frames)
    elif chosen.strategy == "binary":
        df = binary_join(cq, frames, sizes, tree, hint)
    elif chosen.strategy == "reduced":
        df = reduced_join(cq, frames)
    elif chosen.strategy == "hybrid":
        df = hybrid_join(cq, frames, sizes)
    elif chosen.strategy == "cartesian":
        df = cartesian_match(cq, frames, sizes)
    elif chosen.strategy == "shares":
        df = shares_join(cq, frames, chosen.order, sizes, cells, trie)
    elif prescribed and chosen.strategy == "extension" and not late and index is None and trace is None:
        df = ordered_join(cq, frames, chosen.order, sizes, distinct)
    else:
        df = extension_join(cq, frames, chosen.order, sizes, "static" if chosen.strategy == "static" else "per_prefix", index, after, trace, distinct)
    if waiting and not pushdown:
        df = barrier(df, visited)  # else Catalyst would push them
    for c in waiting:
        df = df.where(test_of(graph, c))
    return project_head(df, cq, unique)


def _inner(p: App) -> list[App]:
    """Applications below p that hold an application themselves."""
    out = []
    for a in p.args:
        if isinstance(a, App):
            if any(isinstance(x, App) for x in a.args):
                out.append(a)
            out.extend(_inner(a))
    return out


def _renamed(p: Pattern, names: dict[str, str]) -> Pattern:
    """p with its variables named by order of occurrence; names gets old to new."""
    if isinstance(p, Var):
        return Var(names.setdefault(p.name, f"s{len(names)}"))
    return App(p.sym, tuple(_renamed(a, names) for a in p.args))


def _with_views(cq: ConjunctiveQuery, views: dict[Pattern, DataFrame]) -> tuple[ConjunctiveQuery, dict[str, DataFrame]]:
    """cq with one atom for each shared inner application instead of its own atoms; frames of these atoms."""
    atoms, frames = [], {}
    inner = dict(zip(cq.aux, range(len(cq.aux))))
    by_root = {a.vars[0]: a for a in cq.atoms}

    def term(v: str) -> Pattern:
        return App(by_root[v].sym, tuple(term(x) for x in by_root[v].vars[1:])) if v in inner else Var(v)

    def visit(a: Atom) -> None:
        names: dict[str, str] = {}
        key = _renamed(term(a.vars[0]), names) if a.vars[0] in inner else None
        if key in views:
            alias = f"s{len(atoms)}"
            atoms.append(Atom(format_pattern(key), (a.vars[0], *names), alias))
            frames[alias] = views[key].select(F.col("root").alias(a.vars[0]), *[F.col(new).alias(old) for old, new in names.items()])
            return
        if a not in atoms:
            atoms.append(a)
        for v in a.vars[1:]:
            if v in inner:
                visit(by_root[v])

    for a in cq.atoms:
        if a.vars[0] not in inner:
            visit(a)
    kept = {v for a in atoms for v in a.vars}
    return replace(cq, atoms=tuple(atoms), aux=tuple(v for v in cq.aux if v in kept)), frames


def match_many(graph: CongruenceGraph, patterns: Sequence, share_prefix: bool = True, **options) -> list[DataFrame]:
    """A DataFrame for each pattern. share_prefix: an inner application of two levels or more that several patterns have, up to
    the names of variables, is matched once, written, and stands as one relation in each of them."""
    if not share_prefix:
        return [match(graph, p, **options) for p in patterns]
    queries = [compiled(p) for p in patterns]
    seen: dict[Pattern, int] = {}
    for cq in queries:
        for key in {_renamed(x, {}) for p in cq.patterns if isinstance(p, App) for x in _inner(p)}:
            seen[key] = seen.get(key, 0) + 1
    views = {key: cut(match(graph, key, **options), "shared") for key, n in seen.items() if n > 1}
    sizes = {key: view.count() for key, view in views.items()}
    out = []
    for cq in queries:
        own, shared = _with_views(cq, views) if views else (cq, {})
        frames = {a.alias: shared[a.alias] if a.alias in shared else frame_of(graph.rel(a.sym, a.arity), a) for a in own.atoms}
        counted = {a.alias: sizes[as_pattern(a.sym)] for a in own.atoms if a.alias in shared}
        out.append(match(graph, own, frames=frames, counted=counted, **options))
    return out


def match_stale(graph: CongruenceGraph, pattern, find_map: DataFrame) -> DataFrame:
    """Matches on a graph whose ids aren't canonical: each atom keeps the ids it holds, and the query's equalities between
    representatives, one for each inner application, are joins through the map of ids. So are further occurrences of a variable.
    Roots and variables are representatives."""
    cq = compiled(pattern, canonical=False)

    def rep(df: DataFrame, column: str, name: str) -> DataFrame:
        found = find_map.select(F.col("id").alias(column), F.col("rep").alias("_r"))
        return df.join(found, column, "left").withColumn(name, F.coalesce("_r", column)).drop("_r")

    equal = {stale: inner for stale, inner in cq.same}
    df, roots = None, {inner for _, inner in cq.same}
    for a in cq.atoms:
        names = [f"{a.alias}_{k}" for k in range(len(a.vars))]
        one = graph.rel(a.sym, a.arity).toDF(*names)
        met: dict[str, str] = {}
        for v, c in zip(a.vars, names):
            # What an equality or another place asks for is the representative; a class id that nothing asks for stays as it is.
            name = equal.get(v, v)
            one = rep(one, c, f"{c}_r")
            if name in met:
                one = one.where(F.col(met[name]) == F.col(f"{c}_r"))
            met.setdefault(name, f"{c}_r")
        one = one.select(*[F.col(c).alias(v) for v, c in met.items()])
        keys = [] if df is None else [c for c in df.columns if c in one.columns]
        df = one if df is None else df.join(one, keys) if keys else df.crossJoin(one)
    return df.select(*cq.head).distinct()


def match_order(graph: CongruenceGraph, pattern, **options) -> list[tuple[str, ...]]:
    cq = compiled(pattern)
    return order_variables(cq, _sizes(graph, cq), **options)
