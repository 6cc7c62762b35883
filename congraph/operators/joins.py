"""Two-way strategies: plain joins, semi-join reduction, the hybrid with a cyclic core; and the flat scan."""

from __future__ import annotations

import math
from collections.abc import Mapping, Sequence
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from congraph.operators.atoms import Frames
from congraph.operators.extension import extension_join
from congraph.operators.topdown import barrier, spread
from congraph.plans.compile import ConjunctiveQuery
from congraph.plans.cover import prefix_bound
from congraph.plans.order import order_variables
from congraph.plans.shape import join_tree


class NotAcyclic(ValueError):
    """The semi-join reducer needs a join tree."""


def natural_join(a: DataFrame, b: DataFrame, how: str = "inner", hint: str | None = None) -> DataFrame:
    keys = [c for c in a.columns if c in b.columns]
    if hint:
        b = b.hint(hint)
    return a.join(b, keys, how) if keys else a.crossJoin(b)


def connected_order(cq: ConjunctiveQuery, sizes: Mapping[str, int]) -> list[int]:
    """Atoms from the smallest on, each next one sharing the most variables with those before."""
    left = list(range(len(cq.atoms)))
    done: list[int] = []
    while left:
        bound = {v for i in done for v in cq.atoms[i].vars}
        nxt = min(left, key=lambda i: (-len(bound & set(cq.atoms[i].vars)), sizes[cq.atoms[i].alias], i))
        done.append(nxt)
        left.remove(nxt)
    return done


#: Rows up to which the first relation of two-way joins is dealt anew.
DEALT = 2_000_000
#: Atoms up to which all orders of two-way joins are compared; beyond, the next atom is the one with the least bound.
EXHAUSTIVE = 8


def cheapest_order(cq: ConjunctiveQuery, sizes: Mapping[str, int], frames: Frames) -> list[int]:
    """Atoms so that what the joins give on the way adds up to the least; an atom that shares nothing comes when no other is
    left. A step's size is the bound of its variables under the dependencies; without dependencies, bounds can't tell one
    side from another, and it is estimated from the numbers of distinct keys. Ties go to `connected_order`."""
    first = connected_order(cq, sizes)
    if len(first) < 3:
        return first
    distinct = {} if cq.keyed else distinct_keys(cq, frames)

    def step(done: frozenset, rows: float, i: int) -> float:
        if cq.keyed:
            some = replace(cq, atoms=tuple(cq.atoms[k] for k in sorted(done | {i})))
            return prefix_bound(some, sizes, {v for a in some.atoms for v in a.vars})
        a = cq.atoms[i]
        keys = {v for k in done for v in cq.atoms[k].vars} & set(a.vars)
        held = min(sizes[a.alias], math.prod(distinct[a.alias, v] for v in keys))
        return rows * sizes[a.alias] / max(1, held)

    beside = lambda done, i: any(set(cq.atoms[i].vars) & set(cq.atoms[k].vars) for k in done)
    # For each set of atoms the cheapest way to it: (sum so far, rows of the last step, atoms).
    level: dict[frozenset, tuple[float, float, list[int]]] = {frozenset({i}): (float(sizes[cq.atoms[i].alias]), float(sizes[cq.atoms[i].alias]), [i]) for i in first}
    for _ in first[1:]:
        if len(first) > EXHAUSTIVE:
            best = min(level, key=lambda d: level[d][0])
            level = {best: level[best]}
        grown: dict[frozenset, tuple[float, float, list[int]]] = {}
        for done, (cost, rows, way) in level.items():
            left = [i for i in first if i not in done]
            for i in [i for i in left if beside(done, i)] or left:
                n, wider = step(done, rows, i), done | {i}
                if wider not in grown or cost + n < grown[wider][0] * (1 - 1e-12):
                    grown[wider] = cost + n, n, [*way, i]
        level = grown
    return next(iter(level.values()))[2]


def distinct_keys(cq: ConjunctiveQuery, frames: Frames) -> dict[tuple[str, str], int]:
    """About how many values a variable has in an atom, for variables of several atoms: one job over all of them."""
    counts = None
    for k, a in enumerate(cq.atoms):
        for v in a.distinct:
            if len(cq.containing(v)) > 1:
                one = frames[a.alias].agg(F.approx_count_distinct(v).alias("n")).select(F.lit(k).alias("k"), F.lit(v).alias("v"), "n")
                counts = one if counts is None else counts.unionByName(one)
    return {} if counts is None else {(cq.atoms[r.k].alias, r.v): r.n for r in counts.collect()}


def scan(cq: ConjunctiveQuery, frames: Frames) -> DataFrame:
    """A flat pattern: one relation, its filters already on it."""
    return frames[cq.atoms[0].alias]


def binary_join(cq: ConjunctiveQuery, frames: Frames, sizes: Mapping[str, int], tree: Sequence[int] | None = None, hint: str | None = None) -> DataFrame:
    """Two relations at a time in one order of atoms for all rows; hint: shuffle_hash, merge, broadcast or none."""
    order = list(tree) if tree is not None else cheapest_order(cq, sizes, frames)
    out = frames[cq.atoms[order[0]].alias]
    if not cq.keyed and sizes[cq.atoms[order[0]].alias] <= DEALT:
        # A hub may give each of its rows as many: a small relation in a few files is dealt to all cores.
        out = out.repartition(spread(out.sparkSession))
    for i in order[1:]:
        out = natural_join(out, frames[cq.atoms[i].alias], hint=hint)
    return out


def reduce_frames(cq: ConjunctiveQuery, frames: Frames) -> Frames:
    """Each relation without the rows that no full match uses: semi-joins up the join tree, then down."""
    tree = join_tree(cq)
    if not tree.acyclic:
        raise NotAcyclic(str(cq))
    out = dict(frames)
    name = lambda i: cq.atoms[i].alias
    shared = lambda i, j: [v for v in cq.atoms[i].distinct if v in cq.atoms[j].vars]
    for ear, parent in tree.removed:
        if parent is not None and (keys := shared(parent, ear)):
            out[name(parent)] = out[name(parent)].join(out[name(ear)].select(*keys), keys, "left_semi")
    for ear, parent in reversed(tree.removed):
        if parent is not None and (keys := shared(ear, parent)):
            out[name(ear)] = out[name(ear)].join(out[name(parent)].select(*keys), keys, "left_semi")
    return out


def reduced_join(cq: ConjunctiveQuery, frames: Frames) -> DataFrame:
    """Joins of the reduced relations in the order of the tree; columns go as soon as nothing needs them, if the
    query is keyed (then no rows meet)."""
    tree = join_tree(cq)
    reduced = reduce_frames(cq, frames)
    todo = [i for i, _ in reversed(tree.removed)]
    out = reduced[cq.atoms[todo[0]].alias]
    for k, i in enumerate(todo[1:], 2):
        out = natural_join(out, reduced[cq.atoms[i].alias])
        if not cq.keyed:
            continue
        later = {v for j in todo[k:] for v in cq.atoms[j].vars} | set(cq.head) | {v for c in cq.conditions for v in c.over}
        out = out.select(*[c for c in out.columns if c in later])
    return out


#: Rows up to which `cartesian_match` takes a relation.
SMALL = 200


def cartesian_match(cq: ConjunctiveQuery, frames: Frames, sizes: Mapping[str, int]) -> DataFrame:
    """The definition taken literally: the product of all relations, and equality tests behind a barrier. For tiny inputs."""
    if any(sizes[a.alias] > SMALL for a in cq.atoms):
        raise ValueError(f"a relation has more than {SMALL} rows")
    out, place = None, {}
    tests = []
    for a in cq.atoms:
        names = {v: f"{a.alias}_{v}" for v in a.distinct}
        one = frames[a.alias].select(*[F.col(v).alias(c) for v, c in names.items()])
        out = one if out is None else out.crossJoin(one)
        for v, c in names.items():
            if v in place:
                tests.append((place[v], c))
            place.setdefault(v, c)
    out = barrier(out)
    for x, y in tests:
        out = out.where(F.col(x) == F.col(y))
    return out.select(*[F.col(c).alias(v) for v, c in place.items()])


def hybrid_join(cq: ConjunctiveQuery, frames: Frames, sizes: Mapping[str, int], **options) -> DataFrame:
    """The cyclic core by the extension join, its relations first reduced by the ears; then the ears joined on."""
    tree = join_tree(cq)
    if tree.acyclic:
        return reduced_join(cq, frames)
    out = dict(frames)
    for ear, parent in tree.removed:
        keys = [v for v in cq.atoms[parent].distinct if v in cq.atoms[ear].vars]
        if keys:
            out[cq.atoms[parent].alias] = out[cq.atoms[parent].alias].join(out[cq.atoms[ear].alias].select(*keys), keys, "left_semi")
    core = replace(cq, atoms=tuple(cq.atoms[i] for i in tree.core), head=tuple(dict.fromkeys(v for i in tree.core for v in cq.atoms[i].vars)), conditions=())
    df = extension_join(core, out, order_variables(core, sizes), sizes, **options)
    return reduce(lambda a, i: natural_join(a, out[cq.atoms[i].alias]), [i for i, _ in reversed(tree.removed)], df)
