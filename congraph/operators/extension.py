"""The extension join: a query answered one group of variables at a time, for all prefixes at once.

A round takes the table of prefixes (values of the variables bound so far). If one atom holds the group, its
continuations are joined. If several do, each prefix takes the atom with the fewest continuations under it and
the other atoms filter what that gives; choosing for each prefix is what bounds the work by the largest
possible output. A class whose arguments are all bound has one continuation at most and needs no counts.
"""

from __future__ import annotations

import math
from collections.abc import Mapping, Sequence
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from congraph.checkpoints import cut, cut_parts
from congraph.operators.atoms import Frames
from congraph.plans.compile import Atom, ConjunctiveQuery
from congraph.plans.order import VarGroup


@dataclass
class PrefixIndex:
    """Levels of a trie in a column order: distinct prefixes and the number of continuations under each."""

    rows: Frames
    keyed: bool = False
    kept: dict = field(default_factory=dict)
    #: Levels are tables in the shared folder, to be used again by later queries.
    written: bool = False

    def _keep(self, key, make) -> DataFrame:
        if key not in self.kept:
            self.kept[key] = cut(make(), "index") if self.written else make()
        return self.kept[key]

    def level(self, atom: Atom, columns: Sequence[str]) -> DataFrame:
        """Distinct values of columns; a set of columns that holds the atom's key or all of it is distinct as it is."""

        def make():
            df = self.rows[atom.alias].select(*columns)
            whole = set(columns) >= set(atom.vars) or self.keyed and set(columns) >= set(atom.vars[1:])
            return df if whole else df.distinct()

        return self._keep((atom.alias, tuple(columns)), make)

    def counts(self, atom: Atom, bound: Sequence[str], new: Sequence[str]) -> DataFrame:
        """bound, _n: continuations new under each prefix bound."""
        return self._keep((atom.alias, tuple(bound), tuple(new)), lambda: self.level(atom, [*bound, *new]).groupBy(*bound).agg(F.count(F.lit(1)).alias("_n")))


def build_index(df: DataFrame, order: Sequence[str]) -> list[DataFrame]:
    """Trie levels of one relation: for each d, its distinct prefixes of length d and the continuations under each."""
    out = []
    for d in range(1, len(order) + 1):
        level = df.select(*order[:d]).distinct()
        if d < len(order):
            level = df.select(*order[: d + 1]).distinct().groupBy(*order[:d]).agg(F.count(F.lit(1)).alias("continuations"))
        out.append(level)
    return out


def extend_round(prefixes: DataFrame | None, bound: list[str], group: VarGroup, cq: ConjunctiveQuery, index: PrefixIndex, sizes: Mapping[str, int], choice: str, trace: list | None, distinct: Mapping[tuple[str, str], int] | None = None) -> DataFrame:
    new = list(group)
    holders = [a for a in cq.atoms if set(group) & set(a.vars)]
    on = {a.alias: [v for v in a.distinct if v in bound] for a in holders}

    # Of atoms with known numbers of values the one with the fewest rows below what is bound, on average; else the smallest.
    below = lambda a: sizes[a.alias] / max(1, min(sizes[a.alias], math.prod((distinct or {}).get((a.alias, v), 1) for v in on[a.alias])))

    def filtered(df: DataFrame, name: str, others: list[Atom]) -> DataFrame:
        if trace is not None:
            trace.append((group, name, df))
        # The atom that was chosen least drops the most: it comes before the others.
        for a in sorted(others, key=below, reverse=True) if distinct else others:
            keys = [*on[a.alias], *new]
            df = df.join(index.level(a, keys), keys, "left_semi")
        return df

    def extended(df: DataFrame | None, chosen: Atom) -> DataFrame:
        keys, level = on[chosen.alias], index.level(chosen, [*on[chosen.alias], *new])
        others = [a for a in holders if a is not chosen]
        # No key: a part of the query that shares nothing with what is bound.
        return filtered(level if df is None else df.join(level, keys) if keys else df.crossJoin(level), chosen.alias, others)

    fixed = [a for a in holders if cq.keyed and new == [a.vars[0]] and set(a.vars[1:]) <= set(bound)]
    if prefixes is not None and fixed:
        return extended(prefixes, fixed[0])
    tied = [a for a in holders if on[a.alias]]
    smallest = min(tied or holders, key=lambda a: (below(a), sizes[a.alias]))
    if prefixes is None or choice == "static" or len(tied) < 2:
        return extended(prefixes, smallest)
    # Each prefix takes the atom with the fewest continuations. The chosen atom is a column, and the levels of all atoms
    # stand in one table under that column, so that the prefixes occur once in the plan, however many atoms there are.
    counted = prefixes
    for k, a in enumerate(tied):
        counted = counted.join(index.counts(a, on[a.alias], new).withColumnRenamed("_n", f"_count{k}"), on[a.alias])
    least = F.least(*[F.col(f"_count{k}") for k in range(len(tied))])
    which = F.coalesce(*[F.when(F.col(f"_count{k}") == least, F.lit(k)) for k in range(len(tied))])
    width = max(len(on[a.alias]) for a in tied)
    # Place j of the key: the j-th bound variable of the chosen atom, 0 beyond its last.
    place = lambda a, j: F.col(on[a.alias][j]) if j < len(on[a.alias]) else F.lit(0).cast("long")
    counted = counted.withColumn("_which", which)
    for j in range(width):
        counted = counted.withColumn(f"_k{j}", F.coalesce(*[F.when(F.col("_which") == k, place(a, j)) for k, a in enumerate(tied)]))
    counted = counted.drop(*[f"_count{k}" for k in range(len(tied))])
    levels = None
    for k, a in enumerate(tied):
        level = index.level(a, [*on[a.alias], *new]).select(F.lit(k).alias("_which"), *[place(a, j).alias(f"_k{j}") for j in range(width)], *new)
        levels = level if levels is None else levels.unionByName(level)
    names = ["_which", *[f"_k{j}" for j in range(width)]]
    return filtered(counted.join(levels, names).drop(*names), "+".join(a.alias for a in tied), holders)


def extension_join(cq: ConjunctiveQuery, frames: Frames, order: Sequence[VarGroup], sizes: Mapping[str, int], choice: str = "per_prefix", index: PrefixIndex | None = None, after=None, trace: list | None = None, distinct: Mapping[tuple[str, str], int] | None = None) -> DataFrame:
    """All assignments of the query's variables. after(df, bound): filters by conditions once they can be read.

    trace: gets (group, atom, candidates) of each round, the rows enumerated before the other atoms filter them.
    distinct: values by (alias, variable), where they are known; the static choice goes by them.
    """
    if choice not in ("per_prefix", "static"):
        raise ValueError(choice)
    index = index or PrefixIndex(frames, cq.keyed)
    prefixes, bound = None, []
    for group in order:
        prefixes = extend_round(prefixes, bound, group, cq, index, sizes, choice, trace, distinct)
        bound += group
        if after:
            prefixes = after(prefixes, bound)
    return prefixes


#: Rows of all atoms that a join in a prescribed order takes at a time; such an order may have many more candidates than rows.
SLICE_ROWS = 10_000_000


def implied_atoms(cq: ConjunctiveQuery, order: Sequence[VarGroup]) -> list[tuple[Atom, Atom, Atom]]:
    """(new, a, b): atoms that the query implies and that a prescribed order can filter by. Where a and b meet only in variables
    that come after others of both, the order would bind each side on its own and take all pairs until it gets there. If what
    they share is the key of one of them, their join has no more rows than the other and stands beside them."""
    place = {v: k for k, group in enumerate(order) for v in group}
    out = []
    for a in cq.atoms:
        for b in cq.atoms:
            shared = set(a.vars) & set(b.vars)
            mine, others = set(a.vars) - shared, set(b.vars) - shared
            if not cq.keyed or not shared or not mine or not others or not set(b.vars[1:]) <= shared or any({a, b} == {x, y} for _, x, y in out):
                continue
            first = min(place[v] for v in shared)
            if min(place[v] for v in mine) < first and min(place[v] for v in others) < first:
                # It has no class of its own: the name in its place is no variable of the query.
                out.append((Atom("", (f"_j{len(out)}", *dict.fromkeys([*a.vars, *b.vars])), f"j{len(out)}"), a, b))
    return out


def ordered_join(cq: ConjunctiveQuery, frames: Frames, order: Sequence[VarGroup], sizes: Mapping[str, int], distinct: Mapping[tuple[str, str], int] | None = None) -> DataFrame:
    """The extension join in a prescribed order: implied atoms stand beside the query's own, and slices by a hash of the first
    variable are joined one after the other, so that the disk holds the candidates of one."""
    frames, sizes, more = dict(frames), dict(sizes), []
    for new, a, b in implied_atoms(cq, order):
        keys = [v for v in a.distinct if v in b.vars]
        frames[new.alias] = cut_parts([frames[a.alias].join(frames[b.alias], keys).select(*new.vars[1:])], "implied")
        sizes[new.alias] = frames[new.alias].count()
        more.append(new)
    cq = replace(cq, atoms=(*cq.atoms, *more))
    n, v = math.ceil(sum(sizes[a.alias] for a in cq.atoms) / SLICE_ROWS), order[0][0]
    if n <= 1:
        return extension_join(cq, frames, order, sizes, distinct=distinct)
    slot = F.pmod(F.xxhash64(v), F.lit(n))
    of = lambda k: {alias: df.where(slot == k) if v in df.columns else df for alias, df in frames.items()}
    return cut_parts((extension_join(cq, of(k), order, sizes, distinct=distinct) for k in range(n)), "slice")
