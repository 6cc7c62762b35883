"""Atoms as DataFrames whose columns are the atom's variables."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from congraph.graph import CongruenceGraph, columns_of
from congraph.plans.compile import Atom, ConjunctiveQuery
from congraph.terms import Cond

Frames = dict[str, DataFrame]


def frame_of(rel: DataFrame, atom: Atom) -> DataFrame:
    """A variable that the atom repeats becomes a filter and one column."""
    names = columns_of(atom.arity)
    first: dict[str, str] = {}
    for v, c in zip(atom.vars, names):
        if v in first:
            rel = rel.where(F.col(first[v]) == F.col(c))
        first.setdefault(v, c)
    out = rel.select(*[F.col(c).alias(v) for v, c in first.items()])
    return out.distinct() if len(first) < len(names) and atom.vars[0] not in first else out


def atom_frames(graph: CongruenceGraph, cq: ConjunctiveQuery) -> Frames:
    return {a.alias: frame_of(graph.rel(a.sym, a.arity), a) for a in cq.atoms}


def fold_constants(graph: CongruenceGraph, cq: ConjunctiveQuery, frames: Frames) -> tuple[ConjunctiveQuery, Frames, bool]:
    """Constants become literal filters of the atoms that hold them; False if the graph lacks one."""
    constants = {a.vars[0]: a for a in cq.atoms if a.arity == 0 and a.vars[0] not in cq.head}
    if not constants:
        return cq, frames, True
    value = {}
    for v, a in constants.items():
        if (c := graph.constant(a.sym)) is None:
            return cq, frames, False
        value[v] = c
    atoms, out = [], {}
    for a in cq.atoms:
        if a.arity == 0 and a.vars[0] in value:
            continue
        df = frames[a.alias]
        for v in set(a.vars) & set(value):
            df = df.where(F.col(v) == F.lit(value[v])).drop(v)
        atoms.append(Atom(a.sym, tuple(v for v in a.vars if v not in value), a.alias))
        out[a.alias] = df
    return replace(cq, atoms=tuple(atoms), aux=tuple(v for v in cq.aux if v not in value)), out, True


def test_of(graph: CongruenceGraph, cond: Cond) -> Column:
    columns = [F.col(v) for v in cond.over]
    if cond.constant is not None:
        c = graph.class_of_term(cond.constant)
        if c is None:
            return F.lit(cond.absent)
        columns.append(F.lit(c))
    return cond.test(*columns)


def push_conditions(graph: CongruenceGraph, cq: ConjunctiveQuery, frames: Frames) -> tuple[Frames, list[Cond]]:
    """Conditions within one atom filter it before any join; the rest wait for their last variable."""
    out, late = dict(frames), []
    for c in cq.conditions:
        holders = [a.alias for a in cq.atoms if set(c.over) <= set(a.vars)]
        for alias in holders:
            out[alias] = out[alias].where(test_of(graph, c))
        if not holders:
            late.append(c)
    return out, late


def project_head(df: DataFrame, cq: ConjunctiveQuery, unique: bool) -> DataFrame:
    """The head's columns. In a congruent graph the pattern's variables determine all others, so no rows repeat."""
    out = df.select(*cq.head)
    return out if unique else out.distinct()
