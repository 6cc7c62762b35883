"""Patterns to conjunctive queries: one atom for each application, one fresh variable for each inner one."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

from congraph.terms import App, Cond, Pattern, Var, as_pattern, variables


@dataclass(frozen=True)
class Atom:
    """Relation of a symbol with a variable for its class and for each argument, in that order."""

    sym: str
    vars: tuple[str, ...]
    alias: str

    @property
    def arity(self) -> int:
        return len(self.vars) - 1

    @property
    def distinct(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(self.vars))


@dataclass(frozen=True)
class ConjunctiveQuery:
    head: tuple[str, ...]
    atoms: tuple[Atom, ...]
    #: Inner variables, which the head leaves out.
    aux: tuple[str, ...] = ()
    conditions: tuple[Cond, ...] = ()
    #: True where an atom's arguments determine its class.
    keyed: bool = True
    #: Equalities between representatives that a graph with stale ids needs: (variable, variable).
    same: tuple[tuple[str, str], ...] = ()
    patterns: tuple[Pattern, ...] = field(default=(), compare=False)

    @property
    def vars(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys([*self.head, *(v for a in self.atoms for v in a.vars)]))

    def containing(self, v: str) -> list[int]:
        return [i for i, a in enumerate(self.atoms) if v in a.vars]

    def isolated(self) -> set[str]:
        return {v for v in self.vars if len(self.containing(v)) == 1}

    def __str__(self) -> str:
        return f"Q({', '.join(self.head)}) <- " + ", ".join(f"{a.sym}({', '.join(a.vars)})" for a in self.atoms)


def _flatten(patterns: Sequence[Pattern], roots: Sequence[str], canonical: bool) -> tuple[list[Atom], list[str], list[tuple[str, str]]]:
    atoms: list[Atom] = []
    aux: list[str] = []
    same: list[tuple[str, str]] = []

    def visit(p: Pattern, own: str | None) -> str:
        if isinstance(p, Var):
            return p.name
        name = own or f"_n{len(aux)}"
        if own is None:
            aux.append(name)
        place = len(atoms)
        atoms.append(Atom(p.sym, (name,), ""))
        args = []
        for a in p.args:
            inner = visit(a, None)
            if not canonical and isinstance(a, App):
                # The parent may hold another id of the child's class.
                stale = f"{inner}_s{len(same)}"
                aux.append(stale)
                same.append((stale, inner))
                inner = stale
            args.append(inner)
        atoms[place] = Atom(p.sym, (name, *args), f"r{place}")
        return name

    for p, root in zip(patterns, roots):
        visit(p, root)
    out, seen = [], set()
    for a in atoms:  # equal atoms add nothing under set semantics
        if (a.sym, a.vars) not in seen:
            seen.add((a.sym, a.vars))
            out.append(a)
    return out, aux, same


def compile_pattern(p: Pattern | str, canonical: bool = True, conditions: Sequence[Cond] = ()) -> ConjunctiveQuery:
    """A pattern of one bare variable has no atom; its matches are all classes, with root and variable alike."""
    p = as_pattern(p)
    if isinstance(p, Var):
        return ConjunctiveQuery(("root", p.name), (), conditions=tuple(conditions), patterns=(p,))
    atoms, aux, same = _flatten([p], ["root"], canonical)
    return ConjunctiveQuery(("root", *variables(p)), tuple(atoms), tuple(aux), tuple(conditions), same=tuple(same), patterns=(p,))


def compile_multi(patterns: Sequence[Pattern | str], canonical: bool = True, conditions: Sequence[Cond] = ()) -> ConjunctiveQuery:
    """One query with a root for each member; members share the substitution."""
    ps = [as_pattern(p) for p in patterns]
    if any(isinstance(p, Var) for p in ps):
        raise ValueError("a member of a multi-pattern must be an application")
    roots = [f"root{k}" for k in range(1, len(ps) + 1)]
    atoms, aux, same = _flatten(ps, roots, canonical)
    # Two equal members keep two roots, so their atoms stay apart.
    return ConjunctiveQuery((*roots, *variables(*ps)), tuple(atoms), tuple(aux), tuple(conditions), same=tuple(same), patterns=tuple(ps))


def query(head: Sequence[str], atoms: Sequence[tuple[str, Sequence[str]]], keyed: bool = False) -> ConjunctiveQuery:
    """A conjunctive query as given, over relations whose columns carry no dependency unless keyed."""
    made = tuple(Atom(s, tuple(v), f"r{k}") for k, (s, v) in enumerate(atoms))
    inner = {v for a in made for v in a.vars} - set(head)
    return ConjunctiveQuery(tuple(head), made, tuple(sorted(inner)), keyed=keyed)
