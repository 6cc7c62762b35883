"""Terms and patterns as s-expressions: `(f ?a (g ?a))`; a bare name is a constant, `?x` a variable."""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

from pyspark.sql import Column


@dataclass(frozen=True)
class Var:
    name: str


@dataclass(frozen=True)
class App:
    sym: str
    args: tuple[Var | App, ...] = ()


Pattern = Var | App


def parse_pattern(text: str) -> Pattern:
    """A stack of open applications instead of recursion, so that a term may be of any depth."""
    open_: list[list] = [[]]  # what an application has so far, its symbol first; the outermost holds the whole term
    for token in re.findall(r"[()]|[^\s()]+", text):
        if len(open_) == 1 and open_[0]:
            raise ValueError(f"text after the term: {text!r}")
        if token == "(":
            open_.append([])
        elif token == ")":
            if len(open_) == 1 or not open_[-1]:
                raise ValueError(f"unexpected ) in {text!r}")
            sym, *args = open_.pop()
            open_[-1].append(App(sym, tuple(args)))
        elif len(open_) > 1 and not open_[-1]:
            open_[-1].append(token)
        else:
            open_[-1].append(Var(token[1:]) if token.startswith("?") else App(token))
        if len(open_) > 1 and open_[-1] and not isinstance(open_[-1][0], str):
            raise ValueError(f"an application begins with a symbol: {text!r}")
    if len(open_) > 1 or not open_[0]:
        raise ValueError(f"unfinished term: {text!r}")
    return open_[0][0]


def format_pattern(p: Pattern) -> str:
    if isinstance(p, Var):
        return f"?{p.name}"
    return f"({' '.join([p.sym, *map(format_pattern, p.args)])})" if p.args else p.sym


def as_pattern(p: Pattern | str) -> Pattern:
    return parse_pattern(p) if isinstance(p, str) else p


def occurrences(p: Pattern) -> Iterator[str]:
    """Names of variables from left to right, each time they occur."""
    if isinstance(p, Var):
        yield p.name
    else:
        for a in p.args:
            yield from occurrences(a)


def variables(*patterns: Pattern) -> list[str]:
    return list(dict.fromkeys(v for p in patterns for v in occurrences(p)))


def depth(p: Pattern) -> int:
    return 0 if isinstance(p, Var) else 1 + max((depth(a) for a in p.args), default=0)


def size(p: Pattern) -> int:
    return 1 if isinstance(p, Var) else 1 + sum(size(a) for a in p.args)


@dataclass(frozen=True)
class Cond:
    """A condition on variables. `test` makes a Column of the Columns of `over`; `constant`, a ground term, comes last
    among them as its class (or, absent from the graph, as null and `absent` is what the condition then is)."""

    over: tuple[str, ...]
    test: Callable[..., Column] = field(compare=False)
    constant: str | None = None
    absent: bool = True


def differs(a: str, b: str) -> Cond:
    """Two variables stand for different classes; b may be a ground term instead, in s-expression form."""
    if b.startswith("?"):
        return Cond((a.lstrip("?"), b[1:]), lambda x, y: x != y)
    return Cond((a.lstrip("?"),), lambda x, c: x != c, constant=b, absent=True)


@dataclass(frozen=True)
class Rule:
    """left -> right where the conditions hold; the right side's variables occur on the left."""

    name: str
    left: Pattern
    right: Pattern
    conditions: tuple[Cond, ...] = ()

    def __post_init__(self):
        if loose := set(occurrences(self.right)) - set(occurrences(self.left)):
            raise ValueError(f"{self.name}: {sorted(loose)} occur on the right only")


def rule(name: str, left: str, right: str, *conditions: Cond) -> Rule:
    return Rule(name, parse_pattern(left), parse_pattern(right), conditions)
