"""Patterns and rewrite rules of a small computer algebra: textbook identities, derivatives, integrals."""

from __future__ import annotations

from congraph.terms import Rule, differs, rule

_NONZERO = differs("?b", "zero")

#: Name, left, right (None: the pattern is matched but rewrites nothing), conditions.
_TABLE: tuple[tuple, ...] = (
    ("A01", "(add (add ?a ?b) ?c)", "(add ?a (add ?b ?c))"),
    ("A02", "(add ?a (add ?b ?c))", "(add (add ?a ?b) ?c)"),
    ("A03", "(mul (mul ?a ?b) ?c)", "(mul ?a (mul ?b ?c))"),
    ("A04", "(mul ?a (mul ?b ?c))", "(mul (mul ?a ?b) ?c)"),
    ("A05", "(mul ?a (add ?b ?c))", "(add (mul ?a ?b) (mul ?a ?c))"),
    ("A06", "(add (mul ?a ?b) (mul ?a ?c))", "(mul ?a (add ?b ?c))"),
    ("A07", "(sub (mul ?a ?b) (mul ?a ?c))", "(mul ?a (sub ?b ?c))"),
    ("A08", "(mul ?a (sub ?b ?c))", "(sub (mul ?a ?b) (mul ?a ?c))"),
    ("A09", "(add ?a zero)", "?a"),
    ("A10", "(mul ?a one)", "?a"),
    ("A11", "(mul ?a zero)", "zero"),
    ("A12", "(pow ?a one)", "?a"),
    ("A13", "(pow ?a zero)", "one"),
    ("A14", "(sub ?a (mul ?b one))", "(sub ?a ?b)"),
    ("A15", "(sub (add ?a ?b) ?b)", "?a"),
    ("A16", "(mul (div ?a ?b) ?b)", "?a", _NONZERO),
    ("A17", "(div (mul ?a ?b) ?b)", "?a", _NONZERO),
    ("A18", "(add ?a (neg ?a))", "zero"),
    ("A19", "(mul (pow ?a ?b) (pow ?a ?c))", "(pow ?a (add ?b ?c))"),
    ("A20", "(pow (pow ?a ?b) ?c)", "(pow ?a (mul ?b ?c))"),
    ("A21", "(mul ?a (pow ?a ?b))", "(pow ?a (add ?b one))"),
    ("A22", "(pow (mul ?a ?b) ?c)", "(mul (pow ?a ?c) (pow ?b ?c))"),
    ("A23", "(d ?x (add ?a ?b))", "(add (d ?x ?a) (d ?x ?b))"),
    ("A24", "(d ?x (mul ?a ?b))", "(add (mul ?a (d ?x ?b)) (mul ?b (d ?x ?a)))"),
    # The exponent may depend on the variable too.
    ("A25", "(d ?x (pow ?a ?n))", "(mul (pow ?a ?n) (add (mul (d ?x ?a) (div ?n ?a)) (mul (d ?x ?n) (ln ?a))))", differs("?a", "zero"), differs("?n", "zero")),
    ("A26", "(d ?x (sin ?x))", "(cos ?x)"),
    ("A27", "(d ?x (cos ?x))", "(neg (sin ?x))"),
    ("A28", "(d ?x (ln ?x))", "(div one ?x)"),
    ("A29", "(int (add ?a ?b) ?x)", "(add (int ?a ?x) (int ?b ?x))"),
    ("A30", "(int (cos ?x) ?x)", "(sin ?x)"),
    ("A31", "(int (mul ?a ?b) ?x)", "(sub (mul ?a (int ?b ?x)) (int (mul (d ?x ?a) (int ?b ?x)) ?x))"),
    ("A32", "(sub (mul ?a (int ?b ?x)) (int (mul (d ?x ?a) (int ?b ?x)) ?x))", "(int (mul ?a ?b) ?x)"),
)

RULES: tuple[Rule, ...] = tuple(rule(*row) for row in _TABLE)
PATTERNS: dict[str, str] = {row[0]: row[1] for row in _TABLE}
#: Four levels deep, one variable four times.
DEEP = "(add (mul ?f (mul ?a (neg ?f))) (mul ?f (sub ?b ?f)))"
#: Start terms beside those that come from tables.
STARTS = (
    "(d x (add (sin x) (mul x (cos x))))",
    "(int (mul (cos x) x) x)",
    "(add (mul y (mul x (neg y))) (mul y (sub x y)))",
    "(mul (pow x two) (pow x y))",
    "(sub (add x (mul y one)) (mul y one))",
    "(mul (div x y) y)",
    "(d x (ln x))",
    "(add x (neg x))",
)
