"""Patterns and rewrite rules of a partial evaluator with explicit `let`; a fresh name is the term `fresh(v, e)`."""

from __future__ import annotations

from congraph.terms import Rule, differs, rule

_OTHER = differs("?v", "?w")

_TABLE: tuple[tuple, ...] = (
    ("B01", "(app (lam ?v ?b) ?e)", "(let ?v ?e ?b)"),
    ("B02", "(let ?v ?e (var ?v))", "?e"),
    ("B03", "(let ?v ?e (app ?a ?b))", "(app (let ?v ?e ?a) (let ?v ?e ?b))"),
    ("B04", "(let ?v ?e (add ?a ?b))", "(add (let ?v ?e ?a) (let ?v ?e ?b))"),
    ("B05", "(let ?v ?e (eq ?a ?b))", "(eq (let ?v ?e ?a) (let ?v ?e ?b))"),
    ("B06", "(let ?v ?e (if ?c ?t ?f))", "(if (let ?v ?e ?c) (let ?v ?e ?t) (let ?v ?e ?f))"),
    ("B07", "(let ?v ?e (lam ?v ?b))", "(lam ?v ?b)"),
    ("B08", "(let ?v ?e (lam ?w ?b))", "(lam (fresh ?w ?e) (let ?v ?e (let ?w (var (fresh ?w ?e)) ?b)))", _OTHER),
    ("B09", "(let ?v ?e (var ?w))", "(var ?w)", _OTHER),
    ("B10", "(let ?v ?e true)", "true"),
    ("B11", "(if true ?t ?f)", "?t"),
    ("B12", "(if false ?t ?f)", "?f"),
    ("B13", "(if (eq (var ?x) ?e) ?t ?f)", "(if (eq ?e (var ?x)) ?t ?f)"),
    ("B14", "(add (add ?a ?b) ?c)", "(add ?a (add ?b ?c))"),
    ("B15", "(eq (add ?a ?b) (add ?a ?c))", "(eq ?b ?c)"),
    ("B16", "(app (fix ?v ?b) ?e)", "(app (let ?v (fix ?v ?b) ?b) ?e)"),
    ("B17", "(app (app ?f ?a) ?a)", "(app (app ?f ?a) ?a)"),
    ("B18", "(let ?v ?e (let ?v ?d ?b))", "(let ?v (let ?v ?e ?d) ?b)"),
)

RULES: tuple[Rule, ...] = tuple(rule(*row) for row in _TABLE)
PATTERNS: dict[str, str] = {row[0]: row[1] for row in _TABLE}
STARTS = (
    "(app (lam x (add (var x) (var x))) (var y))",
    "(if (eq (var x) (var y)) true false)",
    "(app (fix f (lam n (if (eq (var n) zero) zero (app (var f) (var n))))) one)",
    "(let x one (lam y (app (var x) (var y))))",
    "(eq (add (var x) one) (add (var x) zero))",
    "(let x (var y) (let x (var z) (app (app (var x) (var z)) (var z))))",
)
