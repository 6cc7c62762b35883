"""Web pages as trees in a congruence graph: el_<tag>(children), cons(head, tail), nil, one leaf for each text."""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from congraph.checkpoints import cut
from congraph.graph import CongruenceGraph
from congraph.operators.match import match
from congraph.sources.shipping import ship_code
from congraph.sources.tables import read_table

_TAG = re.compile(r"<!--.*?-->|<(script|style)\b.*?</\1>|<(/?)([a-zA-Z][a-zA-Z0-9]*)[^>]*>|<![^>]*>", re.S | re.I)
_VOID = frozenset("br hr img input meta link".split())


def _id(*parts) -> int:
    return int.from_bytes(hashlib.blake2b(repr(parts).encode(), digest_size=7).digest(), "little")


def page_nodes(page: str) -> dict[int, tuple[str, tuple[int, ...]]]:
    """Nodes by class id; equal subtrees are one. An element that is never closed ends with its parent."""
    out: dict[int, tuple[str, tuple[int, ...]]] = {}

    def node(sym: str, *args: int, key: str = "") -> int:
        own = _id(sym, key, args)
        out[own] = (sym, args)
        return own

    def close(tag: str, kids: list[int]) -> int:
        tail = node("nil")
        for k in reversed(kids):
            tail = node("cons", k, tail)
        return node(f"el_{tag}", tail)

    stack: list[tuple[str, list[int]]] = [("page", [])]

    def text(piece: str) -> None:
        if piece := " ".join(piece.split()):
            stack[-1][1].append(node("text", key=piece))

    at = 0
    for m in _TAG.finditer(page):
        text(page[at : m.start()])
        at = m.end()
        if not m.group(3):
            continue
        tag = m.group(3).lower()
        if m.group(2):
            if any(t == tag for t, _ in stack[1:]):
                while True:
                    t, kids = stack.pop()
                    stack[-1][1].append(close(t, kids))
                    if t == tag:
                        break
        elif tag in _VOID:
            stack[-1][1].append(close(tag, []))
        else:
            stack.append((tag, []))
    text(page[at:])
    while len(stack) > 1:
        t, kids = stack.pop()
        stack[-1][1].append(close(t, kids))
    close(*stack[0])
    return out


def _nodes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        found: dict = {}
        for page in batch.column("html").to_pylist():
            found.update(page_nodes(page or ""))
        yield pa.record_batch([pa.array([s for s, _ in found.values()], pa.string()), pa.array(list(found), pa.int64()), pa.array([list(a) for _, a in found.values()], pa.list_(pa.int64()))], names=["sym", "cls", "args"])


def lift_markup(spark: SparkSession, sf_dir: str) -> CongruenceGraph:
    ship_code(spark)
    # Text leaves are told apart by their class alone; no pattern asks for one by its words.
    nodes = read_table(spark, sf_dir, "pages").select("html").mapInArrow(_nodes, "sym string, cls long, args array<long>").distinct()
    return CongruenceGraph(spark, nodes=nodes.withColumn("ver", F.lit(0)))


def tree_search(spark: SparkSession, sf_dir: str, strategy: str = "auto") -> DataFrame:
    """pattern, n: repeated neighbours, and list items that begin with a link."""
    g = lift_markup(spark, sf_dir)
    g = g.with_nodes(cut(g.nodes, "markup"))
    rows = [(p, match(g, p, strategy=strategy).count()) for p in ("(cons ?a (cons ?a ?rest))", "(el_li (cons (el_a ?x) ?r))")]
    return spark.createDataFrame(rows, "pattern string, n long")
