"""Congruence graphs as DataFrames: a relation for each symbol, class id first.

A graph is given by its relations (what the lifts make) or by its nodes (sym, cls, args), the form that
insertion, merging and rebuilding work on; each form gives the other.
"""

from __future__ import annotations

import json
from collections.abc import Iterable, Mapping
from dataclasses import replace
from typing import TYPE_CHECKING

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from congraph.checkpoints import cut, cut_parts
from congraph.terms import App, Pattern, Var, as_pattern

if TYPE_CHECKING:
    from congraph.plans.compile import ConjunctiveQuery

NODES = "sym string, cls long, args array<long>, ver int"


def columns_of(arity: int) -> list[str]:
    return ["id", *(f"a{k}" for k in range(1, arity + 1))]


def by_symbol(nodes: DataFrame) -> DataFrame:
    """nodes in order of their symbols: written so, a relation reads the files that hold its symbol and no others."""
    return nodes.repartitionByRange("sym", "cls").sortWithinPartitions("sym")


class CongruenceGraph:
    def __init__(self, spark: SparkSession, relations: Mapping[str, DataFrame] | None = None, nodes: DataFrame | None = None, find_map: DataFrame | None = None, congruent: bool = True, version: int = 0, parts: Mapping[str, tuple[DataFrame, DataFrame]] | None = None):
        if (relations is None) == (nodes is None):
            raise ValueError("a graph is made of its relations or of its nodes")
        self.spark, self._relations, self._nodes = spark, dict(relations or {}), nodes
        #: (id, rep) of the ids that aren't their own representative; None: none.
        self.find_map, self.congruent, self.version = find_map, congruent, version
        #: Two relations whose natural join a relation is, by its symbol; columns as in the relation, class id first.
        self._parts = dict(parts or {})
        self._sizes: dict[tuple[str, int], int] = {}
        self._constants: dict[str, int | None] = {}
        self._stored: dict[tuple[str, int], DataFrame] = {}

    # -- forms -------------------------------------------------------------------------------------------
    def rel(self, sym: str, arity: int) -> DataFrame:
        """id, a1 .. ak; a symbol that the graph lacks gives no rows."""
        names = columns_of(arity)
        if (sym, arity) in self._stored:
            return self._stored[sym, arity]
        if self._nodes is None:
            df = self._relations.get(sym)
            if df is None and "/" in sym and sym.split("/")[0] in self._parts:
                df = self._parts[sym.split("/")[0]][int(sym.split("/")[1])]
            if df is None or len(df.columns) != arity + 1:
                return self.spark.createDataFrame([], ", ".join(f"{c} long" for c in names))
            return df.toDF(*names)
        at = self._nodes.where((F.col("sym") == sym) & (F.size("args") == arity))
        return at.select(F.col("cls").alias("id"), *[F.col("args")[k].alias(f"a{k + 1}") for k in range(arity)])

    def store(self, symbols: Iterable[tuple[str, int]]) -> None:
        """Writes the relations that a lift derives, once for each graph: what reads them often then reads files. Relations of
        a graph of nodes are filters of a written table already."""
        for sym, arity in symbols:
            if self._nodes is None and sym in self._relations and (sym, arity) not in self._stored:
                self._stored[sym, arity] = cut_parts([self.rel(sym, arity)], f"rel-{sym}")

    @property
    def nodes(self) -> DataFrame:
        if self._nodes is not None:
            return self._nodes
        out = None
        for sym, df in self._relations.items():
            args = df.columns[1:]
            made = df.select(F.lit(sym).alias("sym"), F.col(df.columns[0]).alias("cls"), (F.array(*args) if args else F.array().cast("array<long>")).alias("args"), F.lit(self.version).alias("ver"))
            out = made if out is None else out.unionByName(made)
        return out

    def with_nodes(self, nodes: DataFrame, find_map: DataFrame | None = None, congruent: bool = True) -> CongruenceGraph:
        return CongruenceGraph(self.spark, nodes=nodes, find_map=find_map, congruent=congruent, version=self.version + 1)

    def relations(self) -> dict[str, DataFrame]:
        """The database of the graph: a relation for each symbol and arity."""
        if self._nodes is None:
            return {s: self.rel(s, len(d.columns) - 1) for s, d in self._relations.items()}
        kinds = self._nodes.select("sym", F.size("args").alias("k")).distinct().collect()
        return {r.sym: self.rel(r.sym, r.k) for r in kinds}

    def relations_delta(self, since: int) -> dict[str, DataFrame]:
        """Of each symbol the rows of nodes made after version `since`: what a rebuild added to the database."""
        new = self.nodes.where(F.col("ver") > since)
        return CongruenceGraph(self.spark, nodes=new, congruent=self.congruent, version=self.version).relations()

    # -- statistics --------------------------------------------------------------------------------------
    def sizes(self, symbols: Iterable[tuple[str, int]]) -> dict[tuple[str, int], int]:
        """Rows by (symbol, arity), counted once for each graph and in one job for all that are missing."""
        missing = [s for s in dict.fromkeys(symbols) if s not in self._sizes]
        if missing and self._nodes is not None and not self._parts:
            kinds = self._nodes.where(F.col("sym").isin(sorted({sym for sym, _ in missing}))).groupBy("sym", F.size("args").alias("k"))
            found = {(r.sym, r.k): r.n for r in kinds.agg(F.count(F.lit(1)).alias("n")).collect()}
            self._sizes.update({s: found.get(s, 0) for s in missing})
        elif missing:
            counts = None
            for k, (sym, arity) in enumerate(missing):
                one = self._size_of(sym, arity).select(F.lit(k).alias("k"), "n")
                counts = one if counts is None else counts.unionByName(one)
            found = {r.k: r.n for r in counts.collect()}
            self._sizes.update({s: found[k] for k, s in enumerate(missing)})
        return {s: self._sizes[s] for s in symbols}

    def _size_of(self, sym: str, arity: int) -> DataFrame:
        """n: rows of a relation; of one that is a join, from the rows of both parts under each key, without making it."""
        if sym not in self._parts:
            return self.rel(sym, arity).agg(F.count(F.lit(1)).alias("n"))
        a, b = self._parts[sym]
        on = [c for c in a.columns if c in b.columns]
        count = lambda df, n: df.groupBy(*on).agg(F.count(F.lit(1)).alias(n))
        return count(a, "_a").join(count(b, "_b"), on).agg(F.coalesce(F.sum(F.col("_a") * F.col("_b")), F.lit(0).cast("long")).alias("n"))

    def unfolded(self, cq: ConjunctiveQuery) -> ConjunctiveQuery:
        """cq with the two parts of a relation that is a join in place of each atom of it."""
        atoms: list = []
        for a in cq.atoms:
            if a.sym not in self._parts:
                atoms.append(a)
                continue
            names = dict(zip(self._relations[a.sym].columns, a.vars))
            atoms += [replace(a, sym=f"{a.sym}/{k}", vars=tuple(names[c] for c in part.columns), alias=f"{a.alias}_{k}") for k, part in enumerate(self._parts[a.sym])]
        return replace(cq, atoms=tuple(atoms))

    def constant(self, sym: str) -> int | None:
        """Class of a constant."""
        if sym not in self._constants:
            row = self.rel(sym, 0).first()
            self._constants[sym] = None if row is None else row.id
        return self._constants[sym]

    def class_of_term(self, term: Pattern | str) -> int | None:
        """Class of a ground term, bottom up; None if the graph doesn't represent it."""
        term = as_pattern(term)
        if isinstance(term, Var):
            raise ValueError("a ground term has no variables")
        args = [self.class_of_term(a) for a in term.args]
        if any(a is None for a in args):
            return None
        if not args:
            return self.constant(term.sym)
        df = self.rel(term.sym, len(args))
        for k, a in enumerate(args):
            df = df.where(F.col(f"a{k + 1}") == a)
        row = df.first()
        return None if row is None else row.id

    def represented(self, terms: DataFrame) -> DataFrame:
        """value, cls: the class of each ground term (value, an s-expression) or null if the graph doesn't represent it.

        All terms at once, a level of arguments a round: a node whose arguments have classes is looked up under them.
        """
        from congraph.sources.files import term_nodes_of, term_roots

        todo = cut(term_nodes_of(terms).select("sym", F.col("cls").alias("own"), "args"), "terms")
        leaf = todo.where(F.size("args") == 0).select("own", "sym", F.col("args").alias("at"))
        known = None
        while True:
            found = cut(leaf.join(self.nodes.select("sym", F.col("args").alias("at"), "cls"), ["sym", "at"]).groupBy("own").agg(F.min("cls").alias("cls")), "found")
            known = found if known is None else known.unionByName(found)
            if not found.take(1):
                return term_roots(terms).join(known, "own", "left").select("value", "cls")
            # Nodes that hold a term of this round and whose arguments are all known now.
            rows = todo.join(known.select("own"), "own", "left_anti").select("own", "sym", F.size("args").alias("k"), F.posexplode("args").alias("pos", "arg"))
            rows = rows.join(known.select(F.col("own").alias("arg"), "cls"), "arg")
            # As many rows as the symbol has arguments.
            ready = rows.groupBy("own", "sym", "k").agg(F.array_sort(F.collect_list(F.struct("pos", "cls"))).alias("r")).where(F.size("r") == F.col("k"))
            tried = cut(ready.select("own", "sym", F.transform("r", lambda x: x["cls"]).alias("at")), "ready")
            todo = cut(todo.join(tried.select("own"), "own", "left_anti"), "terms")
            leaf = tried

    # -- views and lookups -------------------------------------------------------------------------------
    def members(self) -> DataFrame:
        """cls, nodes: for inspection, as a class may hold any number of nodes."""
        return self.nodes.groupBy("cls").agg(F.sort_array(F.collect_list(F.struct("sym", "args"))).alias("nodes"))

    def lookup(self, wanted: DataFrame) -> DataFrame:
        """wanted (sym, args) with the class that holds the node, or null."""
        return wanted.join(self.nodes.select("sym", "args", "cls"), ["sym", "args"], "left")

    def canonical(self, df: DataFrame, *cols: str) -> DataFrame:
        """df with the representatives of the ids in cols."""
        if self.find_map is None:
            return df
        for c in cols:
            found = self.find_map.select(F.col("id").alias(c), F.col("rep").alias("_rep"))
            df = df.join(found, c, "left").withColumn(c, F.coalesce("_rep", c)).drop("_rep")
        return df

    def violations(self) -> DataFrame:
        """(sym, args) that several classes hold; none in a congruent graph."""
        return self.nodes.groupBy("sym", "args").agg(F.count_distinct("cls").alias("classes")).where("classes > 1")

    def count_terms(self, depth: int) -> DataFrame:
        """cls, terms: represented terms of at most this depth; cycles make it grow without end."""
        nodes = self.nodes
        known = nodes.where(F.size("args") == 0).groupBy("cls").agg(F.count(F.lit(1)).cast("decimal(38,0)").alias("terms"))
        for _ in range(depth - 1):
            rows = nodes.select("cls", "sym", "args", F.posexplode_outer("args").alias("pos", "arg"))
            rows = rows.join(known.select(F.col("cls").alias("arg"), "terms"), "arg", "left")
            ways = F.when(F.col("pos").isNull(), F.lit(1)).otherwise(F.coalesce("terms", F.lit(0)))
            listed = rows.groupBy("cls", "sym", "args").agg(F.collect_list(ways.cast("decimal(38,0)")).alias("w"))
            one = F.aggregate("w", F.lit(1).cast("decimal(38,0)"), lambda a, x: (a * x).cast("decimal(38,0)"))
            known = listed.groupBy("cls").agg(F.sum(one).cast("decimal(38,0)").alias("terms")).where("terms > 0")
        return known

    # -- files -------------------------------------------------------------------------------------------
    def save(self, path: str) -> None:
        """Nodes by symbol, the map of ids and a manifest."""
        self.nodes.write.partitionBy("sym").parquet(f"{path}/nodes")
        if self.find_map is not None:
            self.find_map.write.parquet(f"{path}/find_map")
        manifest = json.dumps({"version": self.version, "congruent": self.congruent, "find_map": self.find_map is not None})
        self.spark.createDataFrame([(manifest,)], "value string").coalesce(1).write.text(f"{path}/manifest")

    @staticmethod
    def load(spark: SparkSession, path: str) -> CongruenceGraph:
        m = json.loads(spark.read.text(f"{path}/manifest").first().value)
        nodes = spark.read.parquet(f"{path}/nodes").selectExpr("cast(sym as string) sym", "cls", "args", "ver")
        return CongruenceGraph(spark, nodes=nodes, find_map=spark.read.parquet(f"{path}/find_map") if m["find_map"] else None, congruent=m["congruent"], version=m["version"])


def graph_of(spark: SparkSession, nodes: Iterable[tuple[str, int, Iterable[int]]], **kind) -> CongruenceGraph:
    """A small graph from literals (sym, class, args)."""
    return CongruenceGraph(spark, nodes=spark.createDataFrame([(s, c, list(a), 0) for s, c, a in nodes], NODES), **kind)


def term_nodes(terms: Iterable[Pattern | str]) -> list[App]:
    """Distinct applications of ground terms, arguments before what they are in."""
    out: dict[App, None] = {}

    def visit(t):
        for a in t.args:
            visit(a)
        out.setdefault(t)

    for t in terms:
        visit(as_pattern(t))
    return list(out)
