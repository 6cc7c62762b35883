"""Matching as view maintenance: what a change of the relations adds to or takes from the matches."""

from __future__ import annotations

import json
from collections.abc import Mapping, Sequence
from dataclasses import dataclass, field

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from congraph.checkpoints import cut
from congraph.graph import CongruenceGraph, columns_of
from congraph.operators.joins import connected_order
from congraph.operators.match import compiled
from congraph.plans.compile import ConjunctiveQuery

#: Changes and matches carry a weight: +1 in, -1 out.
WEIGHT = "w"


def weighted(df: DataFrame, weight: int = 1) -> DataFrame:
    return df.withColumn(WEIGHT, F.lit(weight).cast("long"))


def _settled(df: DataFrame) -> DataFrame:
    return df.groupBy(*[c for c in df.columns if c != WEIGHT]).agg(F.sum(WEIGHT).alias(WEIGHT)).where(F.col(WEIGHT) != 0)


def match_delta(cq: ConjunctiveQuery, old: Mapping[str, DataFrame], delta: Mapping[str, DataFrame]) -> DataFrame:
    """Changes of the matches for changes (same columns and w) of relations by symbol; old: rows with their weights.

    One term for each atom that changes: atoms before it are new, it is the change, those after it are old; the
    split is by atom, so a symbol that occurs twice is counted right. Each term starts from the change.
    """
    out = None
    for i, changing in enumerate(cq.atoms):
        if changing.sym not in delta:
            continue
        sizes = {a.alias: 0 if k == i else 1 + k for k, a in enumerate(cq.atoms)}
        df = None
        for k in connected_order(cq, sizes):
            a = cq.atoms[k]
            if k == i:
                part = delta[a.sym]
            else:
                part = old[a.sym]
                if k < i and a.sym in delta:
                    part = part.unionByName(delta[a.sym])
            names = columns_of(a.arity)
            weight = part.columns[-1]
            rel = part.toDF(*names, weight)
            one = frame_of_weighted(rel, a).withColumnRenamed(WEIGHT, f"_w{k}")
            keys = [] if df is None else [c for c in df.columns if c in one.columns]
            df = one if df is None else df.join(one, keys) if keys else df.crossJoin(one)
        product = F.lit(1).cast("long")
        for k in range(len(cq.atoms)):
            product = product * F.col(f"_w{k}")
        term = df.select(*cq.head, product.alias(WEIGHT))
        out = term if out is None else out.unionByName(term)
    if out is None:
        raise ValueError("no relation of the query changes")
    return _settled(out)


def frame_of_weighted(rel: DataFrame, atom) -> DataFrame:
    names = columns_of(atom.arity)
    first: dict[str, str] = {}
    for v, c in zip(atom.vars, names):
        if v in first:
            rel = rel.where(F.col(first[v]) == F.col(c))
        first.setdefault(v, c)
    return rel.select(*[F.col(c).alias(v) for v, c in first.items()], WEIGHT)


class Log:
    """A table as a list of written changes, each row with its weight; appending writes the change alone.

    Once RUNS changes have come they are summed into one, so that a read meets few tables and a row is written anew only
    once in RUNS batches.
    """

    RUNS = 8

    def __init__(self, spark: SparkSession, schema: str, parts: Sequence[DataFrame] = ()):
        self.spark, self.schema, self.parts = spark, schema, list(parts)

    def append(self, change: DataFrame) -> None:
        self.parts.append(change)
        if len(self.parts) > self.RUNS:
            self.parts = [cut(_settled(self.weighted), "run")]

    @property
    def weighted(self) -> DataFrame:
        if not self.parts:
            return weighted(self.spark.createDataFrame([], self.schema))
        out = self.parts[0]
        for p in self.parts[1:]:
            out = out.unionByName(p)
        return out

    @property
    def rows(self) -> DataFrame:
        return _settled(self.weighted).drop(WEIGHT)


@dataclass
class MatchState:
    """Relations and matches so far; `advance` takes a change and brings both up to date by writing what changed.

    folder: where the state is kept as well (`resume` reads it), so that a batch that comes again after a restart is known.
    """

    cq: ConjunctiveQuery
    relations: dict[str, Log]
    found: Log
    version: int = 0
    seen: set[int] = field(default_factory=set)
    folder: str | None = None

    @staticmethod
    def empty(graph: CongruenceGraph, pattern, folder: str | None = None) -> MatchState:
        cq = compiled(pattern)
        logs = {a.sym: Log(graph.spark, ", ".join(f"{c} long" for c in columns_of(a.arity))) for a in cq.atoms}
        return MatchState(cq, logs, Log(graph.spark, ", ".join(f"`{v}` long" for v in cq.head)), folder=folder)

    @property
    def matches(self) -> DataFrame:
        return self.found.rows

    def advance(self, delta: Mapping[str, DataFrame], batch: int | None = None) -> DataFrame | None:
        """The change of the matches; a batch number that was seen before changes nothing."""
        if batch is not None and batch in self.seen:
            return None
        delta = {s: cut(d.toDF(*columns_of(len(d.columns) - 2), WEIGHT), "delta") for s, d in delta.items() if s in self.relations}
        change = cut(match_delta(self.cq, {s: log.weighted for s, log in self.relations.items()}, delta), "change")
        for s, d in delta.items():
            self.relations[s].append(d)
        self.found.append(change)
        self.version += 1
        if batch is not None:
            self.seen.add(batch)
        if self.folder is not None:
            self._keep()
        return change

    def _keep(self) -> None:
        """One row: the files of every log and the batches seen. Written last, so a batch counts wholly or not at all."""
        logs = {**{f"rel:{s}": log for s, log in self.relations.items()}, "found": self.found}
        state = {"version": self.version, "seen": sorted(self.seen), "logs": {k: [p.inputFiles() for p in log.parts] for k, log in logs.items()}}
        spark = self.found.spark
        spark.createDataFrame([(self.version, json.dumps(state))], "version int, value string").coalesce(1).write.mode("append").parquet(self.folder)

    @staticmethod
    def resume(graph: CongruenceGraph, pattern, folder: str) -> MatchState:
        """The state as the last finished batch left it; an empty one if there is none."""
        out, spark = MatchState.empty(graph, pattern, folder), graph.spark
        try:
            last = spark.read.schema("version int, value string").parquet(folder).orderBy(F.desc("version")).first()
        except AnalysisException:  # nothing is there yet
            return out
        if last is None:
            return out
        state = json.loads(last.value)

        def log(key: str, old: Log) -> Log:
            schema = f"{old.schema}, {WEIGHT} long"
            return Log(spark, old.schema, [spark.read.schema(schema).parquet(*files) if files else spark.createDataFrame([], schema) for files in state["logs"][key]])

        out.relations = {s: log(f"rel:{s}", old) for s, old in out.relations.items()}
        out.found, out.version, out.seen = log("found", out.found), state["version"], set(state["seen"])
        return out


def canonical_delta(relation: DataFrame, find_map: DataFrame) -> DataFrame:
    """The change that new representatives make to a relation: -1 for rows with a stale id, +1 for what they become."""
    now = relation
    for c in relation.columns:
        found = find_map.select(F.col("id").alias(c), F.col("rep").alias("_r"))
        now = now.join(found, c, "left").withColumn(c, F.coalesce("_r", c)).drop("_r")
    now = now.select(*relation.columns).distinct()
    return weighted(now.exceptAll(relation)).unionByName(weighted(relation.exceptAll(now), -1))
