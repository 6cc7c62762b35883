"""The graph engine as SQL text alone: insertion, merging, rebuilding and matching over two tables, `node` and `find`.

The statements are plain enough for Spark SQL and DuckDB alike, so either can run the engine.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from congraph.checkpoints import cut
from congraph.operators.match import compiled


def match_sql(pattern, relation=lambda sym: f"rel_{sym}") -> str:
    """SELECT for a pattern or a list of them over relations (id, a1 .. ak)."""
    cq = compiled(pattern)
    place: dict[str, str] = {}
    where: list[str] = []
    for a in cq.atoms:
        for v, c in zip(a.vars, ["id", *(f"a{k}" for k in range(1, a.arity + 1))]):
            if v in place:
                where.append(f"{place[v]} = {a.alias}.{c}")
            place.setdefault(v, f"{a.alias}.{c}")
    columns = ", ".join(f"{place[v]} AS {v}" for v in cq.head)
    tables = ", ".join(f"{relation(a.sym)} {a.alias}" for a in cq.atoms)
    return f"SELECT {columns} FROM {tables}" + (f" WHERE {' AND '.join(where)}" if where else "")


def relation_sql(sym: str, arity: int, nodes: str = "node") -> str:
    """A relation as a view on nodes (sym, cls, a1, a2, ..); ids are canonical after a rebuild."""
    return f"SELECT cls AS id{''.join(f', a{k}' for k in range(1, arity + 1))} FROM {nodes} WHERE sym = '{sym}'"


def insert_sql(nodes: str, new: str, width: int) -> str:
    """Nodes with those of `new` that the graph lacks."""
    columns = ", ".join(f"a{k}" for k in range(1, width + 1))
    same = " AND ".join(["n.sym = w.sym", *(f"coalesce(n.a{k}, -1) = coalesce(w.a{k}, -1)" for k in range(1, width + 1))])
    return f"SELECT sym, cls, {columns} FROM {nodes} UNION ALL SELECT DISTINCT w.sym, w.cls, {', '.join(f'w.a{k}' for k in range(1, width + 1))} FROM {new} w WHERE NOT EXISTS (SELECT 1 FROM {nodes} n WHERE {same})"


def canonical_sql(nodes: str, find: str, width: int) -> str:
    """Nodes with representatives throughout, each once."""
    joins = "".join(f" LEFT JOIN {find} f{k} ON n.{'cls' if k == 0 else f'a{k}'} = f{k}.id" for k in range(width + 1))
    columns = ["coalesce(f0.rep, n.cls) AS cls", *(f"coalesce(f{k}.rep, n.a{k}) AS a{k}" for k in range(1, width + 1))]
    return f"SELECT DISTINCT n.sym, {', '.join(columns)} FROM {nodes} n{joins}"


def congruent_sql(nodes: str, width: int) -> str:
    """Pairs of classes that hold one node."""
    same = " AND ".join(["x.sym = y.sym", *(f"coalesce(x.a{k}, -1) = coalesce(y.a{k}, -1)" for k in range(1, width + 1))])
    return f"SELECT DISTINCT x.cls AS id, y.cls AS rep FROM {nodes} x JOIN {nodes} y ON {same} WHERE x.cls > y.cls"


def contract_sql(edges: str) -> str:
    """One round of pointing every id at the least id that it is joined with, and that id's own."""
    both = f"(SELECT id, rep FROM {edges} UNION SELECT rep, id FROM {edges} UNION SELECT id, id FROM {edges} UNION SELECT rep, rep FROM {edges})"
    return f"SELECT a.id, min(b.rep) AS rep FROM {both} a JOIN {both} b ON a.rep = b.id GROUP BY a.id"


class SqlEngine:
    """The statements above on Spark; each step is a written table, as SQL on views would grow without end."""

    def __init__(self, spark: SparkSession, width: int):
        self.spark, self.width = spark, width

    def _run(self, text: str, **views: DataFrame) -> DataFrame:
        for name, df in views.items():
            df.createOrReplaceTempView(name)
        return cut(self.spark.sql(text), "sql")

    def insert(self, nodes: DataFrame, new: DataFrame) -> DataFrame:
        return self._run(insert_sql("node", "fresh", self.width), node=nodes, fresh=new)

    def find(self, pairs: DataFrame) -> DataFrame:
        """id, rep of merged pairs (id, rep)."""
        edges = pairs
        while True:
            new = self._run(contract_sql("edge"), edge=edges)
            if new.exceptAll(edges).isEmpty():
                return new
            edges = new

    def rebuild(self, nodes: DataFrame, pairs: DataFrame) -> DataFrame:
        while True:
            nodes = self._run(canonical_sql("node", "find", self.width), node=nodes, find=self.find(pairs))
            pairs = self._run(congruent_sql("node", self.width), node=nodes)
            if pairs.isEmpty():
                return nodes

    def match(self, nodes: DataFrame, pattern, arities: dict[str, int]) -> DataFrame:
        nodes.createOrReplaceTempView("node")
        for sym, k in arities.items():
            self.spark.sql(relation_sql(sym, k)).createOrReplaceTempView(f"rel_{sym}")
        return self.spark.sql(match_sql(pattern))


def view_matches(name: str, df: DataFrame) -> None:
    """Matches as a view `match_<name>` for SQL users."""
    df.createOrReplaceTempView(f"match_{name}")

