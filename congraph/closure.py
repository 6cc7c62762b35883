"""Union-find and congruence closure at scale."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from congraph.checkpoints import cut
from congraph.graph import CongruenceGraph


def components(edges: DataFrame) -> DataFrame:
    """(id, rep) with rep the least id of the component, for ids other than rep; edges(a long, b long).

    Alternating stars: larger neighbours move to the least neighbour, then smaller ones do, until every edge
    leads to a root; rounds grow with the logarithm of the longest path. Two shuffles a round; the driver reads one flag a round.
    """
    edges = cut(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges")
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        down = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(down, "u").select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v"))
        edges = cut(small.where("u <> v").distinct(), "edges")
        forks = edges.groupBy("u").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("u")
        chains = edges.join(edges.select(F.col("u").alias("v")), "v", "left_semi").select("u")
        if not forks.unionByName(chains).take(1):
            return edges.select(F.col("u").alias("id"), F.col("v").alias("rep"))


#: Arguments that are looked up position by position; nodes with more are taken apart into rows.
FEW_ARGS = 4


def canonicalise(nodes: DataFrame, find_map: DataFrame) -> DataFrame:
    """Nodes with the representatives of their class and arguments, equal ones once; ver: the least."""
    rows = nodes.join(find_map.select(F.col("id").alias("cls"), F.col("rep").alias("_c")), "cls", "left").select("sym", F.coalesce("_c", "cls").alias("cls"), "args", "ver")
    out = rows.where(F.size("args") == 0)
    sizes = [r.n for r in nodes.select(F.least(F.size("args"), F.lit(FEW_ARGS + 1)).alias("n")).distinct().collect()]
    for n in sorted(sizes):
        if 0 < n <= FEW_ARGS:
            flat = rows.where(F.size("args") == n).select("sym", "cls", "ver", *[F.col("args")[k].alias(f"_a{k}") for k in range(n)])
            for k in range(n):
                found = find_map.select(F.col("id").alias(f"_a{k}"), F.col("rep").alias("_r"))
                flat = flat.join(found, f"_a{k}", "left").withColumn(f"_a{k}", F.coalesce("_r", f"_a{k}")).drop("_r")
            out = out.unionByName(flat.select("sym", "cls", F.array(*[f"_a{k}" for k in range(n)]).alias("args"), "ver"))
        elif n > FEW_ARGS:
            deep = rows.where(F.size("args") > FEW_ARGS).withColumn("key", F.struct("sym", "cls", "args", "ver"))
            deep = deep.select("key", F.posexplode("args").alias("pos", "id")).join(find_map, "id", "left").select("key", "pos", F.coalesce("rep", "id").alias("id"))
            args = F.transform(F.array_sort(F.collect_set(F.struct("pos", "id"))), lambda x: x["id"])
            out = out.unionByName(deep.groupBy("key").agg(args.alias("args")).select("key.sym", "key.cls", "args", "key.ver"))
    return out.groupBy("sym", "cls", "args").agg(F.min("ver").alias("ver"))


def congruent_pairs(nodes: DataFrame) -> DataFrame:
    """(a, b): classes that hold the same node."""
    least = F.min("cls").over(Window.partitionBy("sym", "args"))
    return nodes.select(least.alias("a"), F.col("cls").alias("b")).where("a <> b")


def merge(graph: CongruenceGraph, pairs: DataFrame) -> CongruenceGraph:
    """The graph with the classes of each pair (a, b) made one; its nodes keep their ids until `rebuild`."""
    old = graph.find_map.select(F.col("id").alias("a"), F.col("rep").alias("b")) if graph.find_map is not None else None
    edges = pairs.select("a", "b") if old is None else pairs.select("a", "b").unionByName(old)
    return graph.with_nodes(graph.nodes, components(edges), congruent=False)


def rebuild(graph: CongruenceGraph) -> CongruenceGraph:
    """The congruence closure: canonical ids throughout, each (sym, args) in one class. The representative is the
    least id of a class, so the order of merges doesn't matter. Congruence climbs one level a round, for as many rounds as
    terms are deep; each round has fewer classes than the one before, so it ends."""
    if graph.find_map is None:
        return graph if graph.congruent else rebuild(graph.with_nodes(graph.nodes, graph.spark.createDataFrame([], "id long, rep long"), False))
    find, nodes = graph.find_map, graph.nodes
    fresh = find
    while True:
        nodes = cut(canonicalise(nodes, fresh), "nodes")
        new = cut(congruent_pairs(nodes), "pairs")
        if not new.take(1):
            return graph.with_nodes(nodes, find)
        # All ids in nodes are representatives now, the least of their classes: only what newly meets is looked up again.
        fresh = components(new)
        moved = find.join(fresh.select(F.col("id").alias("rep"), F.col("rep").alias("_r")), "rep", "left").select("id", F.coalesce("_r", "rep").alias("rep"))
        find = cut(moved.unionByName(fresh), "find")


def insert_terms(graph: CongruenceGraph, terms: DataFrame) -> CongruenceGraph:
    """The graph with ground terms (value, s-expressions) in it; a term that it represents keeps its class."""
    from congraph.sources.files import term_nodes_of

    return rebuild(insert_nodes(graph, cut(term_nodes_of(terms).withColumn("ver", F.lit(graph.version + 1)), "terms")))


def insert_nodes(graph: CongruenceGraph, wanted: DataFrame) -> CongruenceGraph:
    """The graph with nodes (sym, args, cls, ver) added; ones it has keep their class, which then equals the given one."""
    known = graph.nodes
    found = wanted.join(known.select("sym", "args", F.col("cls").alias("old")), ["sym", "args"], "left")
    found = cut(found, "found")
    fresh = found.where("old is null").select("sym", "cls", "args", "ver").dropDuplicates(["sym", "args", "cls"])
    out = graph.with_nodes(known.unionByName(fresh), graph.find_map, congruent=False)
    same = found.where("old is not null and old <> cls").select(F.col("old").alias("a"), F.col("cls").alias("b"))
    return merge(out, same)
