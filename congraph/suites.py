"""Start graphs of the two suites, from fixed terms and from the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from congraph import rules_algebra, rules_binding
from congraph.checkpoints import cut
from congraph.graph import CongruenceGraph, by_symbol
from congraph.intern import key_id
from congraph.operators.match import compiled, match
from congraph.saturate import RULES_IN_PLAN, Saturation, saturate
from congraph.sources.files import term_nodes_of
from congraph.sources.tables import read_table


def _graph(spark: SparkSession, terms: DataFrame) -> CongruenceGraph:
    return CongruenceGraph(spark, nodes=cut(by_symbol(term_nodes_of(terms)), "start"))


def price_terms(spark: SparkSession, sf_dir: str, orders: int | None = None) -> DataFrame:
    """A line's price, discount and tax as a product. orders: only those with a smaller key, to set a suite's size."""
    df = read_table(spark, sf_dir, "lineitem")
    if orders is not None:
        df = df.where(F.col("l_orderkey") < orders)
    dec = lambda c: F.regexp_replace(F.col(c).cast("decimal(14,2)").cast("string"), "[.]", "_")
    text = F.concat(F.lit("(mul (mul p"), dec("l_extendedprice"), F.lit(" (sub one d"), dec("l_discount"), F.lit(")) (add one t"), dec("l_tax"), F.lit("))"))
    return df.select(text.alias("value")).distinct()


def binding_terms(spark: SparkSession, sf_dir: str, parts: int | None = None, swapped: bool = False) -> DataFrame:
    """A part's brand bound in an application of two words of its name, the last and the first; swapped: the other way round."""
    df = read_table(spark, sf_dir, "part")
    if parts is not None:
        df = df.where(F.col("p_partkey") < parts)
    word = lambda c: F.regexp_replace(c, "[^A-Za-z0-9]", "_")
    words = F.split("p_name", " ")
    brand = F.concat(F.lit("v_"), word(F.col("p_brand")))
    body = F.concat(F.lit("(app (lam "), brand, F.lit(" (app (var "), brand, F.lit(") w_"), word(words[0] if swapped else F.element_at(words, -1)), F.lit(")) w_"), word(F.element_at(words, -1) if swapped else words[0]), F.lit(")"))
    return df.select(body.alias("value")).distinct()


def suite(spark: SparkSession, sf_dir: str, name: str, node_limit: int, iter_limit: int = 2, rows: int | None = 20) -> Saturation:
    """A saturated graph of the suite: `algebra` or `binder`. rows: keys below this one only; None: the whole table."""
    rules, fixed, made = (rules_algebra.RULES, rules_algebra.STARTS, price_terms(spark, sf_dir, rows)) if name == "algebra" else (rules_binding.RULES, rules_binding.STARTS, binding_terms(spark, sf_dir, rows))
    starts = spark.createDataFrame([(x,) for x in (*fixed, "zero", "one", "true", "false")], "value string")
    return saturate(_graph(spark, starts.unionByName(made)), rules, node_limit, iter_limit)


def suite_counts(spark: SparkSession, sf_dir: str, name: str, strategy: str = "auto") -> DataFrame:
    """pattern, n: matches of every pattern of the suite on the graph of all lines or parts after a round of rewriting.

    2,000 nodes only end the saturation; no row of the table is left out."""
    graph = suite(spark, sf_dir, name, 2000, 1, None).graph
    # Every pattern reads some relations of it.
    graph = CongruenceGraph(spark, nodes=cut(by_symbol(graph.nodes), "suite"))
    patterns = dict(rules_algebra.PATTERNS if name == "algebra" else rules_binding.PATTERNS)
    if name == "algebra":
        patterns["DEEP"] = rules_algebra.DEEP
    rules = {r.name: r for r in (rules_algebra.RULES if name == "algebra" else rules_binding.RULES)}
    graph.sizes([(a.sym, a.arity) for p in patterns.values() for a in compiled(p).atoms])
    rows, names = [], list(patterns)
    for at in range(0, len(names), RULES_IN_PLAN):
        counts = None
        for k in names[at : at + RULES_IN_PLAN]:
            df = match(graph, patterns[k], strategy=strategy, where=rules[k].conditions if k in rules else ())
            one = df.agg(F.lit(k).alias("pattern"), F.count(F.lit(1)).alias("n"))
            counts = one if counts is None else counts.unionByName(one)
        rows += [(r.pattern, r.n) for r in counts.collect()]
    return spark.createDataFrame(rows, "pattern string, n long")


def associativity_levels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """n: matches of the associativity pattern on the start terms, a chain of sums for each customer's orders."""
    by = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    orders = read_table(spark, sf_dir, "orders").where("o_orderkey is not null")
    rows = orders.select("o_orderkey", F.lag("o_orderkey").over(by).alias("before"), F.row_number().over(by).alias("k"))
    leaf, total = key_id("order", F.col("o_orderkey")), key_id("chain", F.col("o_orderkey"))
    # The sum up to an order is known by that order; up to the first one it is the order itself.
    above = F.when(F.col("k") == 2, key_id("order", F.col("before"))).otherwise(key_id("chain", F.col("before")))
    leaves = rows.select(F.concat(F.lit("o"), F.col("o_orderkey").cast("string")).alias("sym"), leaf.alias("cls"), F.array().cast("array<long>").alias("args"), F.lit(0).alias("ver"))
    sums = rows.where("k >= 2").select(F.lit("add").alias("sym"), total.alias("cls"), F.array(above, leaf).alias("args"), F.lit(0).alias("ver"))
    graph = CongruenceGraph(spark, nodes=cut(leaves.unionByName(sums), "start"))
    return match(graph, rules_algebra.PATTERNS["A01"], strategy="binary").agg(F.count(F.lit(1)).alias("n"))
