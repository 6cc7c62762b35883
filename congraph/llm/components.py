"""Connected components of a distributed edge list, by alternating star contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from congraph.llm.common import Stages


def components(edges: DataFrame, stages: Stages) -> DataFrame:
    """node, component (least node reachable) for every node of edges(a long, b long); loops are allowed.

    Rounds grow with the logarithm of the longest path, and go on until nothing is open.
    """
    edges = stages.write(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges")
    while True:
        # Large star: each node's larger neighbours move to its least neighbour. A hub's edges are grouped only
        # as a minimum, and its neighbours come back by an equi-join that Spark may split.
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.where("u <> v").distinct()
        # Small star: each node and its smaller neighbours move to the least of them.
        down = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(down, "u").select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v"))
        new = stages.write(small.where("u <> v").distinct(), "edges")
        # Stars only: every node with a smaller neighbour has one, and that one has none.
        open_ = new.groupBy("u").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("u").unionByName(new.join(new.select(F.col("u").alias("v")), "v", "left_semi").select("u"))
        edges = new
        if not open_.take(1):
            break
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component"))
