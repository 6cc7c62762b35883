"""Shards by a k-d tree over metadata.

Every node is cut at the weighted median (weight: bytes) of its widest dimension, until the asked number of
leaves or the target size is reached. The median is found by distributed histograms: each round counts the
weight of 2^12 bins of a 64-bit key, value above and a hash of the id below, and looks on in the bin where the
half lies; a round takes all nodes of a level at once. What reaches the driver is one row for each node.

Cases: null text weighs 1 byte, null metadata counts as the lowest value; equal values of a dimension are cut by
the hash of the id, so ties and copies spread; one value everywhere makes the id's hash decide; an empty table
gives no rows; further columns are left alone; with fewer rows than leaves some leaves stay empty.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from congraph.llm.common import partitions_for, written

BIN_BITS = 12
#: Share of a node's weight that a cut may be off by.
TOLERANCE = 1 / 4096
_KEY_BITS = 62


def _scaled(df: DataFrame, dims: dict[str, Column]) -> DataFrame:
    """Each dimension as a long: 31 bits of its place in the global range, then 31 bits of the id's hash."""
    df = df.select("*", *[F.coalesce(c.cast("double"), F.lit(float("-inf"))).alias(f"d_{n}") for n, c in dims.items()])
    finite = lambda n: F.when(F.col(f"d_{n}") > float("-inf"), F.col(f"d_{n}"))
    ends = df.agg(*[f(finite(n)).alias(f"{k}_{n}") for n in dims for k, f in (("lo", F.min), ("hi", F.max))]).first()
    low = F.shiftrightunsigned(F.xxhash64("doc_id"), 33)
    out = []
    for n in dims:
        lo, hi = ends[f"lo_{n}"], ends[f"hi_{n}"]
        span = (hi - lo) if lo is not None and hi > lo else 1.0
        place = F.greatest(F.lit(0.0), (F.col(f"d_{n}") - F.lit(lo or 0.0)) / F.lit(span))
        out.append((F.shiftleft((place * F.lit(float((1 << 31) - 1))).cast("long"), 31) + low).alias(f"k_{n}"))
    return df.select("doc_id", "size", "text_crc32", *out)


def kd_leaves(rows: DataFrame, dims: dict[str, Column], leaves: int | None = None, target_bytes: int | None = None) -> DataFrame:
    """doc_id, size, text_crc32, shard: rows (with these and what dims reads) cut into leaves of near equal weight."""
    table = written(_scaled(rows, dims), "kd")
    total = table.agg(F.sum("size").alias("s")).first().s or 0
    leaves = leaves or max(1, -(-total // max(1, target_bytes or total or 1)))
    #: node -> (first leaf, leaves below it)
    nodes = {0: (0, leaves)}
    frame, names, depth = table.withColumn("node", F.lit(0)), list(dims), 0
    spark = rows.sparkSession
    while any(n > 1 for _, n in nodes.values()):
        ends = frame.groupBy("node").agg(F.sum("size").alias("w"), *[F.min(f"k_{n}").alias(f"lo_{n}") for n in names], *[F.max(f"k_{n}").alias(f"hi_{n}") for n in names]).collect()
        search = {}
        for r in ends:
            first, n = nodes[r.node]
            if n > 1:
                widest = max(names, key=lambda d: (r[f"hi_{d}"] >> 31) - (r[f"lo_{d}"] >> 31))
                # half the leaves go left; so does that share of the weight
                search[r.node] = {"dim": names.index(widest), "prefix": 0, "goal": r.w * (n // 2) / n, "w": r.w, "left": 0.0}
        cuts, shift = {}, _KEY_BITS
        while search:
            upper, shift = shift, max(0, shift - BIN_BITS)
            state = spark.createDataFrame([(k, s["dim"], s["prefix"], float(s["goal"] - s["left"])) for k, s in search.items()], "node int, dim int, prefix long, goal double")
            key = F.element_at(F.array(*[F.col(f"k_{n}") for n in names]), F.col("dim") + 1)
            bins = (
                frame.join(F.broadcast(state), "node")
                .where(F.shiftright(key, upper) == F.col("prefix"))
                .groupBy("node", "goal", F.shiftright(key, shift).alias("bin"))
                .agg(F.sum("size").alias("w"), F.count(F.lit(1)).alias("n"))
            )
            run = W.partitionBy("node").orderBy("bin").rowsBetween(W.unboundedPreceding, 0)
            hit = bins.withColumn("upto", F.sum("w").over(run)).where(F.col("upto") >= F.col("goal")).groupBy("node").agg(F.min_by(F.struct("bin", "w", "n", "upto"), "bin").alias("x"))
            for r in hit.collect():
                s, before = search[r.node], r.x.upto - r.x.w
                goal = s["goal"] - s["left"]
                if shift == 0 or r.x.n == 1 or r.x.w <= TOLERANCE * s["w"]:
                    whole = r.x.upto - goal <= goal - before  # the bin goes where the error is less
                    cuts[r.node] = (s["dim"], ((r.x.bin + whole) << shift) - 1)
                    del search[r.node]
                else:
                    s["prefix"], s["left"] = r.x.bin, s["left"] + before
        kids, rules = {}, []
        for k, (first, n) in nodes.items():
            if k in cuts:
                kids[2 * k + 1], kids[2 * k + 2] = (first, n // 2), (first + n // 2, n - n // 2)
                rules.append((k, *cuts[k]))
            else:
                kids[k] = (first, n) if n == 1 else (first, 1)  # an empty node needs no cut
        nodes, depth = kids, depth + 1
        if not rules:
            break
        # As many rows as nodes: what is broadcast grows with the number of shards, not with the corpus.
        table_of = spark.createDataFrame(rules, "node int, dim int, cut long")
        key = F.element_at(F.array(*[F.col(f"k_{n}") for n in names]), F.col("dim") + 1)
        frame = frame.join(F.broadcast(table_of), "node", "left").withColumn("node", F.when(F.col("dim").isNull(), F.col("node")).otherwise(2 * F.col("node") + 1 + (key > F.col("cut")).cast("int"))).drop("dim", "cut")
        if depth % 3 == 0:
            frame = written(frame, "kd-level")
    shards = spark.createDataFrame([(k, f) for k, (f, _) in nodes.items()], "node int, shard int")
    return frame.join(F.broadcast(shards), "node").select("doc_id", "size", "text_crc32", "shard")


def with_slots(leaves: DataFrame) -> DataFrame:
    """Adds slot, gapless from 0 in each shard: ranks within small parts, then the parts' sizes added up."""
    parts = 4 * partitions_for(leaves.sparkSession)
    leaves = written(leaves.withColumn("part", F.pmod(F.xxhash64("doc_id", "text_crc32"), F.lit(parts)).cast("int")), "leaves")
    sizes = leaves.groupBy("shard", "part").agg(F.count(F.lit(1)).alias("n"))
    before = W.partitionBy("shard").orderBy("part").rowsBetween(W.unboundedPreceding, 0)
    bases = sizes.select("shard", "part", (F.sum("n").over(before) - F.col("n")).alias("base"))
    ranked = leaves.withColumn("r", F.row_number().over(W.partitionBy("shard", "part").orderBy("doc_id", "text_crc32", "size")))
    return ranked.join(bases, ["shard", "part"]).withColumn("slot", F.col("base") + F.col("r") - 1).drop("part", "base", "r")


def shard_documents(docs: DataFrame, leaves: int | None = 8, target_bytes: int | None = None) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard over all rows of a table of documents."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    code = lambda c: F.crc32(F.coalesce(F.col(c).cast("string"), F.lit("")).cast("binary"))
    size = (F.octet_length(text) + 1).cast("long")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), size.alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), *[(code(c) if c in docs.columns else F.lit(0)).alias(f"m_{c}") for c in ("lang", "source")])
    dims = {"size": F.log2("size"), "doc_id": F.col("doc_id"), "lang": F.col("m_lang"), "source": F.col("m_source")}
    placed = with_slots(kd_leaves(rows, dims, leaves, target_bytes))
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), F.col("shard").cast("int").alias("shard"), F.col("slot").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
