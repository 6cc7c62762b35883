"""Congruence graphs from tables. Each lift is lazy: a relation is read only if a query has an atom of it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from congraph.closure import components
from congraph.graph import CongruenceGraph
from congraph.intern import constant_id, hash_id, key_id
from congraph.sources.tables import read_table


def _id(ns: str, column: str):
    return key_id(ns, F.col(column))


def lift_star(spark: SparkSession, sf_dir: str) -> CongruenceGraph:
    """N leaves; every g(k) in one class, every f(k, that class) in another: O(N) nodes for N^2 terms."""
    part = read_table(spark, sf_dir, "part").select(_id("part", "p_partkey").alias("k"))
    g, f = constant_id("class", 0), constant_id("class", 1)
    return CongruenceGraph(spark, {"g": part.select(F.lit(g).alias("id"), "k"), "f": part.select(F.lit(f).alias("id"), "k", F.lit(g).alias("g")), "leaf": part.select("k", F.col("k").alias("a"))})


def lift_trade(spark: SparkSession, sf_dir: str) -> CongruenceGraph:
    """Orders, their lines, buyers, vendors and where these are at home."""
    t = {n: read_table(spark, sf_dir, n) for n in ("nation", "customer", "supplier", "orders", "lineitem")}
    nation = _id("nation", "n_nationkey")
    customer = t["customer"].select(_id("customer", "c_custkey").alias("c"), _id("nation", "c_nationkey").alias("n"))
    supplier = t["supplier"].select(_id("supplier", "s_suppkey").alias("s"), _id("nation", "s_nationkey").alias("n"))
    buyer = t["orders"].select(_id("customer", "o_custkey").alias("c"), _id("order", "o_orderkey").alias("o"))
    triple = t["lineitem"].select("l_orderkey", "l_partkey", "l_suppkey").distinct()
    line = triple.select(hash_id("line", *map(F.col, triple.columns)).alias("l"), _id("order", "l_orderkey").alias("o"), _id("part", "l_partkey").alias("p"), _id("supplier", "l_suppkey").alias("s"))
    pairs = t["lineitem"].select("l_partkey", "l_suppkey").distinct()
    item = pairs.select(hash_id("item", F.col("l_partkey"), F.col("l_suppkey")).alias("i"), _id("part", "l_partkey").alias("p"), _id("supplier", "l_suppkey").alias("s"))
    # Who ships where: pairs are made small before they meet nations.
    served = t["lineitem"].select("l_orderkey", "l_suppkey").distinct().join(t["orders"].select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey").select("l_suppkey", "o_custkey").distinct()
    served = served.join(t["customer"].select(F.col("c_custkey").alias("o_custkey"), "c_nationkey"), "o_custkey").select("l_suppkey", "c_nationkey").distinct()
    ship = served.select(hash_id("ship", F.col("l_suppkey"), F.col("c_nationkey")).alias("h"), _id("supplier", "l_suppkey").alias("s"), _id("nation", "c_nationkey").alias("n"))
    n2 = t["nation"].select(nation.alias("n"), _id("region", "n_regionkey").alias("r"))
    lane = n2.crossJoin(n2.select(F.col("n").alias("m"))).select("r", "n", "m")  # the two given tables of 25 nations
    placed = t["orders"].select(hash_id("item", F.lit("placed"), F.col("o_orderkey")).alias("d"), _id("order", "o_orderkey").alias("o"), hash_id("value", F.col("o_orderstatus")).alias("status"), hash_id("value", F.col("o_orderpriority")).alias("priority"))
    return CongruenceGraph(
        spark,
        {
            "buyer": buyer,
            "home": customer.select("n", "c").unionByName(supplier.select("n", F.col("s").alias("c"))),
            "zone": n2.select("r", "n"),
            "line": line,
            "payer": line.join(buyer, "o").select("c", "l"),
            "vendor": line.select("s", "l"),
            "item": item,
            "ship": ship,
            # Grows with customers times suppliers over nations: whole for small scales; two-way and shares joins take its parts.
            "kin": customer.join(supplier, "n").select("n", "c", "s"),
            "lane": lane,
            "placed": placed,
        },
        parts={"kin": (customer.select("n", "c"), supplier.select("n", "s"))},
    )


def lift_projections(spark: SparkSession, sf_dir: str) -> CongruenceGraph:
    """R(supplier, part), S(part, order), T(order, supplier): the sides of the triangle query."""
    df = read_table(spark, sf_dir, "lineitem").select(_id("supplier", "l_suppkey").alias("s"), _id("part", "l_partkey").alias("p"), _id("order", "l_orderkey").alias("o"))
    return CongruenceGraph(spark, {"R": df.select("s", "p").distinct(), "S": df.select("p", "o").distinct(), "T": df.select("o", "s").distinct()}, congruent=False)


def lift_hub(spark: SparkSession, sf_dir: str) -> CongruenceGraph:
    """A star of edges both ways: any two-way plan of the triangle is quadratic."""
    k = read_table(spark, sf_dir, "part").select((F.col("p_partkey") + 1).cast("long").alias("k"))
    zero = F.lit(0).cast("long")
    edges = k.select(zero.alias("x"), F.col("k").alias("y")).unionByName(k.select(F.col("k").alias("x"), zero.alias("y"))).unionByName(spark.range(1).select(F.col("id").alias("x"), F.col("id").alias("y")))
    return CongruenceGraph(spark, {"R": edges, "S": edges, "T": edges}, congruent=False)


def document_merges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(a, b): each document beside the first of its text, so that a group of n copies gives n - 1 pairs."""
    d = read_table(spark, sf_dir, "documents").select("doc_id", F.sha2("text", 256).alias("digest"))
    first = d.groupBy("digest").agg(F.min("doc_id").alias("first"))
    return d.join(first, "digest").where("doc_id <> first").select(_id("doc", "first").alias("a"), _id("doc", "doc_id").alias("b"))


def _document_relations(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    d = read_table(spark, sf_dir, "documents").select(_id("doc", "doc_id").alias("d"), hash_id("source", F.col("source")).alias("s"), hash_id("lang", F.col("lang")).alias("l"))
    labels = read_table(spark, sf_dir, "labels").select(_id("doc", "doc_id").alias("d"), _id("label", "quality").alias("q"), key_id("label", F.col("toxic")).alias("t"))
    return {
        "doc": d.select("d", F.col("d").alias("a")),
        "from": d.select(hash_id("item", F.lit("from"), F.col("d"), F.col("s")).alias("id"), "d", "s"),
        "inlang": d.select(hash_id("item", F.lit("lang"), F.col("d"), F.col("l")).alias("id"), "d", "l"),
        "rated": labels.select(hash_id("item", F.lit("rated"), F.col("d"), F.col("q"), F.col("t")).alias("id"), "d", "q", "t"),
    }


def lift_documents(spark: SparkSession, sf_dir: str) -> CongruenceGraph:
    """Documents with their source, language and rating; copies are merged, not yet rebuilt."""
    flat = CongruenceGraph(spark, _document_relations(spark, sf_dir))
    return CongruenceGraph(spark, nodes=flat.nodes, find_map=components(document_merges(spark, sf_dir)), congruent=False)


def _quoting(texts: DataFrame, items: DataFrame) -> DataFrame:
    """(first, item_id): the text holds the item. A text that does holds every inner word of the item as a word, so it meets
    the item under its longest inner word, and only then is searched; items without inner words are held against all."""
    spaces = "[\\x20\\x09-\\x0D]+"
    split = F.split("item", spaces)
    inner = F.filter(split, lambda w, i: (i > 0) & (i < F.size(split) - 1) & (w != ""))
    longest = F.element_at(F.array_sort(F.transform(inner, lambda w: F.struct((-F.length(w)).alias("n"), w.alias("w")))), 1)["w"]
    keyed = items.withColumn("word", F.when(F.size(inner) > 0, longest))
    words = texts.select("first", F.explode(F.array_distinct(F.split("text", spaces))).alias("word")).join(keyed.select("word", "item_id", "item"), "word")
    long = words.select("first", "item_id", "item").join(texts, "first").where(F.contains("text", "item")).select("first", "item_id")
    bare = texts.crossJoin(keyed.where("word is null").select("item_id", "item")).where(F.contains("text", "item")).select("first", "item_id")
    return long.unionByName(bare)


def lift_quotes(spark: SparkSession, sf_dir: str) -> CongruenceGraph:
    """quotes(document, item): the document holds the benchmark item's text."""
    items = read_table(spark, sf_dir, "benchmark").select("item_id", F.col("text").alias("item"))
    d = read_table(spark, sf_dir, "documents").select("doc_id", "source", "text", F.sha2("text", 256).alias("digest"))
    first = d.groupBy("digest").agg(F.min("doc_id").alias("first"), F.min("text").alias("text"))
    hits = _quoting(first.select("first", "text"), items)
    origin = d.join(d.groupBy("digest").agg(F.min("doc_id").alias("first")), "digest").select("first", "source").distinct()
    quotes = hits.select(hash_id("item", F.lit("quotes"), F.col("first"), F.col("item_id")).alias("id"), _id("doc", "first").alias("d"), _id("bench", "item_id").alias("i"))
    return CongruenceGraph(spark, {"quotes": quotes, "from": origin.select(hash_id("item", F.lit("from"), F.col("first"), F.col("source")).alias("id"), _id("doc", "first").alias("d"), hash_id("source", F.col("source")).alias("s"))})


def _chains(rows: DataFrame, group: str, order: list[str], parts: list[str], start) -> DataFrame:
    """Rows of a hash-consed chain per group: own id from everything up to a row, prev from everything before it; at from 0.

    What a chain holds is the set of its (place, parts), so its hash is a running exclusive or over the group in order: a
    window that keeps one number, however long a user's or a conversation's history is.
    """
    by = Window.partitionBy(group).orderBy(*order)
    rows = rows.select(group, *order, *[p for p in parts if p not in order], F.row_number().over(by).alias("k"))
    held = F.bit_xor(F.xxhash64("k", *parts)).over(by.rowsBetween(Window.unboundedPreceding, Window.currentRow))
    rows = rows.withColumn("own", F.xxhash64(start, F.col("k"), held))
    prev = F.coalesce(F.lag("own").over(by), start)
    return rows.select(group, (F.col("k") - 1).alias("at"), *parts, prev.alias("prev"), "own")


def lift_events(spark: SparkSession, sf_dir: str, events: DataFrame | None = None) -> CongruenceGraph:
    """act(user, type); step(type, prev): each user's events in order, on top of the user's leaf."""
    e = (read_table(spark, sf_dir, "events") if events is None else events).select("user_id", "ts", "event_id", "event_type")
    chain = _chains(e, "user_id", ["ts", "event_id"], ["event_type"], F.xxhash64("user_id"))
    step = chain.select(hash_id("chain", F.col("own")).alias("id"), hash_id("type", F.col("event_type")).alias("t"), hash_id("chain", F.col("prev")).alias("p"))
    act = e.select("user_id", "event_type").distinct().select(hash_id("item", F.col("user_id"), F.col("event_type")).alias("id"), _id("user", "user_id").alias("u"), hash_id("type", F.col("event_type")).alias("t"))
    return CongruenceGraph(spark, {"act": act, "step": step})


def event_places(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, user_id, k): where in a user's chain the class of a step is; k from 1."""
    e = read_table(spark, sf_dir, "events").select("user_id", "ts", "event_id", "event_type")
    chain = _chains(e, "user_id", ["ts", "event_id"], ["event_type"], F.xxhash64("user_id"))
    return chain.select(hash_id("chain", F.col("own")).alias("id"), "user_id", (F.col("at") + 1).cast("long").alias("k"))


def lift_dialog(spark: SparkSession, sf_dir: str) -> CongruenceGraph:
    """say(role, text, prev): a chain for each conversation on one `start`; equal beginnings share classes."""
    c = read_table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", F.sha2("text", 256).alias("digest"))
    chain = _chains(c, "conv_id", ["turn"], ["role", "digest"], F.lit(0).cast("long"))
    say = chain.select(hash_id("chain", F.col("own")).alias("id"), hash_id("role", F.col("role")).alias("r"), hash_id("text", F.col("digest")).alias("x"), hash_id("chain", F.col("prev")).alias("p")).distinct()
    return CongruenceGraph(spark, {"say": say, "start": spark.range(1).select(hash_id("chain", F.lit(0).cast("long")).alias("id"))})


def dialog_places(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = read_table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", F.sha2("text", 256).alias("digest"))
    chain = _chains(c, "conv_id", ["turn"], ["role", "digest"], F.lit(0).cast("long"))
    return chain.select(hash_id("chain", F.col("own")).alias("id"), "conv_id", "at")


def lift_vectors(spark: SparkSession, sf_dir: str) -> CongruenceGraph:
    """cell(vector): signs of the first four components; tag(vector): its label; agree(label, cell)."""
    v = read_table(spark, sf_dir, "embeddings")
    cell = sum((F.when(F.col("embedding")[k] > 0, F.lit(1 << (3 - k))).otherwise(F.lit(0)) for k in range(1, 4)), F.when(F.col("embedding")[0] > 0, F.lit(8)).otherwise(F.lit(0)))
    v = v.select(_id("vec", "vec_id").alias("v"), _id("label", "label").alias("l"), key_id("cell", cell).alias("c"))
    agree = v.select("l", "c").distinct().select(hash_id("item", F.lit("agree"), F.col("l"), F.col("c")).alias("id"), "l", "c")
    return CongruenceGraph(spark, {"cell": v.select("c", "v"), "tag": v.select("l", "v"), "agree": agree})


