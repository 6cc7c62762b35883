"""Operators around matches, each as a query on the given tables with its SQL."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from congraph.checkpoints import cut, fresh_path
from congraph.graph import term_nodes
from congraph.intern import key_of
from congraph.sources.tables import read_table as t
from congraph.terms import format_pattern, parse_pattern


def o_p3_comparisons(spark, sf):
    df = t(spark, sf, "lineitem").where(F.col("l_quantity").between(10, 20) & F.col("l_returnflag").isin("A", "R") & (F.col("l_discount") >= 0.05) & F.col("l_linestatus").eqNullSafe("F"))
    return df.select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity")


def o_p3_like(spark, sf):
    return t(spark, sf, "part").where(F.col("p_name").like("%a%")).select("p_partkey", "p_name")


def o_j1_broadcast(spark, sf):
    n = t(spark, sf, "nation")  # 25 rows at any scale
    return t(spark, sf, "customer").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")


def o_j3_product(spark, sf):
    return t(spark, sf, "region").crossJoin(t(spark, sf, "nation")).select("r_regionkey", "n_nationkey")


def o_j5_theta(spark, sf):
    a = t(spark, sf, "nation").select(F.col("n_nationkey").alias("a"), "n_regionkey")
    b = t(spark, sf, "nation").select(F.col("n_nationkey").alias("b"), F.col("n_regionkey").alias("r"))
    return a.join(b, (F.col("n_regionkey") == F.col("r")) & (F.col("a") < F.col("b"))).select("a", "b")


def o_j6_semi(spark, sf):
    big = t(spark, sf, "orders").where("o_totalprice > 200000").select(F.col("o_custkey").alias("c_custkey"))
    return t(spark, sf, "customer").join(big, "c_custkey", "left_semi").select("c_custkey")


def o_j6_anti(spark, sf):
    some = t(spark, sf, "orders").select(F.col("o_custkey").alias("c_custkey"))
    return t(spark, sf, "customer").join(some, "c_custkey", "left_anti").select("c_custkey")


def o_j7_outer(spark, sf):
    per = t(spark, sf, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count(F.lit(1)).alias("n"))
    return t(spark, sf, "customer").join(per, "c_custkey", "full_outer").select("c_custkey", F.coalesce("n", F.lit(0)).alias("n_orders"))


def range_join(points: DataFrame, others: DataFrame, key: str, at: str, other_at: str, seconds: int) -> DataFrame:
    """Pairs with one key and 0 <= other_at - at <= seconds: equi-join on time buckets, then the exact test. A row
    goes to the two buckets that its interval touches, so the work follows the local density."""
    bucket = lambda c: F.floor(F.unix_timestamp(c) / seconds)
    left = points.withColumn("_b", F.explode(F.array(bucket(at), bucket(at) + 1)))
    right = others.withColumn("_b", bucket(other_at))
    return left.join(right, [key, "_b"]).where((F.col(other_at) >= F.col(at)) & (F.col(other_at) <= F.col(at) + F.make_dt_interval(secs=F.lit(seconds)))).drop("_b")


def o_j8_range(spark, sf):
    e = t(spark, sf, "events")
    a = e.where("event_type = 'view'").select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("ts_a"))
    b = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("b"), F.col("ts").alias("ts_b"))
    return range_join(a, b, "user_id", "ts_a", "ts_b", 86_400).select("a", "b")


def o_j9_asof(spark, sf):
    """For each purchase the user's last signup at or before it: one window over the union, no join."""
    e = t(spark, sf, "events").where("event_type in ('signup', 'purchase')")
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, 0)
    found = e.withColumn("signup", F.last(F.when(F.col("event_type") == "signup", F.col("event_id")), ignorenulls=True).over(w))
    return found.where("event_type = 'purchase'").select("event_id", F.coalesce("signup", F.lit(-1)).alias("signup"))


def o_j10_lateral(spark, sf):
    d = t(spark, sf, "part")
    words = spark.tvf.explode(F.split(F.col("p_name").outer(), " ")).toDF("word")
    return d.lateralJoin(words).select("p_partkey", "word")


def o_a1_groups(spark, sf):
    df = t(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus")
    return df.agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("decimal(14,2)")).cast("double").alias("quantity"), F.min("l_discount").alias("lo"), F.max("l_discount").alias("hi"), F.round(F.avg("l_quantity"), 6).alias("mean"))


def o_a2_distinct(spark, sf):
    return t(spark, sf, "lineitem").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_orderkey", "l_suppkey").alias("pairs"))


def o_a2_approximate(spark, sf):
    """Within 5 % of the exact count: 1 if so."""
    df = t(spark, sf, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.01).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", 14)).alias("b"), F.count_distinct("l_partkey").alias("n"))
    return df.select((F.abs(F.col("a") - F.col("n")) <= 0.05 * F.col("n")).alias("close_hll"), (F.abs(F.col("b") - F.col("n")) <= 0.05 * F.col("n")).alias("close_sketch"))


def o_a3_cube(spark, sf):
    o = t(spark, sf, "orders")
    return o.cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n")).select(F.coalesce("o_orderstatus", F.lit("*")).alias("status"), F.coalesce("o_orderpriority", F.lit("*")).alias("priority"), "n")


def o_a3_rollup(spark, sf):
    n = t(spark, sf, "nation").join(t(spark, sf, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return n.rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("n")).select(F.coalesce("r_name", F.lit("*")).alias("region"), F.coalesce("n_name", F.lit("*")).alias("nation"), "n")


def o_a3_sets(spark, sf):
    """Grouping sets named one by one: by status, by priority, and all."""
    o = t(spark, sf, "orders")
    g = o.groupingSets([("o_orderstatus",), ("o_orderpriority",), ()], "o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("level"))
    return g.select(F.coalesce("o_orderstatus", F.lit("*")).alias("status"), F.coalesce("o_orderpriority", F.lit("*")).alias("priority"), F.col("level").cast("long").alias("level"), "n")


def _suppliers_of_orders(spark, sf, key, on):
    """The list aggregate with one of Spark's settings on or off, written under it, as plans are made when they run."""
    old = spark.conf.get(key)
    spark.conf.set(key, on)
    try:
        return cut(o_a5_lists(spark, sf), "lists")
    finally:
        spark.conf.set(key, old)


def o_a7_object_hash(spark, sf):
    return _suppliers_of_orders(spark, sf, "spark.sql.execution.useObjectHashAggregateExec", "true")


def o_a7_sort(spark, sf):
    return _suppliers_of_orders(spark, sf, "spark.sql.execution.useObjectHashAggregateExec", "false")


def o_a4_means(spark, sf):
    x = F.col("l_quantity")
    df = t(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.round(F.count(F.lit(1)) / F.sum(1 / x), 6).alias("hmean"), F.round(F.exp(F.avg(F.log(x))), 6).alias("gmean"), F.median(x).alias("median"), F.percentile(x, F.lit(0.9)).alias("p90"))
    return df


def o_a5_best(spark, sf):
    o = t(spark, sf, "orders")
    w = F.struct("o_totalprice", "o_orderkey")
    return o.groupBy("o_custkey").agg(F.max_by("o_orderkey", w).alias("dearest"), F.min_by("o_orderkey", w).alias("cheapest"))


def o_a5_lists(spark, sf):
    """Lists are of one order's lines."""
    return t(spark, sf, "lineitem").groupBy("l_orderkey").agg(F.array_join(F.sort_array(F.collect_set(F.col("l_suppkey"))).cast("array<string>"), ",").alias("suppliers"))


def o_a6_pivot(spark, sf):
    o = t(spark, sf, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1)))
    return o.select("o_orderpriority", *[F.coalesce(c, F.lit(0)).alias(c.lower()) for c in "FOP"])


def o_a6_unpivot(spark, sf):
    return o_a6_pivot(spark, sf).unpivot(["o_orderpriority"], ["f", "o", "p"], "status", "n")


def heavy_hitters(df: DataFrame, key: str, share: float) -> DataFrame:
    """Values with more than a share of the rows: there are fewer than 1 / share of them."""
    total = df.agg(F.count(F.lit(1)).alias("total"))
    return df.groupBy(key).agg(F.count(F.lit(1)).alias("n")).crossJoin(F.broadcast(total)).where(F.col("n") > share * F.col("total")).drop("total")


def o_a8_heavy(spark, sf):
    return heavy_hitters(t(spark, sf, "documents"), "source", 0.04)


def o_w1_ranks(spark, sf):
    w = W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return t(spark, sf, "orders").select("o_orderkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"), F.ntile(3).over(w).cast("long").alias("tile"), F.round(F.percent_rank().over(w), 6).alias("pr"))


def o_w2_neighbours(spark, sf):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    every = w.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return t(spark, sf, "events").select("event_id", F.coalesce(F.lag("event_type").over(w), F.lit("-")).alias("before"), F.coalesce(F.lead("event_type").over(w), F.lit("-")).alias("after"), F.first("event_id").over(every).alias("first"), F.last("event_id").over(every).alias("last"))


def o_w3_frames(spark, sf):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    c = F.lit(1)
    day = W.partitionBy("user_id").orderBy(F.unix_timestamp("ts")).rangeBetween(-86_400, 0)
    return t(spark, sf, "events").select("event_id", F.count(c).over(w.rowsBetween(-2, 0)).alias("last3"), F.count(c).over(w.rowsBetween(W.unboundedPreceding, 0)).alias("so_far"), F.count(c).over(day).alias("in_day"))


def o_l1_top(spark, sf):
    return t(spark, sf, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(10).select("o_orderkey")


def o_l1_top_per_group(spark, sf):
    w = W.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return t(spark, sf, "orders").withColumn("r", F.row_number().over(w)).where("r <= 3").select("o_orderpriority", "o_orderkey")


def o_l2_sets(spark, sf):
    a = t(spark, sf, "customer").select(F.col("c_nationkey").alias("n"))
    b = t(spark, sf, "supplier").select(F.col("s_nationkey").alias("n"))
    tag = lambda df, name: df.select(F.lit(name).alias("op"), "n")
    return tag(a.union(b).distinct(), "union").unionByName(tag(a.intersect(b), "intersect")).unionByName(tag(a.subtract(b), "except")).unionByName(tag(a.exceptAll(b), "except_all"))


def o_l2_intersect_all(spark, sf):
    """Bags: nations of customers and of suppliers, common ones as often as both have them."""
    c = t(spark, sf, "customer").select(F.col("c_nationkey").alias("n"))
    s = t(spark, sf, "supplier").select(F.col("s_nationkey").alias("n"))
    return c.intersectAll(s).select(F.lit("both").alias("op"), "n").unionByName(c.exceptAll(s).select(F.lit("rest").alias("op"), "n"))


def o_l1_sorted_within(spark, sf):
    """Rows sorted inside each task, without a total order: the first of each run of a key is its least."""
    o = t(spark, sf, "orders").repartition("o_custkey").sortWithinPartitions("o_custkey", "o_orderkey")
    return o.groupBy("o_custkey").agg(F.min("o_orderkey").alias("first"))


def o_f1_strings(spark, sf):
    p = F.col("p_name")
    return t(spark, sf, "part").select("p_partkey", F.upper(F.trim(p)).alias("up"), F.length(p).cast("long").alias("n"), F.substring(p, 1, 3).alias("head"), F.levenshtein(p, F.col("p_brand")).cast("long").alias("dist"), F.regexp_extract(p, "([a-z]+)$", 1).alias("tail"), F.concat_ws("-", p, "p_brand").alias("both"))


def o_f2_hashes(spark, sf):
    return t(spark, sf, "part").select("p_partkey", F.md5("p_name").alias("md5"), F.sha2("p_name", 256).alias("sha"))


def o_f3_dates(spark, sf):
    d = F.col("o_orderdate")
    return t(spark, sf, "orders").select("o_orderkey", F.year(d).cast("long").alias("y"), F.month(d).cast("long").alias("m"), F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("month"), F.datediff(F.lit("1999-01-01").cast("date"), d.cast("date")).cast("long").alias("days"))


def o_f4_math(spark, sf):
    x = F.col("l_quantity")
    return t(spark, sf, "lineitem").select(x.alias("q")).distinct().select("q", F.round(F.log("q"), 6).alias("ln"), F.round(F.sqrt("q"), 6).alias("root"), F.least("q", F.lit(10.0)).alias("lo"), F.greatest("q", F.lit(10.0)).alias("hi"), F.pow("q", F.lit(2.0)).alias("sq"))


def o_f5_arrays(spark, sf):
    e = F.col("embedding").cast("array<double>")
    return t(spark, sf, "embeddings").select("vec_id", F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"), F.round(F.aggregate(e, F.lit(0.0), lambda a, x: a + x * x), 4).alias("norm2"), F.exists(e, lambda x: x > 0.3).alias("large"))


def o_f6_maps(spark, sf):
    """A substitution as a map from variable names."""
    m = F.map_from_arrays(F.array(F.lit("root"), F.lit("s")), F.array(F.col("n_nationkey").cast("long"), F.col("n_regionkey").cast("long")))
    return t(spark, sf, "nation").select("n_nationkey", F.element_at(m, "s").alias("s"), F.size(F.map_keys(m)).cast("long").alias("vars"))


def o_f7_json(spark, sf):
    return t(spark, sf, "events").select("event_id", F.coalesce(F.json_object_keys("props")[0], F.lit("-")).alias("first_key"))


def o_f7_from_json(spark, sf):
    """Properties by schema, by path and as a variant."""
    p = F.from_json("props", "k int")["k"].cast("long")
    by_path = F.get_json_object("props", "$.k").cast("long")
    variant = F.variant_get(F.parse_json("props"), "$.k", "bigint")
    return t(spark, sf, "events").select("event_id", F.coalesce(p, F.lit(-1)).alias("k"), (F.coalesce(p, F.lit(-1)) == F.coalesce(by_path, F.lit(-1))).alias("same_path"), (F.coalesce(p, F.lit(-1)) == F.coalesce(variant, F.lit(-1))).alias("same_variant"))


def o_u1_pretty(spark, sf):
    """Terms parsed and printed again by an Arrow UDF: spaces go, the term stays."""
    from congraph.sources.shipping import ship_code

    ship_code(spark)
    terms = t(spark, sf, "nation").select("n_nationkey", F.concat(F.lit("(zone   (home n"), F.col("n_nationkey"), F.lit(")  )")).alias("value"))
    return terms.select("n_nationkey", _pretty(F.col("value")).alias("term"))


@F.pandas_udf(T.StringType())
def _pretty(values: pd.Series) -> pd.Series:
    return values.map(lambda x: format_pattern(parse_pattern(x)))


class _Nodes:
    """A table function: the nodes of a term, arguments before what they are in."""

    def eval(self, text: str):
        for k, node in enumerate(term_nodes([text])):
            yield k, node.sym, len(node.args)


def o_u3_unnest(spark, sf):
    """Terms unnested by a table function in a lateral join."""
    from congraph.sources.shipping import ship_code

    ship_code(spark)
    spark.udtf.register("nodes_of_term", F.udtf(_Nodes, returnType="at int, sym string, arity int"))
    t(spark, sf, "nation").select("n_nationkey", F.concat(F.lit("(zone (home n"), F.col("n_nationkey"), F.lit("))")).alias("value")).createOrReplaceTempView("zone_terms")
    return spark.sql("SELECT n_nationkey, at, sym, arity FROM zone_terms, LATERAL nodes_of_term(value)")


def o_u4_views(spark, sf):
    """Matches as a view for SQL users."""
    from congraph.operators.match import match
    from congraph.sources import lifts
    from congraph.sql_engine import view_matches

    view_matches("zone", match(lifts.lift_trade(spark, sf), "(zone ?n)"))
    return spark.sql("SELECT count(*) AS n, count(DISTINCT root) AS regions FROM match_zone")


def o_s2_bucketed(spark, sf):
    """Two relations written as tables bucketed by their key: the join of the two reads them without a shuffle."""
    from congraph.sources import lifts

    g, names = lifts.lift_trade(spark, sf), []
    for sym, arity, key in (("buyer", 1, "id"), ("home", 1, "a1")):
        name = f"congraph_{sym}_{uuid.uuid4().hex[:12]}"
        g.rel(sym, arity).write.bucketBy(8, key).sortBy(key).option("path", fresh_path(spark, f"bucketed-{sym}")).saveAsTable(name)
        names.append(name)
    buyer, home = (spark.table(n) for n in names)
    both = buyer.select(F.col("id").alias("c"), F.col("a1").alias("o")).join(home.select(F.col("a1").alias("c"), F.col("id").alias("n")), "c")
    return both.select(key_of(F.col("o")).alias("o_orderkey"), key_of(F.col("n")).cast("int").alias("n_nationkey"))


def o_f8_conditional(spark, sf):
    x = F.col("c_acctbal")
    return t(spark, sf, "customer").select("c_custkey", F.when(x < 0, "debt").when(x < 1000, "low").otherwise("high").alias("band"), F.coalesce(F.nullif(F.col("c_nationkey"), F.lit(0)), F.lit(-1)).alias("nation"))


def o_s4_orc(spark, sf):
    from congraph.sources.files import round_trip

    return round_trip(t(spark, sf, "nation"), "orc").select("n_nationkey", "n_name")


def o_s3_terms(spark, sf):
    """Terms written as lines of text, read back, and taken apart into nodes by a table function."""
    from congraph.sources.files import term_table, write_terms

    terms = t(spark, sf, "nation").select(F.concat(F.lit("(zone n"), F.col("n_nationkey"), F.lit(")")).alias("value"))
    return term_table(spark, write_terms(terms)).groupBy("sym").agg(F.count(F.lit(1)).alias("n")).where("sym = 'zone'")


QUERIES = {k: v for k, v in list(globals().items()) if k.startswith("o_") and callable(v)}
ORACLES = {
    "o_p3_comparisons": "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_discount >= 0.05 AND l_linestatus IS NOT DISTINCT FROM 'F'",
    "o_p3_like": "SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%a%'",
    "o_j1_broadcast": "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey",
    "o_j3_product": "SELECT r_regionkey, n_nationkey FROM region CROSS JOIN nation",
    "o_j5_theta": "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey",
    "o_j6_semi": "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 200000)",
    "o_j6_anti": "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)",
    "o_j7_outer": "SELECT c_custkey, count(o_orderkey) AS n_orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey",
    "o_j8_range": "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 86400 SECOND",
    "o_j9_asof": "SELECT p.event_id, coalesce((SELECT s.event_id FROM events s WHERE s.user_id = p.user_id AND s.event_type = 'signup' AND (s.ts < p.ts OR s.ts = p.ts AND s.event_id <= p.event_id) ORDER BY s.ts DESC, s.event_id DESC LIMIT 1), -1) AS signup FROM events p WHERE p.event_type = 'purchase'",
    "o_j10_lateral": "SELECT p_partkey, unnest(string_split(p_name, ' ')) AS word FROM part",
    "o_a1_groups": "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS DECIMAL(14,2))) AS DOUBLE) AS quantity, min(l_discount) AS lo, max(l_discount) AS hi, round(avg(l_quantity), 6) AS mean FROM lineitem GROUP BY ALL",
    "o_a2_distinct": "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT (l_orderkey, l_suppkey)) AS pairs FROM lineitem",
    "o_a2_approximate": "SELECT true AS close_hll, true AS close_sketch",
    "o_a3_cube": "SELECT coalesce(o_orderstatus, '*') AS status, coalesce(o_orderpriority, '*') AS priority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)",
    "o_a3_rollup": "SELECT coalesce(r_name, '*') AS region, coalesce(n_name, '*') AS nation, count(*) AS n FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)",
    "o_a4_means": "SELECT l_returnflag, round(count(*) / sum(1 / l_quantity), 6) AS hmean, round(exp(avg(ln(l_quantity))), 6) AS gmean, median(l_quantity) AS median, quantile_cont(l_quantity, 0.9) AS p90 FROM lineitem GROUP BY 1",
    "o_a5_best": "SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest FROM orders GROUP BY 1",
    "o_a5_lists": "SELECT l_orderkey, array_to_string(list_sort(list_distinct(list(l_suppkey))), ',') AS suppliers FROM lineitem GROUP BY 1",
    "o_a6_pivot": "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p FROM orders GROUP BY 1",
    "o_a6_unpivot": "SELECT p.o_orderpriority, lower(s) AS status, count(o_orderkey) AS n FROM (SELECT DISTINCT o_orderpriority FROM orders) p CROSS JOIN (VALUES ('F'), ('O'), ('P')) v(s) LEFT JOIN orders x ON x.o_orderpriority = p.o_orderpriority AND x.o_orderstatus = s GROUP BY ALL",
    "o_a8_heavy": "SELECT source, count(*) AS n FROM documents GROUP BY 1 HAVING count(*) > 0.04 * (SELECT count(*) FROM documents)",
    "o_w1_ranks": "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(3) OVER w AS tile, round(percent_rank() OVER w, 6) AS pr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)",
    "o_w2_neighbours": "SELECT event_id, coalesce(lag(event_type) OVER w, '-') AS before, coalesce(lead(event_type) OVER w, '-') AS after, first_value(event_id) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS first, last_value(event_id) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "o_w3_frames": "SELECT event_id, count(*) OVER (w ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS last3, count(*) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS so_far, count(*) OVER (PARTITION BY user_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS in_day FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "o_l1_top": "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 5",
    "o_l1_top_per_group": "SELECT o_orderpriority, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) <= 3",
    "o_l2_sets": "WITH a AS (SELECT c_nationkey AS n FROM customer), b AS (SELECT s_nationkey AS n FROM supplier) SELECT 'union' AS op, n FROM (SELECT n FROM a UNION SELECT n FROM b) UNION ALL SELECT 'intersect', n FROM (SELECT n FROM a INTERSECT SELECT n FROM b) UNION ALL SELECT 'except', n FROM (SELECT n FROM a EXCEPT SELECT n FROM b) UNION ALL SELECT 'except_all', n FROM (SELECT n FROM a EXCEPT ALL SELECT n FROM b)",
    "o_f1_strings": "SELECT p_partkey, upper(trim(p_name)) AS up, length(p_name) AS n, substring(p_name, 1, 3) AS head, levenshtein(p_name, p_brand) AS dist, regexp_extract(p_name, '([a-z]+)$', 1) AS tail, concat_ws('-', p_name, p_brand) AS both FROM part",
    "o_f2_hashes": "SELECT p_partkey, md5(p_name) AS md5, sha256(p_name) AS sha FROM part",
    "o_f3_dates": "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, date_diff('day', CAST(o_orderdate AS DATE), DATE '1999-01-01') AS days FROM orders",
    "o_f4_math": "SELECT DISTINCT l_quantity AS q, round(ln(l_quantity), 6) AS ln, round(sqrt(l_quantity), 6) AS root, least(l_quantity, 10.0::DOUBLE) AS lo, greatest(l_quantity, 10.0::DOUBLE) AS hi, pow(l_quantity, 2) AS sq FROM lineitem",
    "o_f5_arrays": "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS positive, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4) AS norm2, len(list_filter(embedding, lambda x: x::DOUBLE > 0.3)) > 0 AS large FROM embeddings",
    "o_f6_maps": "SELECT n_nationkey, CAST(n_regionkey AS BIGINT) AS s, CAST(2 AS BIGINT) AS vars FROM nation",
    "o_f7_json": "SELECT event_id, coalesce(json_keys(props)[1], '-') AS first_key FROM events",
    "o_a3_sets": "SELECT coalesce(o_orderstatus, '*') AS status, coalesce(o_orderpriority, '*') AS priority, grouping_id(o_orderstatus, o_orderpriority) AS level, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())",
    **dict.fromkeys(("o_a7_object_hash", "o_a7_sort"), "SELECT l_orderkey, array_to_string(list_sort(list_distinct(list(l_suppkey))), ',') AS suppliers FROM lineitem GROUP BY 1"),
    "o_l2_intersect_all": "SELECT 'both' AS op, n FROM (SELECT c_nationkey AS n FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier) UNION ALL SELECT 'rest', n FROM (SELECT c_nationkey AS n FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier)",
    "o_l1_sorted_within": "SELECT o_custkey, min(o_orderkey) AS first FROM orders GROUP BY 1",
    "o_f7_from_json": "SELECT event_id, coalesce(CAST(json_extract(props, '$.k') AS BIGINT), -1) AS k, true AS same_path, true AS same_variant FROM events",
    "o_u1_pretty": "SELECT n_nationkey, '(zone (home n' || n_nationkey || '))' AS term FROM nation",
    "o_u3_unnest": "SELECT n_nationkey, 0 AS at, 'n' || n_nationkey AS sym, 0 AS arity FROM nation UNION ALL SELECT n_nationkey, 1, 'home', 1 FROM nation UNION ALL SELECT n_nationkey, 2, 'zone', 1 FROM nation",
    "o_u4_views": "SELECT count(*) AS n, count(DISTINCT n_regionkey) AS regions FROM nation",
    "o_s2_bucketed": "SELECT o_orderkey, c_nationkey AS n_nationkey FROM orders JOIN customer ON o_custkey = c_custkey",
    "o_f8_conditional": "SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 1000 THEN 'low' ELSE 'high' END AS band, coalesce(nullif(c_nationkey, 0), -1) AS nation FROM customer",
    "o_s4_orc": "SELECT n_nationkey, n_name FROM nation",
    "o_s3_terms": "SELECT 'zone' AS sym, count(*) AS n FROM nation",
}
