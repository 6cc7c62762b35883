"""The experiment workloads on the given tables: patterns, strategies and results in natural keys."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from congraph import suites
from congraph.checkpoints import cut
from congraph.closure import insert_terms, rebuild
from congraph.graph import CongruenceGraph
from congraph.incremental import MatchState, weighted
from congraph.intern import hash_collisions, hash_id, key_id, key_of, tag
from congraph.operators.atoms import atom_frames
from congraph.operators.extension import PrefixIndex
from congraph.operators.match import compiled, match, match_many, match_order, match_stale
from congraph.operators.topdown import enumerated
from congraph.plans.compile import ConjunctiveQuery, query
from congraph.plans.cover import agm_bound, fd_bound, integral_cover_bound, output_bound, product_bound
from congraph.sources import lifts
from congraph.sources.files import term_nodes_of
from congraph.sources.markup import tree_search
from congraph.sources.tables import read_table
from congraph.sql_engine import SqlEngine

Query = Callable[[SparkSession, str], DataFrame]


def keys(df: DataFrame, **names: str) -> DataFrame:
    """Columns by new name of natural keys; `column:int` gives a 32-bit one."""
    out = []
    for new, spec in names.items():
        column, _, kind = spec.partition(":")
        key = key_of(F.col(column))
        out.append((key.cast("int") if kind == "int" else key).alias(new))
    return df.select(*out)


TRIANGLE = query(("s", "p", "o"), [("R", "sp"), ("S", "po"), ("T", "os")])
HUB = query(("x", "y", "z"), [("R", "xy"), ("S", "yz"), ("T", "zx")])
#: Two atoms that share one variable, each with others of its own.
BATCH = ConjunctiveQuery(("l", "p", "s", "d", "status", "priority", "o"), query((), [("line", ("l", "o", "p", "s")), ("placed", ("d", "o", "status", "priority"))]).atoms)


def w01(spark, sf, **o):
    return keys(match(lifts.lift_star(spark, sf), "(f ?a (g ?a))", **o), p_partkey="a")


def _ship(df):
    return keys(df, s_suppkey="s", n_nationkey="n:int")


def w02(spark, sf, **o):
    g = lifts.lift_trade(spark, sf)
    df = match(g, "(ship ?s (home ?s))", **o)
    return _homes(g, df)


def _homes(g, df):
    homes = g.rel("home", 1).select(F.col("a1").alias("s"), F.col("id").alias("n"))
    return _ship(df.join(homes, "s"))


def w03(spark, sf, **o):
    g = lifts.lift_trade(spark, sf)
    return _with_line(g, match(g, "(kin (payer ?l) (vendor ?l))", **o), n_nationkey="root:int")


def _with_line(g, df, **more):
    lines = g.rel("line", 3).select(F.col("id").alias("l"), F.col("a1").alias("o"), F.col("a2").alias("p"), F.col("a3").alias("s"))
    return keys(df.join(lines, "l"), o_orderkey="o", p_partkey="p", s_suppkey="s", **more)


def w03b(spark, sf, **o):
    g = lifts.lift_trade(spark, sf)
    return _with_line(g, match(g, "(lane (home (payer ?l)) (home (vendor ?l)))", **o), r_regionkey="root:int")


def w04(spark, sf, **o):
    return keys(match(lifts.lift_trade(spark, sf), "(zone (home (buyer ?o)))", **o), o_orderkey="o", r_regionkey="root:int")


def w05(spark, sf, **o):
    return keys(match(lifts.lift_trade(spark, sf), "(home (buyer ?o))", **o), o_orderkey="o", n_nationkey="root:int")


def w06(spark, sf, **o):
    """Count only: the output grows with the square of a part's suppliers."""
    return match(lifts.lift_trade(spark, sf), ["(item ?p ?s)", "(item ?p ?t)"], **o).agg(F.count(F.lit(1)).alias("n"))


def w06b(spark, sf, **o):
    df = match(lifts.lift_trade(spark, sf), ["(line ?o ?p ?s)", "(line ?o2 ?p ?s)", "(buyer ?o)", "(buyer ?o2)"], **o)
    return keys(df, o1="o", o2="o2", p_partkey="p", s_suppkey="s", c1="root3", c2="root4")


def w06c(spark, sf, **o):
    g = lifts.lift_trade(spark, sf)
    df = match(g, ["(line ?o ?p ?s)", "(ship ?s (home (buyer ?o)))"], **o)
    ships = g.rel("ship", 2).select(F.col("id").alias("root2"), F.col("a2").alias("n"))
    return keys(df.join(ships, "root2"), o_orderkey="o", p_partkey="p", s_suppkey="s", n_nationkey="n:int")


def w07(spark, sf, **o):
    return keys(match(lifts.lift_projections(spark, sf), TRIANGLE, **o), s_suppkey="s", p_partkey="p", o_orderkey="o")


def w08(spark, sf, **o):
    return match(lifts.lift_hub(spark, sf), HUB, **o)


def w09_scan(spark, sf, **o):
    return keys(match(lifts.lift_trade(spark, sf), "(line ?o ?p ?s)", **o), o_orderkey="o", p_partkey="p", s_suppkey="s")


def w09_filter(spark, sf, **o):
    return keys(match(lifts.lift_trade(spark, sf), "(lane ?n ?n)", **o), n_nationkey="n:int", r_regionkey="root:int")


def w10(spark, sf, **o):
    from congraph.intern import constant_id
    from congraph.terms import Cond

    g = lifts.lift_trade(spark, sf)
    zero = constant_id("supplier", 0)
    df = match(g, "(ship ?s (home ?s))", where=[Cond(("s",), lambda s: s != F.lit(zero))], **o)
    homes = g.rel("home", 1).select(F.col("a1").alias("s"), F.col("id").alias("n"))
    return _ship(df.join(homes, "s"))


def w11(spark, sf, **o):
    df = match(lifts.lift_trade(spark, sf), BATCH, **o)
    orders = read_table(spark, sf, "orders")
    status, priority = (orders.select(F.col(c)).distinct().select(hash_id("value", F.col(c)).alias(i), c) for c, i in (("o_orderstatus", "status"), ("o_orderpriority", "priority")))
    df = df.join(status, "status").join(priority, "priority")
    return df.select(key_of(F.col("o")).alias("o_orderkey"), key_of(F.col("p")).alias("p_partkey"), key_of(F.col("s")).alias("s_suppkey"), "o_orderstatus", "o_orderpriority")


def w16(spark, sf):
    g = rebuild(lifts.lift_documents(spark, sf))
    return g.nodes.where("sym in ('doc', 'from', 'inlang')").groupBy("sym").agg(F.count_distinct("cls").alias("n_classes"), F.count(F.lit(1)).alias("n_nodes")).withColumnRenamed("sym", "symbol")


def _rated(spark, sf, df):
    sources = read_table(spark, sf, "documents").select("source").distinct().select(hash_id("source", F.col("source")).alias("s"), "source")
    return df.join(sources, "s").select(key_of(F.col("d")).alias("doc"), "source", key_of(F.col("q")).cast("int").alias("quality"), key_of(F.col("t")).cast("int").alias("toxic")).distinct()


def w17(spark, sf, **o):
    g = rebuild(lifts.lift_documents(spark, sf))
    return _rated(spark, sf, match(g, ["(rated ?d ?q ?t)", "(from ?d ?s)"], **o))


def w28(spark, sf):
    """The same on the graph before its rebuild, through the map of ids."""
    g = lifts.lift_documents(spark, sf)
    return _rated(spark, sf, match_stale(g, ["(rated ?d ?q ?t)", "(from ?d ?s)"], g.find_map))


def w18(spark, sf, **o):
    g = lifts.lift_dialog(spark, sf)
    df = match(g, "(say ?r ?x (say ?r2 ?y (say ?r ?z ?p)))", **o).select("root")
    places = lifts.dialog_places(spark, sf).withColumnRenamed("id", "root")
    return df.join(places, "root").select("conv_id", (F.col("at") - 2).cast("long").alias("turn"))


def w20(spark, sf, **o):
    g = lifts.lift_events(spark, sf)
    df = match(g, "(step ?t (step ?u (step ?t ?p)))", **o).select("root")
    places = lifts.event_places(spark, sf).withColumnRenamed("id", "root")
    return df.join(places, "root").select("user_id", (F.col("k") - 2).alias("k"))


def w22(spark, sf, **o):
    g = lifts.lift_vectors(spark, sf)
    df = match(g, "(agree (tag ?v) (cell ?v))", **o)
    tag = g.rel("tag", 1).select(F.col("a1").alias("v"), F.col("id").alias("l"))
    cell = g.rel("cell", 1).select(F.col("a1").alias("v"), F.col("id").alias("c"))
    return keys(df.join(tag, "v").join(cell, "v"), vec_id="v", label="l:int", cell="c:int")


def w23(spark, sf, **o):
    g = lifts.lift_quotes(spark, sf)
    df = match(g, ["(quotes ?d ?i)", "(from ?d ?s)"], **o)
    sources = read_table(spark, sf, "documents").select("source").distinct().select(hash_id("source", F.col("source")).alias("s"), "source")
    return df.join(sources, "s").select(key_of(F.col("d")).alias("doc"), key_of(F.col("i")).alias("item_id"), "source")


def w30(spark, sf, **o):
    """A cycle with a chain that hangs on it: the hybrid's core is five atoms of eight, and three ears are joined on."""
    g = lifts.lift_trade(spark, sf)
    df = match(g, ["(lane (home (payer ?l)) (home (vendor ?l)))", "(zone (home (payer ?l)))"], **o)
    return _with_line(g, df, r_regionkey="root1:int", zone="root2:int")


def shared_many(spark, sf, share_prefix):
    """Three patterns of which two have the same inner applications, matched together."""
    g = lifts.lift_trade(spark, sf)
    patterns = ["(zone (home (buyer ?o)))", "(lane (home (buyer ?o)) ?m)", "(lane ?m (home (buyer ?x)))"]
    found = match_many(g, patterns, share_prefix=share_prefix, strategy="binary")
    rows = None
    for p, df in zip(patterns, found):
        one = df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(p).alias("pattern"), "n")
        rows = one if rows is None else rows.unionByName(one)
    return rows


def w25(spark, sf, fd):
    return w03(spark, sf, strategy="extension", policy="paper", fd=fd)


def prebuilt(g, pattern):
    """Matches with an index that was built before and is used again: rows of the second use."""
    cq = compiled(pattern)
    frames = atom_frames(g, cq)
    index = PrefixIndex(frames, cq.keyed, written=True)
    match(g, cq, strategy="extension", frames=frames, index=index).count()
    return match(g, cq, strategy="extension", frames=frames, index=index)


def w27(spark, sf):
    g = lifts.lift_trade(spark, sf)
    return _with_line(g, prebuilt(g, "(lane (home (payer ?l)) (home (vendor ?l)))"), r_regionkey="root:int")


def w27_ship(spark, sf):
    g = lifts.lift_trade(spark, sf)
    return _homes(g, prebuilt(g, "(ship ?s (home ?s))"))


def w27_kin(spark, sf):
    g = lifts.lift_trade(spark, sf)
    return _with_line(g, prebuilt(g, "(kin (payer ?l) (vendor ?l))"), n_nationkey="root:int")


def w27_zone(spark, sf):
    return keys(prebuilt(lifts.lift_trade(spark, sf), "(zone (home (buyer ?o)))"), o_orderkey="o", r_regionkey="root:int")


def w27_home(spark, sf):
    return keys(prebuilt(lifts.lift_trade(spark, sf), "(home (buyer ?o))"), o_orderkey="o", n_nationkey="root:int")


def w27_triangle(spark, sf):
    return keys(prebuilt(lifts.lift_projections(spark, sf), TRIANGLE), s_suppkey="s", p_partkey="p", o_orderkey="o")


def w27_hub(spark, sf):
    return prebuilt(lifts.lift_hub(spark, sf), HUB)


def w21_events(spark, sf, slices=5):
    """w20 maintained over slices of each user's events, a later slice on top of the chains of those before."""
    g, places = lifts.lift_events(spark, sf), lifts.event_places(spark, sf)
    steps = cut(g.rel("step", 2).join(places.select("id", "k"), "id"), "steps")
    state = MatchState.empty(g, "(step ?t (step ?u (step ?t ?p)))")
    width = max(1, -(-(steps.agg(F.max("k")).first()[0] or 1) // slices))
    for i in range(slices):
        part = steps.where((F.col("k") > i * width) & (F.col("k") <= (i + 1) * width)).drop("k")
        state.advance({"step": weighted(part)}, i)
    return state.matches.select(F.col("root").alias("id")).join(places, "id").select("user_id", (F.col("k") - 2).alias("k"))


def w21_orders(spark, sf, slices=10):
    """w02 maintained over slices of orders: a pair of supplier and nation comes with the first order that makes it."""
    g = lifts.lift_trade(spark, sf)
    lines, orders, customers = (read_table(spark, sf, t) for t in ("lineitem", "orders", "customer"))
    lo, hi = orders.agg(F.min("o_orderkey"), F.max("o_orderkey")).first()
    width = max(1, -(-(hi - lo + 1) // slices)) if lo is not None else 1
    first = lines.select("l_orderkey", "l_suppkey").distinct().join(orders.select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey")
    first = first.join(customers.select(F.col("c_custkey").alias("o_custkey"), "c_nationkey"), "o_custkey").groupBy("l_suppkey", "c_nationkey").agg(F.min("l_orderkey").alias("o"))
    ship = first.select(hash_id("ship", F.col("l_suppkey"), F.col("c_nationkey")).alias("id"), key_id("supplier", F.col("l_suppkey")).alias("a1"), key_id("nation", F.col("c_nationkey")).alias("a2"), F.floor((F.col("o") - F.lit(lo)) / F.lit(width)).alias("slice"))
    ship = cut(ship, "ships")
    state = MatchState.empty(g, "(ship ?s (home ?s))")
    for i in range(slices):
        new = {"ship": weighted(ship.where(F.col("slice") == i).drop("slice"))}
        state.advance(new | ({"home": weighted(g.rel("home", 1))} if i == 0 else {}), i)
    return _homes(g, state.matches)


def g_insert_terms(spark, sf):
    """Nodes by symbol after the terms of all parts went into a graph that holds others."""
    start = spark.createDataFrame([("(app (lam x (var x)) y)",), ("true",)], "value string")
    g = insert_terms(CongruenceGraph(spark, nodes=cut(term_nodes_of(start), "start")), suites.binding_terms(spark, sf))
    return g.nodes.where("sym in ('app', 'lam', 'var')").groupBy(F.col("sym").alias("symbol")).agg(F.count(F.lit(1)).alias("n"))


def g_represented(spark, sf):
    """Which parts' terms, with the two words changed over, the graph of all parts' terms represents."""
    g = CongruenceGraph(spark, nodes=cut(term_nodes_of(suites.binding_terms(spark, sf)), "start"))
    swapped = suites.binding_terms(spark, sf, swapped=True)
    found = g.represented(swapped)
    return found.agg(F.count(F.lit(1)).alias("terms"), F.count("cls").alias("represented"))


def g_delta(spark, sf):
    """Rows that the database gains by one more version of the graph: the insertion of all parts' terms."""
    start = spark.createDataFrame([("(app (lam x (var x)) y)",)], "value string")
    old = CongruenceGraph(spark, nodes=cut(term_nodes_of(start), "start"))
    new = insert_terms(old, suites.binding_terms(spark, sf)).relations_delta(old.version)
    return new["app"].agg(F.count(F.lit(1)).alias("n"))


def g_collisions(spark, sf):
    """Hashed ids of lines that several lines share: none, or matches would be wrong."""
    names = ["l_orderkey", "l_partkey", "l_suppkey"]
    lines = read_table(spark, sf, "lineitem").select(*names).distinct()
    lines = lines.select(hash_id("line", *map(F.col, names)).alias("id"), F.concat_ws("-", *names).alias("key"))
    return hash_collisions(lines, "id", "key").agg(F.count(F.lit(1)).alias("n"))


def w29_insert(spark, sf):
    """Insertion by the SQL engine: lines that the graph has are not added again."""
    g = lifts.lift_trade(spark, sf)
    flat = lambda df: df.select(F.lit("line").alias("sym"), F.col("id").alias("cls"), "a1", "a2", "a3")
    line = flat(g.rel("line", 3))
    both = SqlEngine(spark, 3).insert(line, line.unionByName(line.select("sym", (F.col("cls") + 1).alias("cls"), F.col("a2").alias("a1"), F.col("a1").alias("a2"), "a3")))
    return both.agg(F.count(F.lit(1)).alias("n"))


def w29_running(spark, sf):
    """The running example by the SQL engine."""
    nodes = lifts.lift_star(spark, sf).nodes.select("sym", "cls", F.get("args", F.lit(0)).alias("a1"), F.get("args", F.lit(1)).alias("a2"))
    return keys(SqlEngine(spark, 2).match(nodes, "(f ?a (g ?a))", {"f": 2, "g": 1}), p_partkey="a")


def w29_congruence(spark, sf):
    flat = CongruenceGraph(spark, lifts._document_relations(spark, sf)).nodes.where("sym <> 'rated'")
    nodes = flat.select("sym", "cls", F.get("args", F.lit(0)).alias("a1"), F.get("args", F.lit(1)).alias("a2"))
    built = SqlEngine(spark, 2).rebuild(nodes, lifts.document_merges(spark, sf).select(F.col("a").alias("rep"), F.col("b").alias("id")))
    return built.groupBy(F.col("sym").alias("symbol")).agg(F.count_distinct("cls").alias("n_classes"), F.count(F.lit(1)).alias("n_nodes"))


def g_find(spark, sf):
    """Representatives of merged documents."""
    return lifts.lift_documents(spark, sf).find_map.select(key_of(F.col("id")).alias("doc_id"), key_of(F.col("rep")).alias("rep"))


def g_lookup(spark, sf):
    """The class of each order's buyer node."""
    g = lifts.lift_trade(spark, sf)
    wanted = g.rel("buyer", 1).select(F.lit("buyer").alias("sym"), F.array("a1").alias("args"))
    return g.with_nodes(CongruenceGraph(spark, {"buyer": g.rel("buyer", 1)}).nodes).lookup(wanted).select(key_of(F.col("args")[0]).alias("o_orderkey"), key_of(F.col("cls")).alias("o_custkey"))


def g_members(spark, sf):
    """Nodes in each nation's class."""
    g = CongruenceGraph(spark, {"home": lifts.lift_trade(spark, sf).rel("home", 1)})
    return g.members().select(key_of(F.col("cls")).cast("int").alias("n_nationkey"), F.size("nodes").cast("long").alias("n"))


def g_terms(spark, sf):
    """Terms that the two large classes of the star stand for: N below g, N * N below f."""
    star = lifts.lift_star(spark, sf)
    leaf = star.rel("leaf", 1).select("id")
    g = CongruenceGraph(spark, {"g": star.rel("g", 1), "f": star.rel("f", 2), "leaf": leaf})
    return g.count_terms(3).where(F.shiftright("cls", 56) == tag("class")).select(key_of(F.col("cls")).alias("which"), F.col("terms").cast("long").alias("terms"))


def g_violations(spark, sf):
    return CongruenceGraph(spark, {k: v for k, v in lifts.lift_trade(spark, sf).relations().items() if k in ("buyer", "home", "zone", "lane")}).violations().agg(F.count(F.lit(1)).alias("n"))


def c_bounds(spark, sf):
    """Bounds of the workloads from the sizes of their relations."""
    rows = []
    trade, sides = lifts.lift_trade(spark, sf), lifts.lift_projections(spark, sf)
    for name, g, p in (("w03", trade, "(kin (payer ?l) (vendor ?l))"), ("w04", trade, "(zone (home (buyer ?o)))"), ("w07", sides, TRIANGLE)):
        cq = compiled(p)
        found = g.sizes([(a.sym, a.arity) for a in cq.atoms])
        n = {a.alias: found[a.sym, a.arity] for a in cq.atoms}
        rows += [(name, "agm", agm_bound(cq, n)), (name, "product", product_bound(cq, n)), (name, "integral", integral_cover_bound(cq, n)), (name, "fd", fd_bound(cq, n) if cq.keyed else agm_bound(cq, n))]
    return spark.createDataFrame([(a, b, float(f"{x:.9g}")) for a, b, x in rows], "workload string, measure string, value double")


def m_orders(spark, sf):
    """Chosen orders as rows: by the bounds of prefixes, and by occurrence and size."""
    g, rows = lifts.lift_trade(spark, sf), []
    for name, p in (("w02", "(ship ?s (home ?s))"), ("w03", "(kin (payer ?l) (vendor ?l))"), ("w04", "(zone (home (buyer ?o)))"), ("w11", BATCH)):
        for policy in ("bound", "paper"):
            rows += [(name, policy, k, " ".join(group)) for k, group in enumerate(match_order(g, p, policy=policy))]
    return spark.createDataFrame(rows, "workload string, policy string, round int, variables string")


def visited_by_search(spark, sf):
    """What the top-down search enumerates before its tests, against the matches, for patterns of several shapes."""
    rows = []
    trade = lifts.lift_trade(spark, sf)
    for name, g, p in (("w01", lifts.lift_star(spark, sf), "(f ?a (g ?a))"), ("w02", trade, "(ship ?s (home ?s))"), ("w04", trade, "(zone (home (buyer ?o)))"), ("w05", trade, "(home (buyer ?o))")):
        rows.append((name, enumerated(g, compiled(p)), match(g, p).count()))
    return spark.createDataFrame(rows, "workload string, visited long, n_matches long")


def c_output(spark, sf):
    """The bound from the size of the output, sqrt(matches * product of relations), for the patterns of c_bounds."""
    rows = []
    trade, sides = lifts.lift_trade(spark, sf), lifts.lift_projections(spark, sf)
    for name, g, p in (("w03", trade, "(kin (payer ?l) (vendor ?l))"), ("w04", trade, "(zone (home (buyer ?o)))"), ("w07", sides, TRIANGLE)):
        cq = compiled(p)
        found = g.sizes([(a.sym, a.arity) for a in cq.atoms])
        n = {a.alias: found[a.sym, a.arity] for a in cq.atoms}
        rows.append((name, float(f"{output_bound(cq, n, match(g, cq, strategy='binary').count()):.6g}")))
    return spark.createDataFrame(rows, "workload string, value double")


def c_candidates(spark, sf):
    """Rows that the extension join enumerates on the cyclic pattern, its largest round against its matches, by order."""
    g, p = lifts.lift_trade(spark, sf), "(lane (home (payer ?l)) (home (vendor ?l)))"
    lines = match(g, p, strategy="binary").count()
    rows = []
    for policy, fd in (("bound", "soft"), ("paper", "strict")):
        trace: list = []
        match(g, p, strategy="extension", policy=policy, fd=fd, trace=trace)
        most = max(df.count() for _, _, df in trace)
        rows.append((f"{policy}_{fd}", most <= 2 * lines, lines))
    return spark.createDataFrame(rows, "policy string, within_twice boolean, n_matches long")


def visited_counts(spark, sf):
    """Tuples that each matcher enumerates on the running example before its last test: N^2 against N."""
    g = lifts.lift_star(spark, sf)
    trace: list = []
    match(g, "(f ?a (g ?a))", strategy="extension", trace=trace).count()
    joined = max(df.count() for _, _, df in trace)
    return spark.createDataFrame([("topdown", enumerated(g, compiled("(f ?a (g ?a))"))), ("extension", joined)], "matcher string, visited long")


#: name: (workload, strategies). Every strategy of a workload has the same oracle.
_ACYCLIC = ("extension", "static", "binary", "reduced", "shares", "topdown", "topdown_eager")
_CYCLIC = ("extension", "static", "binary", "hybrid", "shares", "topdown", "topdown_eager")
WORKLOADS: dict[str, tuple[Callable, tuple[str, ...]]] = {
    "w01_running_example": (w01, ("extension", "static", "binary", "reduced", "shares", "topdown", "topdown_eager")),
    "w02_trade_nonlinear": (w02, _ACYCLIC),
    "w03_cyclic": (w03, _CYCLIC),
    "w03b_cyclic_small_outer": (w03b, ("extension", "binary", "hybrid", "shares")),
    "w04_linear_chain": (w04, _ACYCLIC),
    "w05_nested_unary": (w05, ("extension", "binary", "reduced", "topdown")),
    "w06_multi_count": (w06, ("extension", "binary", "reduced")),
    # Independent roots: the late search takes all pairs of roots, and without a shared variable at the root the eager one does.
    "w06b_four_roots": (w06b, ("extension", "binary", "reduced", "topdown_eager")),
    "w06c_cyclic_multi": (w06c, ("extension", "binary", "hybrid")),
    "w07_triangle": (w07, ("extension", "static", "binary", "shares")),
    "w08_hub_triangle": (w08, ("extension", "shares", "binary")),
    "w09_scan": (w09_scan, ("scan", "extension")),
    "w09_scan_filter": (w09_filter, ("scan", "extension")),
    "w10_condition": (w10, ("extension", "binary", "reduced", "topdown")),
    "w11_batching": (w11, ("extension", "binary", "reduced")),
    "w17_quality": (w17, ("extension", "binary", "topdown")),
    "w18_dialog": (w18, ("extension", "binary", "hybrid", "topdown")),
    "w20_events": (w20, ("extension", "binary", "hybrid", "shares", "topdown")),
    "w22_vectors": (w22, ("extension", "binary", "topdown")),
    "w23_contamination": (w23, ("extension", "binary")),
    "w30_cycle_with_ears": (w30, ("extension", "hybrid", "binary")),
}


def workload_queries() -> tuple[dict[str, Query], dict[str, str]]:
    """Queries by name; and the name of the workload whose oracle each shares."""
    out: dict[str, Query] = {}
    base: dict[str, str] = {}
    for name, (f, strategies) in WORKLOADS.items():
        out[name], base[name] = f, name
        for s in strategies:
            out[f"{name}_{s}"], base[f"{name}_{s}"] = partial(f, strategy=s), name
    extra: dict[str, tuple[Query, str]] = {
        "w10_late_filter": (partial(w10, strategy="extension", pushdown=False), "w10_condition"),
        "w11_unbatched": (partial(w11, strategy="extension", batch=False), "w11_batching"),
        "w07_triangle_sorted_trie": (partial(w07, strategy="shares", trie="sorted"), "w07_triangle"),
        "w02_binary_hash": (partial(w02, strategy="binary", hint="shuffle_hash"), "w02_trade_nonlinear"),
        "w02_binary_merge": (partial(w02, strategy="binary", hint="merge"), "w02_trade_nonlinear"),
        "w16_congruence": (w16, "w16_congruence"),
        "w12_algebra_suite": (partial(suites.suite_counts, name="algebra"), "w12"),
        "w13_binder_suite": (partial(suites.suite_counts, name="binder"), "w13"),
        "w15_associativity": (suites.associativity_levels, "w15_associativity"),
        **{f"w19_tree_search_{s}": (partial(tree_search, strategy=s), "w19") for s in ("extension", "binary", "topdown")},
        "w21_incremental": (w21_events, "w20_events"),
        "w29_sql_running": (w29_running, "w01_running_example"),
        "w29_sql_congruence": (w29_congruence, "w16_congruence"),
        "g_find_documents": (g_find, "g_find_documents"),
        "g_lookup_trade": (g_lookup, "g_lookup_trade"),
        "g_members_trade": (g_members, "g_members_trade"),
        "g_count_terms": (g_terms, "g_count_terms"),
        "g_violations": (g_violations, "g_violations"),
        "c_bounds": (c_bounds, "c_bounds"),
        "c_visited": (visited_counts, "c_visited"),
        "m_orders": (m_orders, "m_orders"),
        "w25_fd_strict": (partial(w25, fd="strict"), "w03_cyclic"),
        "w25_fd_off": (partial(w25, fd="off"), "w03_cyclic"),
        "w27_prebuilt_index": (w27, "w03b_cyclic_small_outer"),
        "w28_stale_ids": (w28, "w17_quality"),
        "w21_incremental_orders": (w21_orders, "w02_trade_nonlinear"),
        "w27_prebuilt_ship": (w27_ship, "w02_trade_nonlinear"),
        "w27_prebuilt_kin": (w27_kin, "w03_cyclic"),
        "w27_prebuilt_zone": (w27_zone, "w04_linear_chain"),
        "w27_prebuilt_home": (w27_home, "w05_nested_unary"),
        "w27_prebuilt_triangle": (w27_triangle, "w07_triangle"),
        "w27_prebuilt_hub": (w27_hub, "w08_hub_triangle"),
        "w29_sql_insert": (w29_insert, "w29_sql_insert"),
        "b4_shared_applications": (partial(shared_many, share_prefix=True), "b4_many"),
        "b4_unshared": (partial(shared_many, share_prefix=False), "b4_many"),
        "g_insert_terms": (g_insert_terms, "g_insert_terms"),
        "g_represented": (g_represented, "g_represented"),
        "g_hash_collisions": (g_collisions, "g_violations"),
        "g_relations_delta": (g_delta, "g_relations_delta"),
        "c_visited_by_search": (visited_by_search, "c_visited_by_search"),
        "c_output_bound": (c_output, "c_output_bound"),
        "c_candidates": (c_candidates, "c_candidates"),
    }
    for k, (f, b) in extra.items():
        out[k], base[k] = f, b
    from itertools import permutations

    # Any order is right; each permutation of the running example and of the triangle is a query.
    for k, order in enumerate(permutations(["root", "a", "_n0"])):
        out[f"w24_order_running_{k}"], base[f"w24_order_running_{k}"] = partial(w01, strategy="extension", order=order), "w01_running_example"
    for k, order in enumerate(permutations(["s", "p", "o"])):
        out[f"w24_order_triangle_{k}"], base[f"w24_order_triangle_{k}"] = partial(w07, strategy="extension", order=order), "w07_triangle"
    for k, order in enumerate(permutations(["root", "_n0", "_n1", "o"])):
        out[f"w24_order_linear_{k:02d}"], base[f"w24_order_linear_{k:02d}"] = partial(w04, strategy="extension", order=order), "w04_linear_chain"
    # Of the 720 orders of the cyclic pattern those that go round the cycle, from every variable and both ways.
    ring = ["l", "_n1", "_n0", "root", "_n2", "_n3"]
    for k in range(6):
        for way, turn in (("there", ring[k:] + ring[:k]), ("back", (ring[k:] + ring[:k])[::-1])):
            out[f"w24_order_cyclic_{k}_{way}"], base[f"w24_order_cyclic_{k}_{way}"] = partial(w03b, strategy="extension", order=turn), "w03b_cyclic_small_outer"
    return out, base


_TRIPLES = "t AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS p, l_suppkey AS s FROM lineitem)"
_WORD = "regexp_replace({}, '[^A-Za-z0-9]', '_', 'g')"
_PARTS = f"p AS (SELECT DISTINCT {_WORD.format('p_brand')} AS b, {_WORD.format("string_split(p_name, ' ')[-1]")} AS l, {_WORD.format("string_split(p_name, ' ')[1]")} AS f FROM part)"
_SHIP = """SELECT DISTINCT s_suppkey, n_nationkey FROM (
    SELECT DISTINCT l_suppkey, c_nationkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey)
    JOIN supplier ON l_suppkey = s_suppkey AND c_nationkey = s_nationkey JOIN nation ON n_nationkey = s_nationkey"""

#: By occurrence: variables of two atoms before those of one, ties by the smaller relation. By bound: no prefix larger than it need be.
_ORDERS = {
    ("w02", "bound"): "s,_n0,root", ("w02", "paper"): "s,_n0,root", ("w03", "bound"): "_n0,_n1,root,l", ("w03", "paper"): "_n0,_n1,l,root",
    ("w04", "bound"): "_n0,root,_n1,o", ("w04", "paper"): "_n0,_n1,root,o", ("w11", "bound"): "o,status priority d,p s l", ("w11", "paper"): "o,status priority d,p s l",
}

ORACLES: dict[str, str] = {
    "m_orders": "SELECT workload, policy, round, variables FROM (VALUES "
    + ", ".join(f"('{w}', '{p}', {k}, '{v}')" for (w, p), order in _ORDERS.items() for k, v in enumerate(order.split(",")))
    + ") v(workload, policy, round, variables)",
    # A chain of n orders has n - 1 sums; chains that begin alike share theirs, and a sum of a sum is a match.
    "w15_associativity": "WITH o AS (SELECT o_custkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS k FROM orders) SELECT count(*) AS n FROM o WHERE k >= 3",
    "g_find_documents": "SELECT doc_id, rep FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS rep FROM documents) WHERE doc_id <> rep",
    "g_lookup_trade": "SELECT o_orderkey, o_custkey FROM orders",
    "g_members_trade": "SELECT n AS n_nationkey, count(*) AS n FROM (SELECT c_nationkey AS n FROM customer UNION ALL SELECT s_nationkey FROM supplier) x(n) GROUP BY 1",
    "g_count_terms": "SELECT CAST(0 AS BIGINT) AS which, count(*) AS terms FROM part UNION ALL SELECT CAST(1 AS BIGINT), count(*) * count(*) FROM part",
    "g_violations": "SELECT CAST(0 AS BIGINT) AS n",
    "w29_sql_insert": f"WITH {_TRIPLES}, m AS (SELECT o, p, s FROM t UNION SELECT p + (2::BIGINT << 56) - (3::BIGINT << 56), o + (3::BIGINT << 56) - (2::BIGINT << 56), s FROM t) SELECT count(*) AS n FROM m",
    "b4_many": """WITH n AS (SELECT count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey), m AS (SELECT count(*) AS m FROM nation)
        SELECT '(zone (home (buyer ?o)))' AS pattern, n FROM n UNION ALL SELECT '(lane (home (buyer ?o)) ?m)', n * m FROM n, m UNION ALL SELECT '(lane ?m (home (buyer ?x)))', n * m FROM n, m""",
    "g_insert_terms": f"""WITH {_PARTS} SELECT 'app' AS symbol, count(DISTINCT (b, l, f)) + count(DISTINCT (b, l)) + 1 AS n FROM p UNION ALL SELECT 'lam', count(DISTINCT (b, l)) + 1 FROM p UNION ALL SELECT 'var', count(DISTINCT b) + 1 FROM p""",
    "g_represented": f"WITH {_PARTS}, q AS (SELECT DISTINCT b, f AS l, l AS f FROM p) SELECT count(*) AS terms, count(*) FILTER (EXISTS (SELECT 1 FROM p WHERE p.b = q.b AND p.l = q.l AND p.f = q.f)) AS represented FROM q",
    "g_relations_delta": f"WITH {_PARTS} SELECT count(DISTINCT (b, l, f)) + count(DISTINCT (b, l)) AS n FROM p",
    "c_visited_by_search": f"""WITH ship AS (SELECT DISTINCT l_suppkey AS s, c_nationkey AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey),
        home AS (SELECT c_nationkey AS n FROM customer UNION ALL SELECT s_nationkey FROM supplier), b AS (SELECT count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey)
        SELECT 'w01' AS workload, count(*) * count(*) AS visited, count(*) AS n_matches FROM part
        UNION ALL SELECT 'w02', (SELECT count(*) FROM ship JOIN home USING (n)), (SELECT count(*) FROM ({_SHIP}))
        UNION ALL SELECT 'w04', n, n FROM b UNION ALL SELECT 'w05', n, n FROM b""",
    "c_output_bound": f"""WITH {_TRIPLES}, c AS (SELECT (SELECT count(*) FROM t)::DOUBLE AS l, (SELECT count(*) FROM customer JOIN supplier ON c_nationkey = s_nationkey)::DOUBLE AS kin,
            (SELECT count(*) FROM nation)::DOUBLE AS zone, (SELECT count(*) FROM orders)::DOUBLE AS buyer, ((SELECT count(*) FROM customer) + (SELECT count(*) FROM supplier))::DOUBLE AS home,
            (SELECT count(*) FROM t JOIN orders ON o = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON s = s_suppkey AND s_nationkey = c_nationkey)::DOUBLE AS q3,
            (SELECT count(*) FROM orders JOIN customer ON o_custkey = c_custkey)::DOUBLE AS q4,
            (SELECT count(*) FROM (SELECT DISTINCT s, p FROM t))::DOUBLE AS rr, (SELECT count(*) FROM (SELECT DISTINCT p, o FROM t))::DOUBLE AS ss, (SELECT count(*) FROM (SELECT DISTINCT o, s FROM t))::DOUBLE AS tt,
            (SELECT count(*) FROM (SELECT DISTINCT s, p FROM t) JOIN (SELECT DISTINCT p, o FROM t) USING (p) JOIN (SELECT DISTINCT o, s FROM t) USING (o, s))::DOUBLE AS q7),
        v AS (SELECT 'w03' AS workload, sqrt(q3 * kin * l * l) AS x FROM c UNION ALL SELECT 'w04', sqrt(q4 * zone * home * buyer) FROM c UNION ALL SELECT 'w07', sqrt(q7 * rr * ss * tt) FROM c)
        SELECT workload, CAST(format('{{:.6g}}', x) AS DOUBLE) AS value FROM v""",
    "c_candidates": f"WITH {_TRIPLES}, q AS (SELECT count(*) AS n FROM t JOIN orders ON o = o_orderkey JOIN customer ON o_custkey = c_custkey) SELECT 'bound_soft' AS policy, true AS within_twice, n AS n_matches FROM q UNION ALL SELECT 'paper_strict', true, n FROM q",
    "w30_cycle_with_ears": f"WITH {_TRIPLES} SELECT o AS o_orderkey, p AS p_partkey, s AS s_suppkey, n_regionkey AS r_regionkey, n_regionkey AS zone FROM t JOIN orders ON o = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey",
    "c_bounds": """WITH line AS (SELECT DISTINCT l_orderkey, l_partkey, l_suppkey FROM lineitem),
        c AS (SELECT (SELECT count(*) FROM line)::DOUBLE AS l, (SELECT count(*) FROM customer JOIN supplier ON c_nationkey = s_nationkey)::DOUBLE AS kin,
            (SELECT count(*) FROM nation)::DOUBLE AS zone, (SELECT count(*) FROM orders)::DOUBLE AS buyer,
            ((SELECT count(*) FROM customer) + (SELECT count(*) FROM supplier))::DOUBLE AS home,
            (SELECT count(*) FROM (SELECT DISTINCT l_suppkey, l_partkey FROM lineitem))::DOUBLE AS r,
            (SELECT count(*) FROM (SELECT DISTINCT l_partkey, l_orderkey FROM lineitem))::DOUBLE AS s,
            (SELECT count(*) FROM (SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem))::DOUBLE AS t),
        v AS (SELECT 'w03' AS workload, 'agm' AS measure, kin * l AS x FROM c UNION ALL SELECT 'w03', 'product', kin * l * l FROM c
            UNION ALL SELECT 'w03', 'integral', kin * l FROM c UNION ALL SELECT 'w03', 'fd', l FROM c
            UNION ALL SELECT 'w04', 'agm', zone * buyer FROM c UNION ALL SELECT 'w04', 'product', zone * home * buyer FROM c
            UNION ALL SELECT 'w04', 'integral', zone * buyer FROM c UNION ALL SELECT 'w04', 'fd', buyer FROM c
            UNION ALL SELECT 'w07', 'agm', least(sqrt(r * s * t), r * s, s * t, r * t) FROM c UNION ALL SELECT 'w07', 'product', r * s * t FROM c
            UNION ALL SELECT 'w07', 'integral', least(r * s, s * t, r * t) FROM c UNION ALL SELECT 'w07', 'fd', least(sqrt(r * s * t), r * s, s * t, r * t) FROM c)
        SELECT workload, measure, CAST(format('{:.9g}', x) AS DOUBLE) AS value FROM v""",
    "c_visited": "SELECT 'topdown' AS matcher, count(*) * count(*) AS visited FROM part UNION ALL SELECT 'extension', count(*) FROM part",
    "w01_running_example": "SELECT p_partkey FROM part",
    "w02_trade_nonlinear": _SHIP,
    "w03_cyclic": f"WITH {_TRIPLES} SELECT o AS o_orderkey, p AS p_partkey, s AS s_suppkey, c_nationkey AS n_nationkey FROM t JOIN orders ON o = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON s = s_suppkey AND s_nationkey = c_nationkey",
    "w03b_cyclic_small_outer": f"WITH {_TRIPLES} SELECT o AS o_orderkey, p AS p_partkey, s AS s_suppkey, n_regionkey AS r_regionkey FROM t JOIN orders ON o = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey",
    "w04_linear_chain": "SELECT o_orderkey, n_regionkey AS r_regionkey FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey",
    "w05_nested_unary": "SELECT o_orderkey, c_nationkey AS n_nationkey FROM orders JOIN customer ON o_custkey = c_custkey",
    "w06_multi_count": "WITH i AS (SELECT DISTINCT l_partkey AS p, l_suppkey AS s FROM lineitem) SELECT count(*) AS n FROM i a JOIN i b ON a.p = b.p",
    "w06b_four_roots": f"WITH {_TRIPLES} SELECT a.o AS o1, b.o AS o2, a.p AS p_partkey, a.s AS s_suppkey, x.o_custkey AS c1, y.o_custkey AS c2 FROM t a JOIN t b ON a.p = b.p AND a.s = b.s JOIN orders x ON a.o = x.o_orderkey JOIN orders y ON b.o = y.o_orderkey",
    "w06c_cyclic_multi": f"WITH {_TRIPLES} SELECT o AS o_orderkey, p AS p_partkey, s AS s_suppkey, c_nationkey AS n_nationkey FROM t JOIN orders ON o = o_orderkey JOIN customer ON o_custkey = c_custkey",
    "w07_triangle": "WITH r AS (SELECT DISTINCT l_suppkey s, l_partkey p FROM lineitem), q AS (SELECT DISTINCT l_partkey p, l_orderkey o FROM lineitem), t AS (SELECT DISTINCT l_orderkey o, l_suppkey s FROM lineitem) SELECT r.s AS s_suppkey, r.p AS p_partkey, q.o AS o_orderkey FROM r JOIN q ON r.p = q.p JOIN t ON q.o = t.o AND t.s = r.s",
    # The two-way form of the hub query is quadratic; its three families of rows are written out.
    "w08_hub_triangle": "WITH k AS (SELECT p_partkey + 1 AS k FROM part) SELECT CAST(0 AS BIGINT) AS x, CAST(0 AS BIGINT) AS y, CAST(0 AS BIGINT) AS z UNION ALL SELECT k, 0, 0 FROM k UNION ALL SELECT 0, k, 0 FROM k UNION ALL SELECT 0, 0, k FROM k",
    "w09_scan": f"WITH {_TRIPLES} SELECT o AS o_orderkey, p AS p_partkey, s AS s_suppkey FROM t",
    "w09_scan_filter": "SELECT n_nationkey, n_regionkey AS r_regionkey FROM nation",
    "w10_condition": f"SELECT * FROM ({_SHIP}) WHERE s_suppkey <> 0",
    "w11_batching": f"WITH {_TRIPLES} SELECT o AS o_orderkey, p AS p_partkey, s AS s_suppkey, o_orderstatus, o_orderpriority FROM t JOIN orders ON o = o_orderkey",
    "w16_congruence": "SELECT 'doc' AS symbol, count(DISTINCT text) AS n_classes, count(DISTINCT text) AS n_nodes FROM documents UNION ALL SELECT 'from', count(*), count(*) FROM (SELECT DISTINCT text, source FROM documents) UNION ALL SELECT 'inlang', count(*), count(*) FROM (SELECT DISTINCT text, lang FROM documents)",
    "w17_quality": "WITH d AS (SELECT *, min(doc_id) OVER (PARTITION BY text) AS doc FROM documents) SELECT DISTINCT a.doc, b.source, quality, toxic FROM d a JOIN labels ON a.doc_id = labels.doc_id JOIN d b ON a.doc = b.doc",
    "w18_dialog": "SELECT a.conv_id, a.turn FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 2 AND a.role = b.role",
    "w20_events": "WITH e AS (SELECT user_id, event_type, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM events) SELECT a.user_id, a.k FROM e a JOIN e c ON a.user_id = c.user_id AND c.k = a.k + 2 AND a.event_type = c.event_type",
    "w22_vectors": "SELECT vec_id, label, CAST((CASE WHEN embedding[1] > 0 THEN 8 ELSE 0 END) + (CASE WHEN embedding[2] > 0 THEN 4 ELSE 0 END) + (CASE WHEN embedding[3] > 0 THEN 2 ELSE 0 END) + (CASE WHEN embedding[4] > 0 THEN 1 ELSE 0 END) AS INTEGER) AS cell FROM embeddings",
    "w23_contamination": "WITH d AS (SELECT *, min(doc_id) OVER (PARTITION BY text) AS doc FROM documents) SELECT DISTINCT doc, item_id, source FROM d JOIN benchmark ON contains(d.text, benchmark.text)",
}
