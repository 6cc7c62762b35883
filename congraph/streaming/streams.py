"""Structured Streaming: flat patterns, windows, deduplication, joins, per-user chains and maintained matches.

Every function runs a stream over folders of files with `availableNow` into files and returns the sink.
"""

from __future__ import annotations

import sys
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from congraph.checkpoints import fresh_path
from congraph.graph import CongruenceGraph
from congraph.incremental import MatchState, weighted
from congraph.sources.files import MOST_ROWS, split_files
from congraph.sources.tables import read_table


def event_stream(spark: SparkSession, sf_dir: str, parts: int = 4, files_each: int = 1, folder: str | None = None) -> DataFrame:
    events = read_table(spark, sf_dir, "events")
    folder = folder or split_files(events, "event_id", parts)
    return spark.readStream.schema(events.schema).option("maxFilesPerTrigger", files_each).parquet(folder)


def to_files(stream: DataFrame, checkpoint: str | None = None, path: str | None = None) -> DataFrame:
    """Append mode into Parquet; with a checkpoint and path of an earlier run it goes on from there."""
    spark = stream.sparkSession
    path, checkpoint = path or fresh_path(spark, "sink"), checkpoint or fresh_path(spark, "progress")
    stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


def to_memory(stream: DataFrame, mode: str) -> DataFrame:
    """Complete or update mode; for results of a bounded number of groups."""
    name = "sink_" + fresh_path(stream.sparkSession, "m").rsplit("-", 1)[1]
    stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", fresh_path(stream.sparkSession, "progress")).trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.table(name)


def st1_filter(spark, sf):
    """A flat pattern on a stream is a filter."""
    return to_files(event_stream(spark, sf).where("event_type = 'purchase'").select("event_id", "user_id"))


def st2_tumbling(spark, sf):
    """Complete mode: as many rows as days and types."""
    counts = event_stream(spark, sf).groupBy(F.window("ts", "1 day"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return to_memory(counts, "complete").select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "event_type", "n")


def st2_sliding(spark, sf):
    counts = event_stream(spark, sf).groupBy(F.window("ts", "2 days", "1 day")).agg(F.count(F.lit(1)).alias("n"))
    return to_memory(counts, "complete").select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "n")


def st2_session(spark, sf):
    """Runs of a user's events with less than six hours between: append mode gives a run once the watermark passed it. All
    events come in one trigger, so none is late; then one event beyond the last day closes every run. Its own run is dropped
    from the sink: a filter on the stream would go below the watermark, which then would not see that event."""
    events = read_table(spark, sf, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"))
    close = events.agg(F.max("event_id").alias("event_id"), F.max("ts").alias("ts")).select((F.col("event_id") + 1).alias("event_id"), F.lit(-1).cast("long").alias("user_id"), F.expr("ts + INTERVAL 30 DAYS").alias("ts"))
    folder, sink, progress = fresh_path(spark, "slices"), fresh_path(spark, "sink"), fresh_path(spark, "progress")
    for part in (events, close):
        part.write.option("maxRecordsPerFile", MOST_ROWS).mode("append").parquet(folder)
        runs = spark.readStream.schema(events.schema).parquet(folder).withWatermark("ts", "20 days").groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count(F.lit(1)).alias("n"))
        found = to_files(runs.select("user_id", F.col("session_window.start").alias("start"), "n"), progress, sink)
    return found.where("user_id >= 0").groupBy("user_id").agg(F.count(F.lit(1)).alias("runs"), F.sum("n").alias("events"))


def st3_late_rows(spark, sf):
    """Late rows: the first file comes again after all others, when the watermark has passed its days; its copies are dropped
    in append mode and counted by update mode without a watermark."""
    events = read_table(spark, sf, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    lo, hi = events.agg(F.min("event_id"), F.max("event_id")).first()
    folder = fresh_path(spark, "late")
    middle = lo + (hi - lo) // 2
    early, rest = events.where(F.col("event_id") <= middle), events.where(F.col("event_id") > middle)
    for part in (early, rest, early):
        part.repartition(1).write.mode("append").parquet(folder)  # one file a slice, so that a trigger takes one slice
    stream = lambda: spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(folder)
    counts = lambda df: df.groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("day"), "n")
    kept = to_files(counts(stream().withWatermark("ts", "1 hour")))
    every = to_memory(counts(stream()), "complete")
    first = F.date_format("day", "yyyy-MM-dd")
    both = kept.select(first.alias("day"), F.col("n").alias("kept")).join(every.select(first.alias("day"), F.col("n").alias("seen")), "day")
    edge = events.where(F.col("event_id") == middle).select(F.date_format("ts", "yyyy-MM-dd").alias("day"))
    return both.join(edge, "day", "left_anti").select("day", "kept", "seen")


def st9_restart(spark, sf):
    """A stream stopped after its first files goes on from its checkpoint: every event is out once."""
    events = read_table(spark, sf, "events")
    folder, sink, progress = split_files(events.where("event_type <> 'view'"), "event_id", 2), fresh_path(spark, "sink"), fresh_path(spark, "progress")
    stream = lambda: spark.readStream.schema(events.schema).parquet(folder).select("event_id", "event_type")
    to_files(stream(), progress, sink)
    events.where("event_type = 'view'").write.mode("append").parquet(folder)
    return to_files(stream(), progress, sink).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


def st9_update(spark, sf):
    """Update mode: each trigger gives the groups that changed; the last row of a group is its count."""
    counts = event_stream(spark, sf).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
    return to_memory(counts, "update").groupBy("event_type").agg(F.max("n").alias("n"))


def st9_maintained_restart(spark, sf):
    """Maintained matches across a restart: the second run resumes the state and takes the new files only."""
    events = read_table(spark, sf, "events")
    graph = CongruenceGraph(spark, {"did": spark.createDataFrame([], "id long, a1 long, a2 long")})
    folder, kept = split_files(events.where("event_type <> 'view'"), "event_id", 1), fresh_path(spark, "kept")
    stream = lambda: spark.readStream.schema(events.schema).parquet(folder)
    match_stream(stream(), graph, ["(did ?u ?t)", "(did ?u ?s)"], _did, kept)
    events.where("event_type = 'view'").write.mode("append").parquet(folder)
    return match_stream(stream(), graph, ["(did ?u ?t)", "(did ?u ?s)"], _did, kept).matches.groupBy(F.col("u").alias("user_id")).agg(F.count(F.lit(1)).alias("n"))


def s5_rate(spark, sf):
    """The rate source by micro-batches: a fixed number of rows a batch, three batches."""
    folder = fresh_path(spark, "rate")
    query = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", 100).load().writeStream.format("parquet").option("path", folder).option("checkpointLocation", fresh_path(spark, "progress")).start()
    while query.isActive and (not query.lastProgress or query.lastProgress["batchId"] < 3):
        query.awaitTermination(1)
    query.stop()
    return spark.read.parquet(folder).where("value < 300").agg(F.count(F.lit(1)).alias("n"), F.max("value").alias("top"))


def st4_bounded(spark, sf):
    """Deduplication with a watermark: ids of events, whose state goes once the watermark passed them."""
    folder = split_files(read_table(spark, sf, "events"), "event_id", 2)
    events = event_stream(spark, sf, folder=folder).withColumn("ts", F.col("ts").cast("timestamp"))
    return to_files(events.withWatermark("ts", "30 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id"))


def st4_dedup(spark, sf):
    """Hash-consing on a stream: a user's type counts once, whatever repeats. Without a watermark the state holds every pair
    of user and type, by design: a pair counts once for ever. `st4_bounded` lets old state go."""
    return to_files(event_stream(spark, sf).select("user_id", "event_type").dropDuplicates(["user_id", "event_type"]))


def st5_static(spark, sf):
    """New atoms against a frozen relation."""
    c = read_table(spark, sf, "customer").select(F.col("c_custkey").alias("user_id"), "c_nationkey")
    return to_files(event_stream(spark, sf).join(c, "user_id").select("event_id", "c_nationkey"))


def st6_interval(spark, sf):
    """A pattern of two atoms on one stream: a view and a purchase of the user within an hour."""
    folder = split_files(read_table(spark, sf, "events"), "event_id", 2)
    a = event_stream(spark, sf, folder=folder).where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("event_id").alias("a"), F.col("ts").cast("timestamp").alias("t")).withWatermark("t", "30 days")
    b = event_stream(spark, sf, folder=folder).where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("b"), F.col("ts").cast("timestamp").alias("t2")).withWatermark("t2", "30 days")
    return to_files(a.join(b, F.expr("u = user_id AND t2 >= t AND t2 <= t + INTERVAL 1 HOUR")).select("a", "b"))


#: Users that one state of `ChainMatcher` holds, about: a call and a read and write of state cost as much for one user as for these.
USERS_EACH = 2_000


class ChainMatcher(StatefulProcessor):
    """Keeps the last two types of each user of a bucket; a third event equal to the one two before is a match. A bucket's users
    are taken together, sorted once and compared by columns."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.last = handle.getValueState("last", "users array<long>, k array<long>, before array<string>, last array<string>")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        events = pd.concat(list(rows)).sort_values(["user_id", "ts", "event_id"], ignore_index=True)
        users, ks, befores, lasts = self.last.get() if self.last.exists() else ([], [], [], [])
        kept = pd.DataFrame({"user_id": pd.Series(users, dtype="int64"), "k": pd.Series(ks, dtype="int64"), "before": pd.Series(befores, dtype=object), "last": pd.Series(lasts, dtype=object)})
        by = events.groupby("user_id", sort=False)
        own = events[["user_id"]].merge(kept, "left", "user_id")
        place, held = by.cumcount(), own["k"].fillna(0).astype("int64")
        one, two = by["event_type"].shift(1), by["event_type"].shift(2)
        # The first two events of a user here follow what is kept.
        one = one.where(place >= 1, own["last"])
        two = two.where(place >= 2, own["last"].where(place == 1, own["before"]))
        k = held + place + 1
        found = (k > 2) & events["event_type"].notna() & (events["event_type"] == two)
        end = ~events["user_id"].duplicated(keep="last")
        new = pd.DataFrame({"user_id": events["user_id"], "k": k, "before": one, "last": events["event_type"]})[end]
        kept = pd.concat([kept[~kept["user_id"].isin(new["user_id"])], new])
        text = lambda c: [None if pd.isna(x) else x for x in kept[c]]
        self.last.update((kept["user_id"].tolist(), kept["k"].tolist(), text("before"), text("last")))
        yield pd.DataFrame({"user_id": events["user_id"][found].astype("int64"), "k": (k - 2)[found]})

    def close(self) -> None:
        pass


def st7_chain(spark, sf):
    # The stream's own Python process starts before the session's files reach it.
    cloudpickle.register_pickle_by_value(sys.modules[__name__])
    settings = {"spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"}
    old = {k: spark.conf.get(k, None) for k in settings}
    for k, v in settings.items():
        spark.conf.set(k, v)
    users = read_table(spark, sf, "events").agg(F.approx_count_distinct("user_id")).first()[0]
    bucket = F.pmod(F.xxhash64("user_id"), F.lit(max(1, -(-users // USERS_EACH)))).alias("bucket")
    try:
        events = event_stream(spark, sf).where("user_id is not null").select(bucket, "user_id", "ts", "event_id", "event_type")
        return to_files(events.groupBy("bucket").transformWithStateInPandas(ChainMatcher(), "user_id long, k long", "Append", "None"))
    finally:
        cloudpickle.unregister_pickle_by_value(sys.modules[__name__])
        for k, v in old.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def match_stream(stream: DataFrame, graph: CongruenceGraph, pattern, deltas: Callable[[DataFrame], dict[str, DataFrame]], folder: str | None = None) -> MatchState:
    """Matches kept up to date by micro-batches; deltas(batch): new rows of relations by symbol. A batch that comes
    again after a failure is known by its number; folder: of an earlier run, from which it goes on."""
    folder = folder or fresh_path(stream.sparkSession, "maintained")
    state = MatchState.resume(graph, pattern, f"{folder}/state")

    def take(batch: DataFrame, number: int) -> None:
        state.advance({s: weighted(d) for s, d in deltas(batch).items()}, number)

    stream.writeStream.foreachBatch(take).option("checkpointLocation", f"{folder}/progress").trigger(availableNow=True).start().awaitTermination()
    return state


def _did(batch: DataFrame) -> dict[str, DataFrame]:
    """did(user, type) for the events of a batch."""
    kinds = F.create_map(*[x for k, n in enumerate(("click", "error", "purchase", "signup", "view")) for x in (F.lit(n), F.lit(k).cast("long"))])
    return {"did": batch.select(F.col("event_id").alias("id"), F.col("user_id").alias("a1"), F.element_at(kinds, F.col("event_type")).alias("a2"))}


def st8_maintained(spark, sf):
    """(user ?u ?t) with (user ?u ?s): a user's pairs of event types, maintained over the stream."""
    graph = CongruenceGraph(spark, {"did": spark.createDataFrame([], "id long, a1 long, a2 long")})
    state = match_stream(event_stream(spark, sf, parts=3, files_each=1 << 20), graph, ["(did ?u ?t)", "(did ?u ?s)"], _did)
    return state.matches.groupBy(F.col("u").alias("user_id")).agg(F.count(F.lit(1)).alias("n"))


def st3_late(spark, sf):
    """Counts by day in append mode: a day is out once the watermark passed it, later rows of it are dropped. Events come in
    four slices by time, each whole in one trigger however many files it has, so with a watermark of a day none is late
    in whatever order files are listed; days at the end stay open."""
    events = read_table(spark, sf, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    at, parts = F.unix_micros("ts"), 4
    lo, hi = events.agg(F.coalesce(F.min(at), F.lit(0)), F.coalesce(F.max(at), F.lit(0))).first()
    width = max(1, -(-(hi - lo + 1) // parts))
    folder, sink, progress = fresh_path(spark, "slices"), fresh_path(spark, "sink"), fresh_path(spark, "progress")
    for k in range(parts):
        events.where((at >= lo + k * width) & (at < lo + (k + 1) * width)).write.option("maxRecordsPerFile", MOST_ROWS).mode("append").parquet(folder)
        stream = spark.readStream.schema(events.schema).parquet(folder)
        counts = stream.withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n"))
        days = to_files(counts.select(F.col("window.start").alias("start"), "n"), progress, sink)
    return days.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "n")


_DONE = "(SELECT max(ts) - INTERVAL 1 DAY FROM events)"
QUERIES = {f"o_st{k}": f for k, f in (("1_filter", st1_filter), ("2_tumbling", st2_tumbling), ("2_sliding", st2_sliding), ("3_watermark", st3_late), ("4_dedup", st4_dedup), ("5_static_join", st5_static), ("6_interval_join", st6_interval), ("7_chain_state", st7_chain), ("8_maintained", st8_maintained), ("2_session", st2_session), ("3_late_rows", st3_late_rows), ("4_bounded_dedup", st4_bounded), ("9_restart", st9_restart), ("9_update", st9_update), ("9_maintained_restart", st9_maintained_restart))} | {"o_s5_rate": s5_rate}
ORACLES = {
    "o_st1_filter": "SELECT event_id, user_id FROM events WHERE event_type = 'purchase'",
    "o_st2_tumbling": "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, count(*) AS n FROM events GROUP BY ALL",
    "o_st2_sliding": "SELECT strftime(date_trunc('day', ts) - INTERVAL (k) DAY, '%Y-%m-%d') AS day, count(*) AS n FROM events CROSS JOIN (VALUES (0), (1)) v(k) GROUP BY 1",
    "o_st3_watermark": f"SELECT strftime(d, '%Y-%m-%d') AS day, n FROM (SELECT date_trunc('day', ts) AS d, count(*) AS n FROM events GROUP BY 1) WHERE d + INTERVAL 1 DAY <= {_DONE}",
    "o_st2_session": """WITH e AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events)
        SELECT user_id, CAST(sum(fresh) AS BIGINT) AS runs, count(*) AS events FROM e GROUP BY 1""",
    "o_st3_late_rows": """WITH m AS (SELECT min(event_id) + (max(event_id) - min(event_id)) // 2 AS m FROM events), e AS (SELECT ts, event_id <= m AS early, date_trunc('day', ts) AS d FROM events, m)
        SELECT strftime(d, '%Y-%m-%d') AS day, count(*) AS kept, count(*) + count(*) FILTER (early) AS seen FROM e
        WHERE d + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events) AND d <> (SELECT date_trunc('day', ts) FROM events, m WHERE event_id = m) GROUP BY d""",
    "o_st4_bounded_dedup": "SELECT event_id FROM events",
    "o_st9_restart": "SELECT event_type, count(*) AS n FROM events GROUP BY 1",
    "o_st9_update": "SELECT event_type, count(*) AS n FROM events GROUP BY 1",
    "o_st9_maintained_restart": "SELECT user_id, CAST(count(*) * count(*) AS BIGINT) AS n FROM events GROUP BY 1",
    "o_s5_rate": "SELECT CAST(300 AS BIGINT) AS n, CAST(299 AS BIGINT) AS top",
    "o_st4_dedup": "SELECT DISTINCT user_id, event_type FROM events",
    "o_st5_static_join": "SELECT event_id, c_nationkey FROM events JOIN customer ON user_id = c_custkey",
    "o_st6_interval_join": "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR",
    "o_st7_chain_state": "WITH e AS (SELECT user_id, event_type, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM events) SELECT a.user_id, a.k FROM e a JOIN e c ON a.user_id = c.user_id AND c.k = a.k + 2 AND a.event_type = c.event_type",
    "o_st8_maintained": "SELECT user_id, CAST(count(*) * count(*) AS BIGINT) AS n FROM events GROUP BY 1",
}
