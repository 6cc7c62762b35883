"""Terms and tables as files: s-expressions in text, round trips through other formats, a stream of files."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from congraph.checkpoints import fresh_path
from congraph.sources.shipping import ship_code
from congraph.terms import App, parse_pattern


#: Rows of one file of a stream.
MOST_ROWS = 1_000_000


def write_terms(terms: DataFrame) -> str:
    """terms(value): one s-expression a row, into text files."""
    path = fresh_path(terms.sparkSession, "terms")
    terms.write.text(path)
    return path


def _nodes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        found: dict = {}
        known: dict = {}
        for text in batch.column("value").to_pylist():
            _ident(parse_pattern(text), found, known)
        rows = [(sym, own, args) for own, (sym, args) in found.items()]
        yield pa.record_batch([pa.array([r[0] for r in rows], pa.string()), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.list_(pa.int64()))], names=["sym", "cls", "args"])


def _ident(t: App, out: dict, known: dict | None = None) -> int:
    """Id of a ground term, a hash of its symbol and its arguments' ids; out: all nodes below; known: ids of nodes met before.
    Terms may be of any depth."""
    known = {} if known is None else known
    made: list[int] = []
    todo: list[tuple[App, bool]] = [(t, False)]
    while todo:
        p, done = todo.pop()
        if not done:
            todo.append((p, True))
            todo.extend((a, False) for a in reversed(p.args))
            continue
        at = len(made) - len(p.args)
        args = made[at:]
        own = known.get(node := (p.sym, *args))
        if own is None:
            own = known[node] = int.from_bytes(hashlib.blake2b(repr((p.sym, args)).encode(), digest_size=7).digest(), "little")
        out[own] = (p.sym, args)
        made[at:] = [own]
    return made[0]


@F.pandas_udf(T.LongType())
def _root(values: pd.Series) -> pd.Series:
    return values.map(lambda text: _ident(parse_pattern(text), {})).astype("int64")


def term_roots(terms: DataFrame) -> DataFrame:
    """value, own: the id that `term_nodes_of` gives a whole term."""
    ship_code(terms.sparkSession)
    return terms.select("value", _root(F.col("value")).alias("own"))


def term_nodes_of(terms: DataFrame) -> DataFrame:
    """Distinct nodes (sym, cls, args, ver) of ground terms (value); a class id is a hash of the term below it."""
    spark = terms.sparkSession
    ship_code(spark)
    # A row takes long to parse and few bytes, by which partitions would become fewer than cores.
    dealt = terms.select("value").repartition(max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions"))))
    return dealt.mapInArrow(_nodes, "sym string, cls long, args array<long>").distinct().withColumn("ver", F.lit(0))


def term_table(spark: SparkSession, path: str) -> DataFrame:
    return term_nodes_of(spark.read.text(path))


def round_trip(df: DataFrame, kind: str) -> DataFrame:
    """df written in a format and read again: orc, parquet, json, csv."""
    path = fresh_path(df.sparkSession, kind)
    writer = df.write.format(kind)
    reader = df.sparkSession.read.format(kind).schema(df.schema)
    if kind == "csv":
        writer, reader = writer.option("header", True), reader.option("header", True)
    writer.save(path)
    return reader.load(path)


def split_files(df: DataFrame, order: str, parts: int) -> str:
    """df in `parts` slices by ranges of a column, as a stream of files would bring it; a slice is as many files as the
    session has partitions for it, none over MOST_ROWS rows."""
    path = fresh_path(df.sparkSession, "slices")
    lo, hi = df.agg(F.min(order), F.max(order)).first()
    width = max(1, -(-(hi - lo + 1) // parts))
    for k in range(parts):
        df.where((F.col(order) >= lo + k * width) & (F.col(order) < lo + (k + 1) * width)).repartitionByRange(order).sortWithinPartitions(order).write.option("maxRecordsPerFile", MOST_ROWS).mode("append").parquet(path)
    return path
