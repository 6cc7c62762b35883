"""Shared plumbing: work folders, written stages, document columns, position by id."""

from __future__ import annotations

import atexit
import bisect
import ctypes
import gc
import tempfile
import uuid
from urllib.parse import urlparse

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from congraph.sources.shipping import ship_code

#: What `[\x20\x09-\x0D]` names, as bytes.split() also takes it.
SPACE_BYTES = bytes([0x20, *range(0x09, 0x0E)])


def work_dir(spark: SparkSession, name: str) -> str:
    """A fresh folder below spark.checkpoint.dir, which driver and executors share.

    Only a session in local mode, where both are one machine, may go without the setting.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="congraph-")
        atexit.register(_remove_local, base[len("file://") :])
        spark.conf.set("spark.checkpoint.dir", base)
    return f"{base.rstrip('/')}/congraph-{name}-{uuid.uuid4().hex}"


def _remove_local(path: str) -> None:
    import shutil

    shutil.rmtree(path, ignore_errors=True)


def written(df: DataFrame, name: str) -> DataFrame:
    """The rows of df, written once to the shared folder: a lost executor recomputes nothing before it."""
    path = work_dir(df.sparkSession, name)
    save(df, path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


#: Spark's setting that removes a plan's shuffle files when it has run.
_CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
#: Rows that go to a Python worker at a time, and the most that a written stage sends: both ends hold a batch whole.
_BATCH, BATCH_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch", 4000


def save(df: DataFrame, path: str) -> None:
    """Writes df as Parquet. What it shuffled goes at once, as the rows now stand in the table; settings are put back."""
    conf = df.sparkSession.conf
    rows = int(conf.get(_BATCH, None) or 0)
    wanted = {_CLEAN: "true", _BATCH: str(min(rows, BATCH_ROWS) if rows > 0 else BATCH_ROWS)}
    old = {k: conf.get(k, None) for k in wanted}
    try:
        for k, v in wanted.items():
            conf.set(k, v)
        df.write.parquet(path)
    finally:
        for k, v in old.items():
            conf.unset(k) if v is None else conf.set(k, v)


class Stages:
    """Written stages of one run; `clear` deletes them once what was built from them is written too."""

    def __init__(self, spark: SparkSession):
        self.spark, self.paths = spark, []

    def write(self, df: DataFrame, name: str) -> DataFrame:
        path = work_dir(self.spark, name)
        save(df, path)
        self.paths.append(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def clear(self) -> None:
        for path in self.paths:
            remove(self.spark, path)
        self.paths = []


def remove(spark: SparkSession, path: str) -> None:
    """Deletes a folder through the file system that its URL names."""
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop, True)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def doc_text(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id long, text binary in UTF-8, null as empty): what the kernels read, whatever else df holds."""
    ship_code(df.sparkSession)
    return df.select(
        F.col(id_col).cast("long").alias("doc_id"),
        F.coalesce(F.col(text_col).cast("string"), F.lit("")).cast("binary").alias("text"),
    )


#: What tokenizing keeps in a worker from task to task, by operator; other operators let it go.
CACHES: list[dict] = []
_TIDIED: list[int] = []


def tidy() -> None:
    """Once a task: caches of earlier operators go, and memory that earlier tasks of this worker freed goes back to the system.
    A worker serves all stages of a pipeline in turn, and would otherwise hold the most of each."""
    from pyspark import TaskContext

    task = TaskContext.get()
    if task is None or _TIDIED == [task.taskAttemptId()]:
        return
    _TIDIED[:] = [task.taskAttemptId()]
    if held := [c for c in CACHES if c]:
        for c in held:
            c.clear()
        gc.collect()
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
        trim(0)


def slices(batches, rows: int = 1000):
    """The batches in pieces of so many rows: what a worker holds as Python objects at a time."""
    tidy()
    for batch in batches:
        for a in range(0, batch.num_rows, rows):
            yield batch.slice(a, rows)


def dense(sparse: DataFrame, bits: int, stages: Stages) -> Column:
    """(slot, n) as one array of 2^bits numbers, 0 where a slot is missing; a scalar that every task gets."""
    every = sparse.sparkSession.range(1 << bits).select(F.col("id").cast("int").alias("slot"))
    full = stages.write(every.join(sparse, "slot", "left").select("slot", F.coalesce("n", F.lit(0)).cast("long").alias("n")), "table")
    return full.agg(F.transform(F.array_sort(F.collect_list(F.struct("slot", "n"))), lambda x: x["n"])).scalar()


def sieve(keys: DataFrame, stages: Stages, bits: int = 17) -> Column:
    """Whether a row's `key` is, as far as a bitmap of 2^bits longs tells, among keys(key long), the hashes of what is
    wanted: none is missed, a few others may pass. The bitmap is of one size whatever the corpus."""
    slot = F.expr(f"cast(shiftrightunsigned(key, 6) & {(1 << bits) - 1} as int)")
    marks = keys.groupBy(slot.alias("slot")).agg(F.bit_or(F.expr("shiftleft(1L, cast(key & 63 as int))")).alias("n"))
    return F.get(dense(marks, bits, stages), slot).bitwiseAND(F.expr("shiftleft(1L, cast(key & 63 as int))")) != 0


def odd_ids(rows: DataFrame) -> DataFrame:
    """doc_id, once each, of ids that several rows have, and null: ids that do not tell a row."""
    return rows.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1 or doc_id is null").select("doc_id")


def partitions_for(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


def bucket_bounds(df: DataFrame, id_col: str, buckets: int) -> list[int]:
    """Upper bounds that deal the ids into about equal ranges; from a quantile sketch over all rows.

    One row of at most `buckets` longs comes to the driver.
    """
    if buckets <= 1:
        return []
    got = df.agg(
        F.percentile_approx(id_col, [i / buckets for i in range(1, buckets)], 20 * buckets).alias("q")
    ).first()
    return sorted(set(got.q or []))


def bucket_of(col: Column, bounds: list[int]) -> Column:
    """Number of bounds that lie below the id, so that buckets follow the order of ids; null ids come last. A search tree of
    comparisons, as deep as the logarithm of the number of bounds."""

    def between(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(lo)
        mid = (lo + hi) // 2
        return F.when(col <= F.lit(bounds[mid]), between(lo, mid)).otherwise(between(mid + 1, hi))

    return between(0, len(bounds))


def bucket_index(value: int, bounds: list[int]) -> int:
    return bisect.bisect_left(bounds, value)


def filesystem(url: str):
    """(pyarrow file system, path in it) of a folder URL: local and mounted folders, HDFS, S3, GCS."""
    import pyarrow.fs as fs

    parsed = urlparse(url)
    if parsed.scheme in ("", "file"):
        return fs.LocalFileSystem(), parsed.path or url
    return fs.FileSystem.from_uri(url)
