"""Cutting lineage by tables in the shared folder that the session names in spark.checkpoint.dir."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession


def fresh_path(spark: SparkSession, name: str) -> str:
    """A new folder in the shared one; only local sessions may go without the setting."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        folder = tempfile.mkdtemp(prefix="congraph-cut-")
        atexit.register(shutil.rmtree, folder, True)
        base = f"file://{folder}"
        spark.conf.set("spark.checkpoint.dir", base)
    return f"{base.rstrip('/')}/cut-{name}-{uuid.uuid4().hex}"


def cut(df: DataFrame, name: str = "step") -> DataFrame:
    """df's rows, written once and read again."""
    path = fresh_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


#: Spark's setting that removes a plan's shuffle files when it has run.
_CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def cut_parts(parts: Iterable[DataFrame], name: str = "part") -> DataFrame:
    """Rows of all parts, written one after the other: what a part shuffles goes before the next one begins."""
    paths: list[str] = []
    for df in parts:
        spark, schema = df.sparkSession, df.schema
        paths.append(fresh_path(spark, name))
        old = spark.conf.get(_CLEAN, None)
        spark.conf.set(_CLEAN, "true")
        try:
            df.write.parquet(paths[-1])
        finally:
            spark.conf.unset(_CLEAN) if old is None else spark.conf.set(_CLEAN, old)
    return spark.read.schema(schema).parquet(*paths)
