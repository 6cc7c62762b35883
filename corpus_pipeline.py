"""A corpus pipeline: toxic documents go, then copies, then near copies; what stays is packed.

Cases, as in the operators: a null text is the empty one; a row is scored by its own text; of equal texts one row stays, that of
the least doc_id, also among rows that repeat an id; of near copies likewise; rows without words link with nothing; rows with a
null id are told apart by their texts; very long texts are read whole; an empty table gives no rows; further columns, whatever
their names, go along up to the packing.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from congraph.llm.best_fit import pack_documents
from congraph.llm.common import written
from congraph.llm.exact_dedup import drop_copies
from congraph.llm.ngram_join import drop_near_copies
from congraph.llm.toxicity import drop_toxic


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return drop_toxic(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def exact_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return drop_copies(docs)


def ngram_join(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return drop_near_copies(docs)


def best_fit(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pack_documents(docs)


STAGES = [("toxicity", toxicity), ("exact_dedup", exact_dedup), ("ngram_join", ngram_join), ("best_fit", best_fit)]

#: Learnt scores, components and packing are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = written(docs, name)
    return docs
