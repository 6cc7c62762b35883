"""Exact deduplication by owners in Patricia tries.

Texts count as equal when they are identical after each run of `[\\x20\\x09-\\x0D]` becomes one space; null is
the empty text. Map tasks merge copies that they see in small tries, so a text that fills a third of the
corpus leaves each task once; the rest is dealt by length and content hash, and one trie for each partition
settles equality on the full bytes. The owner of a text is its smallest doc_id; null ids come last.

Cases: null text = empty text; rows that repeat a doc_id count each and share the owner; rows with a null doc_id
have a null `kept`, as in SQL, and of those whose text has no id at all `drop_copies` keeps one; an empty table gives
no rows; further columns of the input are left alone (`exact_classes` reads two columns only, `drop_copies` keeps all).
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from congraph.llm.common import SPACE_BYTES, doc_text, odd_ids, partitions_for, slices, written
from congraph.llm.patricia import PatriciaTrie

_TO_SPACE = bytes(0x20 if b in SPACE_BYTES else b for b in range(256))

_DIGEST = "doc_id long, n_bytes int, digest binary"
_FOUND = "text binary, n_bytes int, digest binary, owner long, n long"
_OWNERS = "n_bytes int, digest binary, keep_id long, group_size long"


def normalised(text: bytes) -> bytes:
    text = text.translate(_TO_SPACE)
    if b"  " not in text:
        return text
    inner = b" ".join(text.split())
    if not inner:
        return b" "
    return b" " * text.startswith(b" ") + inner + b" " * text.endswith(b" ")


def _column(batch: pa.RecordBatch, name: str) -> list:
    return batch.column(name).to_pylist()


def _digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches):
        texts = [normalised(t) for t in _column(batch, "text")]
        yield pa.record_batch(
            [
                batch.column("doc_id"),
                pa.array([len(t) for t in texts], pa.int32()),
                pa.array([hashlib.sha256(t).digest() for t in texts], pa.binary()),
            ],
            names=["doc_id", "n_bytes", "digest"],
        )


def _emit(trie: PatriciaTrie, rows: int = 2000, most: int = 16 << 20) -> Iterator[pa.RecordBatch]:
    keys, owners, counts, loads, held = [], [], [], [], 0

    def batch():
        return pa.record_batch(
            [
                pa.array(keys, pa.binary()),
                pa.array([len(k) for k in keys], pa.int32()),
                pa.array(loads, pa.binary()),
                pa.array(owners, pa.int64()),
                pa.array(counts, pa.int64()),
            ],
            names=["text", "n_bytes", "digest", "owner", "n"],
        )

    for key, owner, count, load in trie.items():
        keys.append(key), owners.append(owner), counts.append(count), loads.append(load)
        held += len(key)
        if len(keys) >= rows or held >= most:
            yield batch()
            keys, owners, counts, loads, held = [], [], [], [], 0
    if keys:
        yield batch()


def _merge_in_task(budget: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trie = PatriciaTrie(1 << 62)
        for batch in slices(batches):
            for doc, raw in zip(_column(batch, "doc_id"), _column(batch, "text")):
                text = normalised(raw)
                trie.insert(text, doc, 1, hashlib.sha256(text).digest())
                if trie.used > budget:
                    yield from _emit(trie)
        yield from _emit(trie)

    return run


def _owners(budget: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trie = PatriciaTrie(budget)
        for batch in slices(batches):
            for row in zip(*(_column(batch, c) for c in ("text", "owner", "n", "digest"))):
                trie.insert(*row)
        out: list[tuple] = []
        for key, owner, count, digest in trie.items():
            out.append((len(key), digest, owner, count))
            if len(out) == 10_000:
                yield _owner_batch(out)
                out = []
        if out:
            yield _owner_batch(out)

    return run


def _owner_batch(rows: list[tuple]) -> pa.RecordBatch:
    size, digest, owner, count = zip(*rows)
    return pa.record_batch(
        [pa.array(size, pa.int32()), pa.array(digest, pa.binary()), pa.array(owner, pa.int64()), pa.array(count, pa.int64())],
        names=["n_bytes", "digest", "keep_id", "group_size"],
    )


def exact_classes(docs: DataFrame, task_budget: int = 32 << 20, trie_budget: int = 96 << 20) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256: one row for each row of docs.

    task_budget, trie_budget: bytes of trie that a map task, a partition's trie may hold; the first then sends
    on what it has, the second spills by subtree.
    """
    spark = docs.sparkSession
    rows = doc_text(docs)
    owners = (
        rows.mapInArrow(_merge_in_task(task_budget), _FOUND)
        .repartition(partitions_for(spark), "n_bytes", F.xxhash64("digest"))
        .mapInArrow(_owners(trie_budget), _OWNERS)
    )
    marked = rows.mapInArrow(_digests, _DIGEST)
    # The trie alone says which texts are equal; length and SHA-256 only lead a row to its owner.
    return marked.join(owners, ["n_bytes", "digest"]).select(
        "doc_id",
        "keep_id",
        "group_size",
        (F.col("doc_id") == F.col("keep_id")).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )


@F.pandas_udf(T.StringType())
def _digest_of(texts: pd.Series) -> pd.Series:
    return texts.map(lambda t: hashlib.sha256(normalised(bytes(t))).hexdigest())


def drop_copies(docs: DataFrame) -> DataFrame:
    """docs with one row of each text: that of the least doc_id, or any one of its repeats.

    Rows whose doc_id repeats or is null are told apart by their texts.
    """
    classes = written(exact_classes(docs), "copies")
    odd = written(odd_ids(classes).select(F.col("doc_id").alias("_id")), "odd")
    own_id = docs["doc_id"].cast("long")
    plain = classes.where("kept").select(F.col("doc_id").alias("_id")).join(odd, "_id", "left_anti")
    known = docs.join(plain, own_id == plain["_id"], "left_semi")
    if not odd.take(1):
        return known
    text = F.coalesce(F.col("text").cast("string"), F.lit("")).cast("binary")
    rest = docs.join(odd, own_id.eqNullSafe(odd["_id"]), "left_semi").withColumn("_own_text", _digest_of(text))
    owners = classes.select("keep_id", F.col("text_sha256").alias("_owned")).distinct()
    rest = rest.join(owners, (rest["_own_text"] == owners["_owned"]) & rest["doc_id"].cast("long").eqNullSafe(owners["keep_id"]), "left_semi")
    return known.unionByName(rest.dropDuplicates(["doc_id", "_own_text"]).select(*docs.columns))
