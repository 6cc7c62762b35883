"""Token ids in files of fixed-width bit-packed blocks, with random access.

A file holds: MAGIC; blocks of BLOCK ids, each id in the minimum number of bits of the vocabulary, little
end first, a block padded to whole 64-bit words; then doc ids, doc starts and block offsets as 64-bit
integers; then the TAIL. One file is one range of doc ids in ascending order, so the files in order of their
ranges hold the corpus in order.

Cases: null text = empty text, one end id; repeated doc_ids stand side by side; an empty table gives no file
and no rows; further columns are left alone.
"""

from __future__ import annotations

import io
import os
import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from congraph.llm.common import bucket_bounds, bucket_of, doc_text, filesystem, partitions_for, work_dir, written
from congraph.llm.tokens import encoder

MAGIC = b"CGPACK1\n"
#: bits, ids in a block, ids, documents, blocks, crc32 of the blocks
TAIL = struct.Struct("<IIQQQI8s")
BLOCK = 4096


def id_bits(vocab_size: int) -> int:
    return max(1, (vocab_size - 1).bit_length())


def pack(ids: np.ndarray, bits: int) -> bytes:
    """Ids side by side in `bits` bits each; 64 ids make `bits` words."""
    rows = -(-len(ids) // 64)
    padded = np.zeros(rows * 64, "<u8")
    padded[: len(ids)] = ids
    lanes, words = padded.reshape(rows, 64), np.zeros((rows, bits), "<u8")
    for lane in range(64):
        word, shift = divmod(lane * bits, 64)
        words[:, word] |= lanes[:, lane] << np.uint64(shift)
        if shift + bits > 64:
            words[:, word + 1] |= lanes[:, lane] >> np.uint64(64 - shift)
    return words.tobytes()


def unpack(data: bytes, n: int, bits: int) -> np.ndarray:
    words = np.frombuffer(data, "<u8").reshape(-1, bits)
    lanes, mask = np.empty((len(words), 64), "<u8"), np.uint64((1 << bits) - 1)
    for lane in range(64):
        word, shift = divmod(lane * bits, 64)
        lanes[:, lane] = words[:, word] >> np.uint64(shift)
        if shift + bits > 64:
            lanes[:, lane] |= words[:, word + 1] << np.uint64(64 - shift)
    return (lanes & mask).reshape(-1)[:n].astype("<u4")


class PackWriter:
    """Writes one file front to back; memory holds one block and the table of documents."""

    def __init__(self, out, bits: int):
        self.out, self.bits = out, bits
        self.held, self.n_held, self.n_ids, self.at, self.crc = [], 0, 0, len(MAGIC), 0
        self.docs, self.starts, self.blocks = [], [], []
        out.write(MAGIC)

    def add(self, doc_id: int, ids: np.ndarray) -> None:
        self.docs.append(doc_id), self.starts.append(self.n_ids)
        self.held.append(ids)
        self.n_held += len(ids)
        self.n_ids += len(ids)
        if self.n_held >= 16 * BLOCK:
            self._flush(False)

    def _flush(self, last: bool) -> None:
        ids = np.concatenate(self.held) if self.held else np.empty(0, "<u4")
        full = len(ids) if last else len(ids) // BLOCK * BLOCK
        # A block is a whole number of rows of 64, so blocks packed together are the blocks side by side.
        data, each = pack(ids[:full], self.bits), BLOCK // 64 * self.bits * 8
        self.blocks.extend(range(self.at, self.at + len(data), each))
        self.out.write(data)
        self.crc = zlib.crc32(data, self.crc)
        self.at += len(data)
        self.held, self.n_held = [ids[full:]], len(ids) - full

    def close(self) -> None:
        self._flush(True)
        for column in (self.docs, self.starts, self.blocks):
            self.out.write(np.array(column, "<i8").tobytes())
        self.out.write(TAIL.pack(self.bits, BLOCK, self.n_ids, len(self.docs), len(self.blocks), self.crc, MAGIC))


class PackReader:
    """Random access to one file: ids [a, b) read only the blocks that hold them."""

    def __init__(self, file):
        self.file = file
        file.seek(0, os.SEEK_END)
        end = file.tell() - TAIL.size
        file.seek(end)
        self.bits, self.block, self.n_ids, n_docs, n_blocks, self.crc, magic = TAIL.unpack(file.read(TAIL.size))
        if magic != MAGIC:
            raise ValueError("not a file of packed ids")
        file.seek(end - 8 * (2 * n_docs + n_blocks))
        table = np.frombuffer(file.read(8 * (2 * n_docs + n_blocks)), "<i8")
        self.docs, self.starts, self.blocks = table[:n_docs], table[n_docs : 2 * n_docs], table[2 * n_docs :]
        self.end = end - 8 * len(table)

    def ids(self, a: int, b: int) -> np.ndarray:
        if a >= b:
            return np.empty(0, "<u4")
        first, last = a // self.block, (b - 1) // self.block
        self.file.seek(int(self.blocks[first]))
        stop = int(self.blocks[last + 1]) if last + 1 < len(self.blocks) else self.end
        data = self.file.read(stop - int(self.blocks[first]))
        n = min(self.n_ids, (last + 1) * self.block) - first * self.block
        return unpack(data, n, self.bits)[a - first * self.block : b - first * self.block]

    def documents(self, at_once: int = 1 << 20) -> Iterator[tuple[int, int, np.ndarray]]:
        """(doc_id, start in the file, ids), a run of about at_once ids read at a time."""
        stops = np.append(self.starts[1:], self.n_ids)
        i = 0
        while i < len(self.docs):
            j = max(i + 1, int(np.searchsorted(stops, self.starts[i] + at_once, side="right")))
            run = self.ids(int(self.starts[i]), int(stops[j - 1]))
            for k in range(i, j):
                a = int(self.starts[k] - self.starts[i])
                yield int(self.docs[k]), int(self.starts[k]), run[a : a + int(stops[k] - self.starts[k])]
            i = j


_MANIFEST = "bucket int, path string, n_docs long, n_ids long"
_READ = "doc_id long, start long, n_tokens long, ids_crc32 long"


def _write_files(folder: str, name: str, end_id: int, path: str | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, base = filesystem(folder)
        cache = encoder(name, words=False, path=path)
        bits, end = id_bits(cache.vocab_size), np.array([end_id], cache.dtype).tobytes()
        now, writer, stream, file, done = None, None, None, "", []

        def close():
            writer.close()
            stream.close()
            done.append((now, file, len(writer.docs), writer.n_ids))

        for batch in batches:
            for bucket, doc, text in zip(*(batch.column(c).to_pylist() for c in ("bucket", "doc_id", "text"))):
                if bucket != now:
                    if writer:
                        close()
                    # A name of its own for each attempt: only the files that the written manifest names count.
                    now, file = bucket, f"{base}/{bucket:06d}-{uuid.uuid4().hex}.ids"
                    fs.create_dir(base, recursive=True)
                    stream = fs.open_output_stream(file)
                    writer = PackWriter(stream, bits)
                writer.add(doc, np.frombuffer(cache.encode(text.decode()) + end, cache.dtype))
        if writer:
            close()
        if done:
            yield pa.RecordBatch.from_pylist([dict(zip(("bucket", "path", "n_docs", "n_ids"), x)) for x in done], pa.schema([("bucket", pa.int32()), ("path", pa.string()), ("n_docs", pa.int64()), ("n_ids", pa.int64())]))

    return run


def _read_files(folder: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, _ = filesystem(folder)
        for batch in batches:
            for path, base in zip(batch.column("path").to_pylist(), batch.column("base").to_pylist()):
                with fs.open_input_file(path) as file:
                    rows = [(d, base + s, len(x), zlib.crc32(x.tobytes())) for d, s, x in PackReader(file).documents()]
                for a in range(0, len(rows), 10_000):
                    columns = zip(*rows[a : a + 10_000])
                    yield pa.record_batch([pa.array(c, pa.int64()) for c in columns], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return run


def write_packed(docs: DataFrame, name: str = "byte_bpe_50k.json", end_id: int = 2, buckets: int | None = None, path: str | None = None) -> tuple[str, DataFrame]:
    """Encodes docs and writes them; (folder, manifest: bucket, path, n_docs, n_ids, base = ids in earlier files)."""
    spark = docs.sparkSession
    folder, n = work_dir(spark, "ids"), buckets or partitions_for(spark)
    rows = doc_text(docs)
    bounds = bucket_bounds(rows.select("doc_id"), "doc_id", n)
    manifest = written(
        rows.withColumn("bucket", bucket_of(F.col("doc_id"), bounds))
        .repartitionById(n, F.col("bucket"))
        .sortWithinPartitions("bucket", "doc_id")
        .mapInArrow(_write_files(folder, name, end_id, path), _MANIFEST),
        "manifest",
    )
    # One row for each file.
    return folder, manifest.withColumn("base", F.sum("n_ids").over(W.orderBy("bucket").rowsBetween(W.unboundedPreceding, 0)) - F.col("n_ids"))


def read_packed(spark: SparkSession, folder: str, manifest: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document in the files."""
    return manifest.select("bucket", "path", "base").repartition(partitions_for(spark), "bucket").mapInArrow(_read_files(folder), _READ)


def packed_ids(folder: str, path: str, a: int, b: int) -> np.ndarray:
    """Ids [a, b) of one file, without the rest of it."""
    fs, _ = filesystem(folder)
    with fs.open_input_file(path) as file:
        return PackReader(file).ids(a, b)


def in_memory(rows: list[tuple[int, np.ndarray]], bits: int) -> PackReader:
    out = io.BytesIO()
    writer = PackWriter(out, bits)
    for doc, ids in rows:
        writer.add(doc, ids)
    writer.close()
    return PackReader(out)
