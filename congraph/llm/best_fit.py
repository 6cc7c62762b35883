"""Packing of token sequences by minimum bin slack.

Which pieces share a sequence depends on their lengths alone, so the search runs on the histogram of lengths,
at most `capacity` numbers for any corpus: the longest length left opens a bin, a bitset subset-sum over the
lengths left finds the fullest completion, and that combination is used as often as the counts allow before
the next search. Pieces then find their places by their rank among pieces of their length.

Cases: null text = empty text, one piece with the end id; a text of over `capacity` ids is cut into pieces of
`capacity`, the last may be shorter; ties (equal lengths) are ranked by their place in the written pieces;
repeated doc_ids keep apart; an empty table gives no rows; further columns are left alone.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from congraph.llm.common import doc_text, written
from congraph.llm.tokens import encoder

CAPACITY = 2048
_PIECES = "doc_id long, piece int, start long, length int, ids_crc32 long, part int, place long"
_PLACED = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"


def fullest(counts: dict[int, int], room: int) -> dict[int, int]:
    """The multiset of lengths (at most counts of each) whose sum comes closest to room from below."""
    reach, steps, goal, mask = 1, [], 1 << room, (1 << room + 1) - 1
    for length in sorted((x for x, n in counts.items() if n and x <= room), reverse=True):
        left, take = min(counts[length], room // length), 1
        while left and not reach & goal:
            take = min(take, left)
            steps.append((length, take, reach))
            reach |= (reach << length * take) & mask
            left, take = left - take, 2 * take
        if reach & goal:
            break
    total, chosen = reach.bit_length() - 1, {}
    for length, take, before in reversed(steps):
        if not before >> total & 1:
            chosen[length] = chosen.get(length, 0) + take
            total -= length * take
    return chosen


def bin_plan(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[dict[int, int], int]]:
    """[(lengths of a bin, number of such bins)] that uses every piece of the histogram once."""
    left, plan = {x: n for x, n in counts.items() if n}, []
    while left:
        seed = max(left)
        rest = dict(left)
        rest[seed] -= 1
        chosen = fullest(rest, capacity - seed)
        chosen[seed] = chosen.get(seed, 0) + 1
        times = min(left[x] // n for x, n in chosen.items())
        plan.append((chosen, times))
        for x, n in chosen.items():
            left[x] -= n * times
            if not left[x]:
                del left[x]
    return plan


def _places(plan: list[tuple[dict[int, int], int]]) -> dict[int, tuple[np.ndarray, ...]]:
    """By length: first rank, first bin, pieces in a bin and their offset, of each run of equal bins."""
    runs: dict[int, list[tuple[int, int, int, int]]] = {}
    ranks: dict[int, int] = {}
    first_bin = 0
    for chosen, times in plan:
        offset = 0
        for length in sorted(chosen, reverse=True):
            n, rank = chosen[length], ranks.get(length, 0)
            runs.setdefault(length, []).append((rank, first_bin, n, offset))
            ranks[length] = rank + n * times
            offset += n * length
        first_bin += times
    return {x: tuple(np.array(c, "int64") for c in zip(*r)) for x, r in runs.items()}


def _cut(name: str, end_id: int, capacity: int, path: str | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache, part = encoder(name, words=True, path=path), TaskContext.get().partitionId()
        seen = np.zeros(capacity + 1, "int64")
        end = np.array([end_id], cache.dtype).tobytes()
        for batch in batches:
            rows = []
            for doc, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist()):
                ids = np.frombuffer(cache.encode(text.decode()) + end, cache.dtype).astype("<u4")
                for piece, start in enumerate(range(0, len(ids), capacity)):
                    cut = ids[start : start + capacity]
                    rows.append((doc, piece, start, len(cut), zlib.crc32(cut.tobytes()), part, int(seen[len(cut)])))
                    seen[len(cut)] += 1
            if rows:
                types = (pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.int64())
                yield pa.record_batch([pa.array(c, t) for c, t in zip(zip(*rows), types)], names=[x.split()[0] for x in _PIECES.split(", ")])

    return run


def _place(places: dict[int, tuple[np.ndarray, ...]]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length, rank = (batch.column(c).to_numpy().astype("int64") for c in ("length", "rank"))
            bins, offsets = np.empty_like(rank), np.empty_like(rank)
            for x in np.unique(length):
                at = np.flatnonzero(length == x)
                first, first_bin, n, offset = places[int(x)]
                k = np.searchsorted(first, rank[at], side="right") - 1
                step = rank[at] - first[k]
                bins[at] = first_bin[k] + step // n[k]
                offsets[at] = offset[k] + step % n[k] * x
            kept = [batch.column(c) for c in ("doc_id", "piece", "start")]
            yield pa.record_batch(
                [*kept, pa.array(length), batch.column("ids_crc32"), pa.array(bins), pa.array(offsets)],
                names=[x.split()[0] for x in _PLACED.split(", ")],
            )

    return run


def place_pieces(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """Sequence and offset for written pieces (columns of _PIECES; part, place: rank of a length within a part)."""
    counts = pieces.groupBy("part", "length").agg(F.count(F.lit(1)).alias("n"))
    counts = written(counts, "lengths")
    # At most `capacity` rows, whatever the corpus.
    histogram = {r.length: r.n for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    before = W.partitionBy("length").orderBy("part").rowsBetween(W.unboundedPreceding, 0)
    bases = counts.select("part", "length", (F.sum("n").over(before) - F.col("n")).alias("base"))
    ranked = pieces.join(bases, ["part", "length"]).withColumn("rank", F.col("place") + F.col("base"))
    return ranked.mapInArrow(_place(_places(bin_plan(histogram, capacity))), _PLACED)


def pack_documents(docs: DataFrame, name: str = "word_bpe_49k.json", end_id: int = 0, capacity: int = CAPACITY, path: str | None = None) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset: one row for each piece of each row of docs."""
    return place_pieces(written(doc_text(docs).mapInArrow(_cut(name, end_id, capacity, path), _PIECES), "pieces"), capacity)


def packed_sequences(docs: DataFrame, placed: DataFrame, name: str = "word_bpe_49k.json", end_id: int = 0, path: str | None = None) -> DataFrame:
    """sequence_id, ids array: the sequences themselves; a group is one sequence and holds `capacity` ids at most."""

    def fill(table: pa.Table) -> pa.Table:
        cache = encoder(name, words=True, path=path)
        rows = sorted(zip(*(table.column(c).to_pylist() for c in ("offset", "start", "length", "text"))))
        end, ids = np.array([end_id], cache.dtype).tobytes(), []
        for _, start, length, text in rows:
            ids.extend(np.frombuffer(cache.encode(text.decode()) + end, cache.dtype)[start : start + length].tolist())
        return pa.table({"sequence_id": table.column("sequence_id")[:1].combine_chunks(), "ids": pa.array([ids], pa.list_(pa.int32()))})

    return doc_text(docs).join(placed, "doc_id").groupBy("sequence_id").applyInArrow(fill, "sequence_id long, ids array<int>")
