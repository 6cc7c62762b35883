"""Jaccard join over word shingles, for components of near copies.

Documents with equal shingle sets are one class. Of each class the shingles are put in order, rare first, and
only a prefix is joined: sets that link share a shingle of both prefixes. How rare a shingle is comes from a
counting sketch over all documents, a table of fixed size: its order is the same everywhere, which is all that
the filter needs to lose nothing, and common shingles stand out in it at any scale.

Round one takes each posting list as a star around the member that has the shingle earliest in its order (the
one with the fewest rare shingles of its own, which is the original among its edited copies); pairs pass the length
and position filters and are verified. Round two takes, for each such hub, all classes that share a list with it, once
whatever the number of lists. Where they lie in several components, those outside the largest one are held against the
others by length and by the suffix filter: both sets' counts over PARTS ranges of hashes bound what they can have in common.
What passes is verified, each pair once. Pairs inside a component need no check, as they can't change the result; so
large groups of copies cost their size, not its square. Lists of very common shingles are dealt in parts, each with a
hub of its own, and the hubs of one list form a star.

Cases: no words or null text: the empty set, linked with nothing; fewer words than a shingle: the whole
sequence; repeated rows of a doc_id are rows of their own with one component; null ids come last, a group
without any other has a null component; ties in rarity are ordered by
hash; an empty table gives no rows; further columns are left alone. Sets are compared as 64-bit hashes of
shingles, and a class is known by 64 bits of its set.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from congraph.llm.common import Stages, doc_text, odd_ids, partitions_for, sieve, slices
from congraph.llm.components import components
from congraph.llm.shingles import WIDTH, mixed, shingle_set

#: Counters of the sketch: 2^22 of 4 bytes, for any corpus.
SKETCH_BITS = 22
_CHUNK = 1 << 14
#: Longs, as a power of two, of the bitmap that leads a scan to the documents whose sets are wanted: 2 MB, for any corpus.
SIEVE_BITS = 18
#: Ranges of hashes whose counts stand for a set before its pairs are verified.
PARTS = 1024
#: Members of a group, and of those outside its largest component, that one task holds against each other.
BLOCK = 1000
#: Documents with a shingle beyond which its list is dealt in parts.
LONG_LIST = 20_000
#: Neighbours by length that a member of a list is tried against, for whether it may link with any.
NEIGHBOURS = 16

_SETS = "doc_id long, class long, n int, chunk int, part int, counts binary"
_POSTING = "gram long, salt int, class long, n int, pos int"
_PAIR = "kind int, a long, b long, n int, pos int"
#: Kinds of rows of the star round: a candidate pair; a group and a member; a long list and the hub of a part of it.
CANDIDATE, MEMBER, PART_HUB = 0, 1, 2


def least_overlap(n: int, m: int, percent: int) -> int:
    """Fewest common shingles of sets of n and m with 100 * common >= percent * union."""
    return -(-percent * (n + m) // (100 + percent))


def prefix_length(n: int, percent: int) -> int:
    return n - -(-percent * n // 100) + 1


def part_counts(grams: np.ndarray) -> bytes:
    """How many shingles fall in each range of hashes, up to 255. Sums of differences bound the sets' difference from below."""
    counts = np.bincount((grams >> np.uint64(64 - PARTS.bit_length() + 1)).astype("i8"), minlength=PARTS)
    return np.minimum(counts, 255).astype("u1").tobytes()


def class_of(grams: np.ndarray) -> int:
    return int.from_bytes(hashlib.blake2b(grams.tobytes(), digest_size=8).digest(), "little", signed=True)


def _count(width: int):
    """Class and size of each document; and, once a task, its counts by chunks of the sketch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        sketch, seen = np.zeros(1 << SKETCH_BITS, "<u4"), set()
        none = lambda n, t: pa.nulls(n, t)
        names = [x.split()[0] for x in _SETS.split(", ")]
        for batch in slices(batches):
            classes, sizes = [], []
            for text in batch.column("text").to_pylist():
                grams = shingle_set(text, width)
                own = class_of(grams)
                classes.append(own), sizes.append(len(grams))
                if own not in seen and len(grams):
                    if len(seen) < 1_000_000:
                        seen.add(own)
                    np.add.at(sketch, (grams >> np.uint64(64 - SKETCH_BITS)).astype("i8"), 1)
            k = len(classes)
            yield pa.record_batch([batch.column("doc_id"), pa.array(classes, pa.int64()), pa.array(sizes, pa.int32()), none(k, pa.int32()), none(k, pa.int32()), none(k, pa.binary())], names=names)
        part = TaskContext.get().partitionId()
        for a in range(0, len(sketch), _CHUNK):
            if (piece := sketch[a : a + _CHUNK]).any():
                yield pa.record_batch([none(1, pa.int64()), none(1, pa.int64()), none(1, pa.int32()), pa.array([a // _CHUNK], pa.int32()), pa.array([part], pa.int32()), pa.array([piece.tobytes()], pa.binary())], names=names)

    return run


def _sum_chunks(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total = np.zeros(_CHUNK, "u8")
    for batch in batches:
        for data in batch.column("counts").to_pylist():
            total += np.frombuffer(data, "<u4")
    top = np.minimum(total, np.uint64(0xFFFFFFFF)).astype("<u4")
    yield pa.record_batch([pa.array([key[0].as_py()], pa.int32()), pa.array([top.tobytes()], pa.binary())], names=["chunk", "counts"])


def rarity_sketch(chunks: DataFrame) -> np.ndarray:
    """Counts of all documents by the first bits of a shingle's hash; 2^SKETCH_BITS numbers reach the driver."""
    few = chunks.select("chunk", F.pmod("part", F.lit(16)).alias("salt"), "counts")
    half = few.groupBy("chunk", "salt").applyInArrow(_sum_chunks, "chunk int, counts binary")
    out = np.zeros(1 << SKETCH_BITS, "<u4")
    for r in half.groupBy("chunk").applyInArrow(_sum_chunks, "chunk int, counts binary").collect():
        out[r.chunk * _CHUNK : (r.chunk + 1) * _CHUNK] = np.frombuffer(r.counts, "<u4")
    return out


def _prefixes(sketch, width: int, percent: int, long_list: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts, seen = sketch.value, set()
        for batch in slices(batches):
            out: list[list[np.ndarray]] = [[], [], [], [], []]
            for text in batch.column("text").to_pylist():
                grams = shingle_set(text, width)
                if not (n := len(grams)):
                    continue
                own = class_of(grams)
                if own in seen:  # a copy in this task; further copies go when lists are read
                    continue
                if len(seen) < 1_000_000:
                    seen.add(own)
                rare = counts[(grams >> np.uint64(64 - SKETCH_BITS)).astype("i8")]
                order = np.lexsort((grams, rare))[: prefix_length(n, percent)]
                first, held = grams[order].view("i8"), rare[order].astype("i8")
                # The count is at least the list's length; 0 marks lists that are dealt whole.
                salt = np.where(held > long_list, own % np.maximum(1, -(-held // long_list)) + 1, 0)
                for column, values in zip(out, (first, salt.astype("i4"), np.full(len(first), own), np.full(len(first), n, "i4"), np.arange(len(first), dtype="i4"))):
                    column.append(values)
            if out[0]:
                yield pa.record_batch([pa.array(np.concatenate(c)) for c in out], names=[x.split()[0] for x in _POSTING.split(", ")])

    return run


def _stars(percent: int):
    """Lists come sorted by gram, salt, pos, n, class. Gives their pairs around the first member, and who met there."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split()[0] for x in _POSTING.split(", ")]
        held: list[list[np.ndarray]] = []  # the last list, which may go on; LONG_LIST bounds its length

        def lists(columns):
            gram, salt, own = columns[:3]
            fresh = np.concatenate(([True], (gram[1:] != gram[:-1]) | (salt[1:] != salt[:-1])))
            # Copies of a class in one list are neighbours.
            new = np.concatenate(([True], fresh[1:] | (own[1:] != own[:-1])))
            columns, fresh = [c[new] for c in columns], fresh[new]
            start = np.maximum.accumulate(np.where(fresh, np.arange(len(fresh)), 0))
            return _star_rows(*columns, start, percent)

        for batch in batches:
            columns = [batch.column(c).to_numpy() for c in names]
            gram, salt = columns[:2]
            if not len(gram):
                continue
            cut = np.flatnonzero((gram != gram[-1]) | (salt != salt[-1]))
            cut = cut[-1] + 1 if len(cut) else 0
            if cut or held and (held[0][0][0] != gram[0] or held[0][1][0] != salt[0]):
                yield from lists([np.concatenate(c) for c in zip(*held, [c[:cut] for c in columns])])
                held = []
            held.append([c[cut:] for c in columns])
        if held:
            yield from lists([np.concatenate(c) for c in zip(*held)])

    return run


def _star_rows(gram, salt, own, n, pos, start, percent) -> Iterator[pa.RecordBatch]:
    rank = np.arange(len(gram)) - start
    hub, zero = own[start], np.zeros(len(gram), "i4")

    def rows(kind, a, b, n, pos):
        if len(a):
            yield pa.record_batch([pa.array(np.full(len(a), kind, "i4")), pa.array(a), pa.array(b), pa.array(n), pa.array(pos)], names=[x.split()[0] for x in _PAIR.split(", ")])

    i = np.flatnonzero(rank > 0)
    i = i[passes(n[start[i]], pos[start[i]], n[i], pos[i], percent)]
    yield from rows(CANDIDATE, np.minimum(hub[i], own[i]), np.maximum(hub[i], own[i]), zero[i], zero[i])
    # Pairs with the hub are candidates; members beside it count if they may link with another.
    whole = salt == 0
    more = np.flatnonzero(whole & (rank > 0))
    more = more[_may_link(start[more], n[more], pos[more], percent)]
    yield from rows(MEMBER, hub[more], own[more], zero[more], zero[more])
    i = np.flatnonzero(~whole)
    yield from rows(MEMBER, gram[i], own[i], zero[i], zero[i])
    i = np.flatnonzero(~whole & (rank == 0))
    yield from rows(PART_HUB, gram[i], own[i], n[i], pos[i])


def _may_link(of: np.ndarray, n: np.ndarray, pos: np.ndarray, percent: int) -> np.ndarray:
    """Whether another row of the same list passes the filters with a row. In lists too long to try all others, whether the
    next one by length is near enough."""
    found = np.zeros(len(of), bool)
    order = np.lexsort((n, of))
    of, n, pos = of[order], n[order].astype("i8"), pos[order]
    _, first, size = np.unique(of, return_index=True, return_counts=True)
    long = np.repeat(size > NEIGHBOURS + 1, size)
    for d in range(1, NEIGHBOURS + 1):
        t = np.flatnonzero(of[d:] == of[:-d])
        if not len(t):
            break
        t = t[passes(n[t], pos[t], n[t + d], pos[t + d], percent) | (long[t] & (100 * n[t] >= percent * n[t + d]))]
        found[t] = found[t + d] = True
    out = np.empty(len(of), bool)
    out[order] = found
    return out


def passes(n: np.ndarray, i: np.ndarray, m: np.ndarray, j: np.ndarray, percent: int) -> np.ndarray:
    """Length filter, and position filter: with a common shingle at i and j, what may still be common is enough."""
    n, i, m, j = (x.astype("i8") for x in (n, i, m, j))
    need = -(-percent * (n + m) // (100 + percent))
    near = 100 * np.minimum(n, m) >= percent * np.maximum(n, m)
    # Shingles before the common one may be common too, so it is the least of both prefixes that counts.
    most = np.minimum(i, j) + 1 + np.minimum(n - i - 1, m - j - 1)
    return near & (most >= need)


def _verify(percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, 200):
            a, b, links = batch.column("a").to_pylist(), batch.column("b").to_pylist(), []
            for k, (x, y) in enumerate(zip(batch.column("set_a"), batch.column("set_b"))):
                x, y = np.frombuffer(x.as_buffer(), "<u8"), np.frombuffer(y.as_buffer(), "<u8")
                both = np.concatenate((x, y))
                both.sort(kind="stable")
                if np.count_nonzero(both[1:] == both[:-1]) >= least_overlap(len(x), len(y), percent):
                    links.append(k)
            if links:
                yield pa.record_batch([pa.array([a[k] for k in links], pa.int64()), pa.array([b[k] for k in links], pa.int64())], names=["a", "b"])

    return run


def _counts(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            sets = [shingle_set(t, width) for t in batch.column("text").to_pylist()]
            columns = [pa.array([class_of(s) for s in sets], pa.int64()), pa.array([len(s) for s in sets], pa.int32()), pa.array([part_counts(s) for s in sets], pa.binary())]
            yield pa.record_batch(columns, names=["class", "n", "counts"])

    return run


def _sets(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            sets = [shingle_set(t, width) for t in batch.column("text").to_pylist()]
            yield pa.record_batch([pa.array([class_of(s) for s in sets], pa.int64()), pa.array([s.tobytes() for s in sets], pa.binary())], names=["class", "grams"])

    return run


def _near(percent: int):
    """The suffix filter: what both sets hold of each range of hashes bounds their overlap."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, 500):
            x, y = (np.frombuffer(b"".join(batch.column(c).to_pylist()), "u1").reshape(-1, PARTS).astype("i2") for c in ("x", "y"))
            total = batch.column("n").to_numpy().astype("i8")
            ok = np.flatnonzero(np.abs(x - y).sum(1) <= total - 2 * -(-percent * total // (100 + percent)))
            yield pa.record_batch([batch.column(c).take(pa.array(ok)) for c in ("a", "b")], names=["a", "b"])

    return run


class _Rows:
    """The texts, led to by class: of each wanted class one document is read again, and only those are shingled."""

    def __init__(self, rows: DataFrame, docs_of: DataFrame, width: int, stages: Stages):
        self.rows, self.width, self.stages = rows, width, stages
        # Copies meet in the tasks that read them, before they are dealt.
        self.chosen = docs_of.where("n > 0").groupBy("class").agg(F.min(F.coalesce("doc_id", F.lit(0))).alias("doc_id"))

    def _of(self, wanted: DataFrame) -> DataFrame:
        ids = self.chosen.join(wanted.distinct(), "class", "left_semi").select(F.xxhash64("doc_id").alias("key"))
        keyed = self.rows.withColumn("key", F.xxhash64(F.coalesce("doc_id", F.lit(0))))
        return keyed.where(sieve(ids, self.stages, SIEVE_BITS)).select("text")

    def counts(self, wanted: DataFrame) -> DataFrame:
        """class, n, counts, once each."""
        made = self.stages.write(self._of(wanted).mapInArrow(_counts(self.width), "class long, n int, counts binary"), "counts")
        return made.dropDuplicates(["class"])

    def links(self, pairs: DataFrame, counts: DataFrame, percent: int) -> DataFrame:
        """Pairs that link: those that pass the suffix filter are verified, once each, beside their two sets."""
        side = lambda s, c: counts.select(F.col("class").alias(s), F.col("n").alias(f"n_{s}"), F.col("counts").alias(c))
        both = pairs.join(side("a", "x"), "a").join(side("b", "y"), "b").select("a", "b", (F.col("n_a") + F.col("n_b")).alias("n"), "x", "y")
        return self.verified(self.stages.write(both.mapInArrow(_near(percent), "a long, b long"), "near"), percent)

    def verified(self, pairs: DataFrame, percent: int) -> DataFrame:
        wanted = pairs.select(F.explode(F.array("a", "b")).alias("class"))
        sets = self.stages.write(self._of(wanted).mapInArrow(_sets(self.width), "class long, grams binary"), "grams").dropDuplicates(["class"])
        a = sets.select(F.col("class").alias("a"), F.col("grams").alias("set_a"))
        b = sets.select(F.col("class").alias("b"), F.col("grams").alias("set_b"))
        return self.stages.write(pairs.join(b, "b").join(a, "a").mapInArrow(_verify(percent), "a long, b long"), "links")


def _crossing(percent: int):
    """Rows of cells, sorted by cell: all members of a block, and probes; pairs of both that may link."""
    step = PARTS // 128

    def pairs(own, n, component, main, probe, counts):
        order = np.argsort(n[~probe], kind="stable")
        base = [c[~probe][order] for c in (own, n, component, main, counts)]
        coarse = base[4].reshape(len(order), 128, step).sum(2, dtype="i4")
        for k in np.flatnonzero(probe):
            lo, hi = np.searchsorted(base[1], (-(-percent * int(n[k]) // 100), 100 * int(n[k]) // percent + 1))
            # Both ends outside the largest component: the pair comes twice, and one is enough.
            at = lo + np.flatnonzero((base[2][lo:hi] != component[k]) & ((base[0][lo:hi] > own[k]) | (base[2][lo:hi] == base[3][lo:hi])))
            total = base[1][at].astype("i8") + int(n[k])
            apart = total - 2 * -(-percent * total // (100 + percent))
            near = np.abs(coarse[at] - counts[k].reshape(128, step).sum(1, dtype="i4")).sum(1) <= apart
            at, apart = at[near], apart[near]
            at = at[np.abs(base[4][at].astype("i2") - counts[k].astype("i2")).sum(1) <= apart]
            if len(at):
                yield pa.record_batch([pa.array(np.minimum(base[0][at], own[k])), pa.array(np.maximum(base[0][at], own[k]))], names=["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, now = [], None

        def flush():
            if held:
                yield from pairs(*(np.concatenate(c) for c in zip(*held)))

        for batch in batches:
            cell = np.stack([batch.column(c).to_numpy() for c in ("group", "block", "probes")], 1)
            if not len(cell):
                continue
            columns = [batch.column(c).to_numpy(zero_copy_only=False) for c in ("class", "n", "component", "main", "probe")]
            columns.append(np.frombuffer(b"".join(batch.column("counts").to_pylist()), "u1").reshape(len(cell), PARTS))
            cuts = [0, *(np.flatnonzero((cell[1:] != cell[:-1]).any(1)) + 1), len(cell)]
            for a, b in zip(cuts, cuts[1:]):
                if tuple(cell[a]) != now:
                    yield from flush()
                    held, now = [], tuple(cell[a])
                held.append([c[a:b] for c in columns])
        yield from flush()

    return run


def _cells(members: DataFrame, counts: DataFrame, stages: Stages) -> DataFrame:
    """members: group, class, component. Groups with several components, dealt in cells: a block of all members beside a
    block of those outside the largest component."""
    of = members.groupBy("group", "component").agg(F.count(F.lit(1)).alias("size"))
    of = of.groupBy("group").agg(F.max_by("component", F.struct("size", "component")).alias("main"), F.sum("size").alias("all"), F.max("size").alias("most"), F.count(F.lit(1)).alias("parts"))
    several = stages.write(of.where("parts > 1").select("group", "main", F.ceil(F.col("all") / BLOCK).alias("blocks"), F.ceil((F.col("all") - F.col("most")) / BLOCK).alias("probe_blocks")), "groups")
    rows = members.join(several, "group")
    place = lambda n: F.pmod(F.xxhash64("class"), F.col(n))
    every = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.col(n) - 1))
    kept = ("group", "class", "component", "main")
    base = rows.select(*kept, F.lit(False).alias("probe"), place("blocks").alias("block"), every("probe_blocks").alias("probes"))
    probe = rows.where("component <> main").select(*kept, F.lit(True).alias("probe"), every("blocks").alias("block"), place("probe_blocks").alias("probes"))
    return base.unionByName(probe).join(counts, "class")


def _candidates(members: DataFrame, counts: DataFrame, percent: int, stages: Stages) -> DataFrame:
    key = ("group", "block", "probes")
    cells = _cells(members, counts, stages).repartition(partitions_for(members.sparkSession), *key).sortWithinPartitions(*key)
    return cells.mapInArrow(_crossing(percent), "a long, b long").distinct()


def _part_stars(hubs: DataFrame, percent: int) -> DataFrame:
    """Candidate pairs of a long list's part hubs with the first of them."""
    first = hubs.groupBy("gram").agg(F.min(F.struct("pos", "n", "class")).alias("hub"))
    both = hubs.join(first, "gram").where(F.col("class") != F.col("hub.class"))
    n, m = F.col("n"), F.col("hub.n")
    near = (100 * F.least(n, m) >= percent * F.greatest(n, m)) & (
        F.least("pos", "hub.pos") + 1 + F.least(n - F.col("pos") - 1, m - F.col("hub.pos") - 1) >= F.ceil(percent * (n + m) / F.lit(100 + percent))
    )
    return both.where(near).select(F.least("class", "hub.class").alias("a"), F.greatest("class", "hub.class").alias("b"))


class _Starred:
    """What the star round gives: docs_of (doc_id, class, n), candidate pairs, members of groups, and the counts of both."""

    def __init__(self, docs: DataFrame, percent: int, width: int, stages: Stages, long_list: int):
        spark, parts = docs.sparkSession, partitions_for(docs.sparkSession)
        rows = doc_text(docs)
        first = stages.write(rows.mapInArrow(_count(width), _SETS), "sets")
        self.docs_of = first.where("chunk is null").select("doc_id", "class", "n")
        sketch = spark.sparkContext.broadcast(rarity_sketch(first.where("chunk is not null")))
        lists = rows.mapInArrow(_prefixes(sketch, width, percent, long_list), _POSTING).repartition(parts, "gram", "salt").sortWithinPartitions("gram", "salt", "pos", "n", "class")
        found = stages.write(lists.mapInArrow(_stars(percent), _PAIR).distinct(), "stars")
        hubs = found.where(F.col("kind") == PART_HUB).select(F.col("a").alias("gram"), F.col("b").alias("class"), "n", "pos")
        pairs = found.where(F.col("kind") == CANDIDATE).select("a", "b").unionByName(_part_stars(hubs, percent))
        self.pairs = stages.write(pairs.distinct(), "pairs")
        self.members = found.where(F.col("kind") == MEMBER).select(F.col("a").alias("group"), F.col("b").alias("class"))
        self.texts = _Rows(rows, self.docs_of, width, stages)
        self.counts = self.texts.counts(self.pairs.select(F.explode(F.array("a", "b")).alias("class")).unionByName(self.members.select("class")))


def near_pairs(docs: DataFrame, percent: int = 80, width: int = WIDTH, long_list: int = LONG_LIST) -> tuple[DataFrame, DataFrame]:
    """The join itself: (a, b), each pair of classes that link, once; and doc_id, class_id, n_shingles, n_links, one row
    for each row of docs. Rows of one class link with each other too, and n_links counts other rows.

    Every pair that passes the filters is verified, also inside a component, so the work grows with the number of links.
    """
    stages = Stages(docs.sparkSession)
    s = _Starred(docs, percent, width, stages, long_list)
    # With each class as its own component every pair of a group crosses.
    pairs = stages.write(s.pairs.unionByName(_candidates(s.members.withColumn("component", F.col("class")), s.counts, percent, stages)).distinct(), "pairs")
    links = Stages(docs.sparkSession).write(s.texts.links(pairs, s.counts, percent).distinct(), "links")
    sizes = s.docs_of.where("n > 0").groupBy("class").agg(F.count(F.lit(1)).alias("own"))
    both = links.select(F.col("a").alias("class"), F.col("b").alias("other")).unionByName(links.select(F.col("b").alias("class"), F.col("a").alias("other")))
    others = both.join(sizes.select(F.col("class").alias("other"), F.col("own").alias("size")), "other").groupBy("class").agg(F.sum("size").alias("linked"))
    counts = stages.write(sizes.join(others, "class", "left").select("class", (F.col("own") - 1 + F.coalesce("linked", F.lit(0))).alias("links")), "counts")
    members = s.docs_of.join(counts, "class", "left").select("doc_id", F.col("class").alias("class_id"), F.col("n").cast("long").alias("n_shingles"), F.coalesce("links", F.lit(0)).alias("n_links"))
    members = Stages(docs.sparkSession).write(members, "members")
    stages.clear()
    return links, members


def _grouped(docs: DataFrame, percent: int, width: int, long_list: int = LONG_LIST) -> tuple[DataFrame, DataFrame]:
    """(doc_id, n, class, group) of each row, group null without words; (group, least, least_class) of each group."""
    stages, kept = Stages(docs.sparkSession), Stages(docs.sparkSession)
    s = _Starred(docs, percent, width, stages, long_list)
    of = components(s.texts.links(s.pairs, s.counts, percent), stages)
    label = of.select(F.col("node").alias("class"), "component")
    members = s.members.join(label, "class", "left").withColumn("component", F.coalesce("component", "class"))
    members = stages.write(members, "members")
    crossing = stages.write(_candidates(members, s.counts, percent, stages).join(s.pairs, ["a", "b"], "left_anti"), "crossing")
    if crossing.take(1):
        more = s.texts.verified(crossing, percent)
        of = components(of.select(F.col("node").alias("a"), F.col("component").alias("b")).unionByName(more), stages)
        label = of.select(F.col("node").alias("class"), "component")
    tagged = s.docs_of.join(label, "class", "left").withColumn("group", F.when(F.col("n") > 0, F.coalesce("component", "class")))
    tagged = kept.write(tagged.select("doc_id", "n", "class", "group"), "tagged")
    # The least id, null ids last. Written, so that the join after it may split a group with many rows.
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "class"))
    least = kept.write(tagged.where("n > 0").groupBy("group").agg(first.alias("f")).select("group", F.col("f.doc_id").alias("least"), F.col("f.class").alias("least_class")), "least")
    stages.clear()
    return tagged, least


def near_components(docs: DataFrame, percent: int = 80, width: int = WIDTH, long_list: int = LONG_LIST) -> DataFrame:
    """doc_id, n_shingles, component_id (least doc_id reachable by links), class, one row for each row of docs.

    Pairs inside a component are left out here; `near_pairs` has them.
    """
    tagged, least = _grouped(docs, percent, width, long_list)
    return tagged.join(least, "group", "left").select("doc_id", F.col("n").cast("long").alias("n_shingles"), F.coalesce("least", "doc_id").alias("component_id"), F.col("class").alias("class_id"))


def _class_of_text(width: int):
    @F.pandas_udf("long")
    def run(texts: pd.Series) -> pd.Series:
        return texts.map(lambda t: class_of(shingle_set(bytes(t), width))).astype("int64")

    return run


def drop_near_copies(docs: DataFrame, percent: int = 80, width: int = WIDTH) -> DataFrame:
    """docs with one row of each component: that of the least doc_id, or any one of its repeats. Rows without words stay.

    Rows whose doc_id repeats or is null are told apart by their sets.
    """
    tagged, least = _grouped(docs, percent, width)
    odd = Stages(docs.sparkSession).write(odd_ids(tagged).select(F.col("doc_id").alias("_id")), "odd")
    wordless = tagged.where("n = 0").select("doc_id", F.col("class").alias("own"))
    chosen = least.select(F.col("least").alias("doc_id"), F.col("least_class").alias("own"))
    plain = chosen.unionByName(wordless).select(F.col("doc_id").alias("_id")).where("_id is not null").join(odd, "_id", "left_anti")
    own_id = docs["doc_id"].cast("long")
    known = docs.join(plain, own_id == plain["_id"], "left_semi")
    if not odd.take(1):
        return known
    text = F.coalesce(F.col("text").cast("string"), F.lit("")).cast("binary")
    rest = docs.join(odd, own_id.eqNullSafe(F.col("_id")), "left_semi").withColumn("_own", _class_of_text(width)(text))
    empty = F.col("_own") == class_of(np.empty(0, "u8"))
    one = rest.where(~empty).join(chosen, F.col("_own").eqNullSafe(chosen["own"]) & rest["doc_id"].cast("long").eqNullSafe(chosen["doc_id"]), "left_semi").dropDuplicates(["doc_id", "_own"])
    return known.unionByName(one.unionByName(rest.where(empty)).select(*docs.columns))
