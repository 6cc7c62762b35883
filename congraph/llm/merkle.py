"""Merkle fingerprints of documents: sections, paragraphs, segments.

Paragraphs are lines; a section is a run of paragraphs that ends where a paragraph's hash says so (one in four
on average) or at a blank line. Segments, the leaves, are runs of words that end where a word's own bytes say so
(four words on average), so that an insertion shifts no later segment, paragraph or section. Every byte is in a leaf, so
equal roots mean equal texts, and comparing trees from the top finds the branches that differ.

A fingerprint is `root.tree`: 32 hex digits of the root, then, in base 64, short hashes of the sections, of their
paragraphs and of the leaves below. Likeness descends two trees: sections that both have count with all their leaves, of
the others the paragraphs that both have do, and only what then differs is compared leaf by leaf, as multisets.

Cases: null text = empty text, a tree without leaves; two empty trees are alike (1.0), an empty and another
are not (0.0); repeated doc_ids are ordered by text, each with the next row as its next document; a table of one row has
itself as next; a text whose words all look alike may have long segments; an empty table gives no rows; further columns are
left alone.
"""

from __future__ import annotations

import base64
import hashlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from congraph.llm.common import bucket_bounds, bucket_of, doc_text, partitions_for

#: A segment ends after a word, a section after a paragraph, whose hash is 0 in this modulus.
SEGMENT_EVERY, SECTION_EVERY = 4, 4
_NODE, _SHORT = 16, 4

Tree = list[list[list[bytes]]]


def segments(data: bytes) -> list[bytes]:
    """The text in pieces that join to it again: cut at line ends, and after words by their last two bytes and length."""
    points = np.frombuffer(data, "u1")
    stops = np.flatnonzero((points == 0x20) | (points == 0x0A))
    if not len(stops):
        return [data] if data else []
    size = np.diff(stops, prepend=-1)
    last, before = (points[np.maximum(stops - k, 0)].astype("u4") for k in (1, 2))
    hashed = (last * 0x9E3779B1 + before * 0x85EBCA77 + size.astype("u4") * 0xC2B2AE3D).astype("u4") >> np.uint32(16)
    # A word of one or two bytes would look back into another.
    hashed = np.where(size > 2, hashed, np.where(size > 1, last * np.uint32(7) + np.uint32(1), np.uint32(1)))
    cut = [0, *(stops[(hashed % SEGMENT_EVERY == 0) | (points[stops] == 0x0A)] + 1).tolist()]
    if cut[-1] < len(data):
        cut.append(len(data))
    return [data[a:b] for a, b in zip(cut, cut[1:])]


def merkle_tree(text: str) -> Tree:
    """Leaf digests by paragraph by section."""
    sections: Tree = []
    section: list[list[bytes]] = []
    leaves: list[bytes] = []
    blake = hashlib.blake2b
    for piece in segments(text.encode("utf-8", "surrogatepass")):
        leaves.append(blake(piece, digest_size=_NODE).digest())
        if piece[-1] == 0x0A:
            section.append(leaves)
            if leaves[-1][0] % SECTION_EVERY == 0 or piece == b"\n" and len(leaves) == 1:
                sections.append(section)
                section = []
            leaves = []
    if leaves:
        section.append(leaves)
    if section:
        sections.append(section)
    return sections


def _join(tag: bytes, digests: list[bytes]) -> bytes:
    return hashlib.blake2b(tag + b"".join(digests), digest_size=_NODE).digest()


def node_digests(tree: Tree) -> tuple[bytes, list[bytes], list[list[bytes]]]:
    """Root, sections, paragraphs of each section."""
    paragraphs = [[_join(b"p", leaves) for leaves in section] for section in tree]
    sections = [_join(b"s", p) for p in paragraphs]
    return _join(b"r", sections), sections, paragraphs


class Mark:
    """A fingerprint's tree: short hashes of sections, paragraphs and leaves, with the paragraphs of each section and the
    leaves of each paragraph as ranges."""

    __slots__ = ("root", "sections", "paragraphs", "leaves", "_counted")

    def __init__(self, root: str, sections: list[tuple[bytes, int, int]], paragraphs: list[tuple[bytes, int, int]], leaves: np.ndarray):
        self.root, self.sections, self.paragraphs, self.leaves = root, sections, paragraphs, leaves
        self._counted = None

    @staticmethod
    def of(tree: Tree) -> Mark:
        root, sections, paragraphs = node_digests(tree)
        out, rows, data, n = [], [], [], 0
        for digest, section, own in zip(sections, tree, paragraphs):
            out.append((digest[:_SHORT], len(rows), len(rows) + len(section)))
            for d, leaves in zip(own, section):
                rows.append((d[:_SHORT], n, n + len(leaves)))
                n += len(leaves)
                data.extend(x[:_SHORT] for x in leaves)
        return Mark(root.hex(), out, rows, np.frombuffer(b"".join(data), "<u4"))

    def text(self) -> str:
        """`root.tree`, from which `parse` makes the mark again."""
        head = [len(self.sections), *(b - a for _, a, b in self.sections), *(b - a for _, a, b in self.paragraphs)]
        nodes = b"".join(d for d, _, _ in (*self.sections, *self.paragraphs))
        return f"{self.root}.{base64.b64encode(np.array(head, '<u4').tobytes() + nodes + self.leaves.tobytes()).decode()}"

    @staticmethod
    def parse(print_: str) -> Mark:
        root, _, tree = print_.partition(".")
        data = base64.b64decode(tree)
        number = lambda at, n: np.frombuffer(data, "<u4", n, 4 * at).tolist()
        k = number(0, 1)[0]
        wide = number(1, k)
        long = number(1 + k, sum(wide))
        at = 4 * (1 + k + len(long))

        def ranges(sizes: list[int], at: int) -> list[tuple[bytes, int, int]]:
            ends = np.cumsum(sizes, dtype="i8").tolist()
            return [(data[at + _SHORT * i : at + _SHORT * (i + 1)], e - n, e) for i, (n, e) in enumerate(zip(sizes, ends))]

        sections, paragraphs = ranges(wide, at), ranges(long, at + _SHORT * k)
        return Mark(root, sections, paragraphs, np.frombuffer(data, "<u4", offset=at + _SHORT * (k + len(long))))

    def counted(self, rows: list[tuple[bytes, int, int]]) -> tuple[np.ndarray, np.ndarray]:
        """Distinct leaves of some paragraphs and how often each occurs."""
        if len(rows) < len(self.paragraphs):
            return np.unique(np.concatenate([self.leaves[a:b] for _, a, b in rows] or [self.leaves[:0]]), return_counts=True)
        if self._counted is None:
            self._counted = np.unique(self.leaves, return_counts=True)
        return self._counted


def fingerprint(tree: Tree) -> str:
    return Mark.of(tree).text()


def _without(own: list[tuple[bytes, int, int]], other: list[tuple[bytes, int, int]]) -> list[tuple[bytes, int, int]]:
    """Nodes of `own` that `other` lacks, each as often as it lacks it."""
    held = Counter(d for d, _, _ in other)
    if not any(d in held for d, _, _ in own):
        return own
    out = []
    for node in own:
        if held[node[0]] > 0:
            held[node[0]] -= 1
        else:
            out.append(node)
    return out


def alike(x: Mark, y: Mark) -> float:
    """0 to 1: leaves in branches and leaves that both trees have, of all leaves of both."""
    if x.root == y.root:
        return 1.0
    total = len(x.leaves) + len(y.leaves)
    parts = []
    for own, other in ((x, y), (y, x)):
        open_ = _without(own.sections, other.sections)
        parts.append(own.paragraphs if open_ is own.sections else [p for _, a, b in open_ for p in own.paragraphs[a:b]])
    parts = [_without(parts[0], parts[1]), _without(parts[1], parts[0])]
    differing = sum(b - a for _, a, b in (*parts[0], *parts[1]))
    (u, n), (v, m) = (mark.counted(rows) for mark, rows in zip((x, y), parts))
    _, i, j = np.intersect1d(u, v, assume_unique=True, return_indices=True)
    return (total - differing + 2 * int(np.minimum(n[i], m[j]).sum())) / total


def likeness(a: str, b: str) -> float:
    """Likeness of two fingerprints, from the fingerprints alone."""
    return 1.0 if a == b else alike(Mark.parse(a), Mark.parse(b))


def edits(a: Tree, b: Tree) -> list[tuple[int, int]]:
    """(section, paragraph) of a whose branch b lacks: equal nodes are skipped whole."""
    root_a, sections_a, paragraphs_a = node_digests(a)
    root_b, sections_b, paragraphs_b = node_digests(b)
    if root_a == root_b:
        return []
    whole, parts = Counter(sections_b), Counter(p for s in paragraphs_b for p in s)
    out = []
    for i, s in enumerate(sections_a):
        if whole[s] > 0:
            whole[s] -= 1
            continue
        for j, p in enumerate(paragraphs_a[i]):
            if parts[p] > 0:
                parts[p] -= 1
            else:
                out.append((i, j))
    return out


_OUT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double, root string"


def _prints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows in order of bucket and id, each bucket closed by the first row of what follows it."""
    held, rows = None, []

    def row(now, after):
        (doc, text, mark, shown), (_, next_text, next_mark, _) = now, after
        half = len(text) // 2
        edited = text[: len(text) - half] + next_text[:half]
        edited_mark = mark if edited == text else Mark.of(merkle_tree(edited))
        edited_shown = shown if edited_mark is mark else edited_mark.text()
        return doc, len(text), hashlib.sha256(edited.encode()).hexdigest(), shown, edited_shown, alike(mark, edited_mark), alike(mark, next_mark), mark.root

    def batch():
        types = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64(), pa.string())
        return pa.record_batch([pa.array(c, t) for c, t in zip(zip(*rows), types)], names=[x.split()[0] for x in _OUT.split(", ")])

    for got in batches:
        for doc, text, guest in zip(*(got.column(c).to_pylist() for c in ("doc_id", "text", "guest"))):
            text = text.decode()
            mark = Mark.of(merkle_tree(text))
            now = (doc, text, mark, mark.text())
            if held is not None:
                rows.append(row(held, now))
            held = None if guest else now
            if len(rows) >= 500:
                yield batch()
                rows = []
    if rows:
        yield batch()


def fingerprints(docs: DataFrame) -> DataFrame:
    """One row for each row of docs: its fingerprint, that of its edited text, and their likeness.

    One shuffle deals the texts by ranges of ids; the first row of each range also goes, as a guest, to the
    range before it, and the first of all to the last.
    """
    spark = docs.sparkSession
    n = partitions_for(spark)
    rows = doc_text(docs)
    bounds = bucket_bounds(rows.select("doc_id"), "doc_id", n)
    dealt = rows.withColumn("bucket", bucket_of(F.col("doc_id"), bounds))
    # One row for each range.
    firsts = {r.bucket: r.first for r in dealt.select("doc_id", "bucket").groupBy("bucket").agg(F.min("doc_id").alias("first")).collect()}
    if not firsts:
        return spark.createDataFrame([], _OUT)
    order = sorted(firsts)
    before = {firsts[b]: order[k - 1] for k, b in enumerate(order)}
    heads = [before[x] for x in sorted(before)]
    guests = _first_rows(rows, sorted(before), heads)
    both = dealt.select("bucket", F.lit(False).alias("guest"), "doc_id", "text").unionByName(guests)
    return both.repartitionById(n, F.col("bucket")).sortWithinPartitions("bucket", "guest", "doc_id", "text").mapInArrow(_prints, _OUT)


def _first_rows(rows: DataFrame, ids: list[int], heads: list[int]) -> DataFrame:
    """The least row of each given id, for the bucket in heads beside it; as many ids as ranges are broadcast."""
    of = rows.sparkSession.createDataFrame(list(zip(ids, heads)), "doc_id long, bucket int")
    found = rows.join(F.broadcast(of), "doc_id").groupBy("doc_id", "bucket").agg(F.min("text").alias("text"))
    return found.select("bucket", F.lit(True).alias("guest"), "doc_id", "text")
