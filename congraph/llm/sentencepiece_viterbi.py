"""SentencePiece encoding and decoding by a Viterbi pass that words share.

A text is cut into marked words (the mark stands for a space). The distinct words of a batch are sorted, which
is the depth-first order of their trie, and the forward states of a word are kept up to what it has in common
with the next, so a shared prefix is scored once.

For a unigram model a state is the best score and the last piece of the prefix. A model of merges (BPE) has a
forward pass of the same form: the encoding of a prefix is that of a shorter prefix and one more piece, and a
piece may follow another exactly if merging the two alone leaves them as they are. One piece is feasible at
each position, so the best path is the library's encoding.

Cases: null text = empty text, no ids; a space run keeps each space as a mark; characters that the model lacks
become bytes (or the unknown id); a text that holds the mark itself decodes to a space there; repeated doc_ids
are rows of their own; an empty table gives no rows; further columns are left alone; words may be of any length.
"""

from __future__ import annotations

import re
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from congraph.llm.common import doc_text

MARK = "▁"
UNIGRAM, BPE = 1, 2
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
#: Words that a worker keeps.
CACHE_WORDS = 600_000
#: What a unigram model pays for an unknown character below its least score.
UNKNOWN_PENALTY = 10.0

_WORDS = re.compile(f"{MARK}*[^{MARK}\n]+|{MARK}+|\n")


def _fields(data: bytes) -> Iterator[tuple[int, object]]:
    """(field number, value) of one protocol buffer message."""
    at = 0

    def varint():
        nonlocal at
        value = shift = 0
        while True:
            b = data[at]
            at += 1
            value |= (b & 0x7F) << shift
            shift += 7
            if b < 0x80:
                return value

    while at < len(data):
        key = varint()
        kind = key & 7
        if kind == 0:
            yield key >> 3, varint()
        elif kind == 2:
            n = varint()
            yield key >> 3, data[at : at + n]
            at += n
        else:
            n = 8 if kind == 1 else 4
            yield key >> 3, data[at : at + n]
            at += n


class PieceModel:
    """Pieces, scores and types of a model file."""

    def __init__(self, path: str):
        with open(path, "rb") as file:
            data = file.read()
        self.pieces: list[tuple[str, float, int]] = []
        trainer: dict[int, object] = {}
        normalizer: dict[int, object] = {}
        for number, value in _fields(data):
            if number == 1:
                piece = dict(_fields(value))
                score = struct.unpack("<f", piece[2])[0] if 2 in piece else 0.0
                self.pieces.append((piece.get(1, b"").decode(), score, piece.get(3, NORMAL)))
            elif number == 2:
                trainer = dict(_fields(value))
            elif number == 3:
                normalizer = dict(_fields(value))
        self.kind = trainer.get(3, UNIGRAM)
        if self.kind not in (UNIGRAM, BPE):
            raise ValueError("only unigram and merge models are read")
        if normalizer.get(2) or normalizer.get(4, 1):
            raise ValueError("only models that leave characters and spaces as they are")
        self.dummy_prefix = bool(normalizer.get(3, 1))
        self.ids = {p: k for k, (p, _, t) in enumerate(self.pieces) if t == NORMAL}
        self.scores = {p: s for p, s, t in self.pieces if t == NORMAL}
        if any(t in (USER, UNUSED) for _, _, t in self.pieces) or any(MARK in p.lstrip(MARK) or "\n" in p for p in self.ids):
            raise ValueError("pieces that cross words or are matched first aren't supported")
        self.bytes = {int(p[3:5], 16): k for k, (p, _, t) in enumerate(self.pieces) if t == BYTE}
        self.unknown = next((k for k, (_, _, t) in enumerate(self.pieces) if t == UNKNOWN), 0)
        surface = {k: bytes([b]) for b, k in self.bytes.items()}
        self.surfaces = [surface.get(k, p.encode() if t == NORMAL else " ⁇ ".encode() if t == UNKNOWN else b"") for k, (p, _, t) in enumerate(self.pieces)]
        self.dtype = "<u2" if len(self.pieces) <= 1 << 16 else "<u4"
        #: Pieces by their letters from the last to the first; "" marks a whole piece.
        self.endings: dict = {}
        for p in self.ids:
            node = self.endings
            for c in reversed(p):
                node = node.setdefault(c, {})
            node[""] = p
        self.least = min(self.scores.values(), default=0.0)

    def ids_of(self, piece: str) -> list[int]:
        got = self.ids.get(piece)
        if got is not None:
            return [got]
        return [self.bytes[b] for b in piece.encode()] if self.bytes else [self.unknown]

    def merge(self, text: str) -> list[str]:
        """Pieces of a short text by merging neighbours, best score first, leftmost among equals."""
        parts, scores = list(text), self.scores
        while len(parts) > 1:
            best, at = None, -1
            for k in range(len(parts) - 1):
                s = scores.get(parts[k] + parts[k + 1])
                if s is not None and (best is None or s > best):
                    best, at = s, k
            if at < 0:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts


class SharedPrefixViterbi:
    def __init__(self, model: PieceModel):
        self.model = model
        self.fits: dict[tuple[str, str], bool] = {}

    def _may_follow(self, before: str, piece: str) -> bool:
        got = self.fits.get((before, piece))
        if got is None:
            if len(self.fits) > 1_000_000:
                self.fits.clear()
            got = self.fits[before, piece] = self.model.merge(before + piece) == ([before, piece] if before else [piece])
        return got

    def encode_words(self, words: list[str]) -> Iterator[tuple[str, list[str], int]]:
        """(word, pieces, letters that were scored anew) in the order of the words' trie."""
        bpe, endings, scores = self.model.kind == BPE, self.model.endings, self.model.scores
        unknown = self.model.least - UNKNOWN_PENALTY
        last: list[str] = [""]  # the piece that ends at each position
        best: list[float] = [0.0]
        before = ""
        for word in sorted(words):
            same, most = 0, min(len(before), len(word))
            while same < most and before[same] == word[same]:
                same += 1
            del last[same + 1 :], best[same + 1 :]
            for i in range(same, len(word)):
                node, j, chosen, top = endings, i, "", -1e30
                while j >= 0:
                    node = node.get(word[j])
                    if node is None:
                        break
                    piece = node.get("")
                    if piece is not None:
                        if bpe:
                            if self._may_follow(last[j], piece):
                                chosen, top = piece, best[j] + 1
                                break
                        elif best[j] + scores[piece] >= top:  # of equals the longest
                            chosen, top = piece, best[j] + scores[piece]
                    j -= 1
                if not chosen or not bpe and word[i] not in scores and best[i] + unknown > top:
                    chosen, top = word[i], best[i] + unknown
                last.append(chosen)
                best.append(top)
            pieces, at = [], len(word)
            while at:
                pieces.append(last[at])
                at -= len(last[at])
            yield word, pieces[::-1], len(word) - same
            before = word


class Encoder:
    def __init__(self, path: str):
        self.model = PieceModel(path)
        self.viterbi, self.kept = SharedPrefixViterbi(self.model), {}

    def words(self, text: str) -> list[str]:
        if not text:
            return []
        marked = (MARK if self.model.dummy_prefix else "") + text.replace(" ", MARK)
        return _WORDS.findall(marked)

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        cut = [self.words(t) for t in texts]
        kept = self.kept
        new = set().union(*cut).difference(kept) if cut else set()
        if len(kept) + len(new) > CACHE_WORDS:
            kept.clear()
            new = set().union(*cut)
        model = self.model
        for word, pieces, _ in self.viterbi.encode_words(list(new)):
            kept[word] = np.array([k for p in pieces for k in model.ids_of(p)], model.dtype).tobytes()
        return [np.frombuffer(b"".join(map(kept.__getitem__, x)), model.dtype) for x in cut]

    def decode(self, ids: np.ndarray) -> str:
        """The text behind ids; the mark that was put before it goes."""
        text = b"".join(map(self.model.surfaces.__getitem__, ids.tolist())).decode("utf-8", "replace").replace(MARK, " ")
        return text[1:] if self.model.dummy_prefix and text[:1] == " " else text


_KEPT: dict[str, Encoder] = {}


def encoder(path: str | None = None) -> Encoder:
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("piece_bpe_32k.model")
    if path not in _KEPT:
        _KEPT[path] = Encoder(path)
    return _KEPT[path]


_OUT = "doc_id long, n_tokens long, ids_crc32 long, decoded_crc32 long, round_trip boolean"


def _digest(path: str | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sp = encoder(path)
        for batch in batches:
            rows = []
            texts = [t.decode() for t in batch.column("text").to_pylist()]
            for doc, text, ids in zip(batch.column("doc_id").to_pylist(), texts, sp.encode(texts)):
                decoded = sp.decode(ids)
                rows.append((doc, len(ids), zlib.crc32(ids.astype("<u4").tobytes()), zlib.crc32(decoded.encode()), decoded == text))
            types = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.bool_())
            yield pa.record_batch([pa.array(c, t) for c, t in zip(zip(*rows), types)] if rows else [pa.array([], t) for t in types], names=[x.split()[0] for x in _OUT.split(", ")])

    return run


def _ids(path: str | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sp = encoder(path)
        for batch in batches:
            ids = [x.tolist() for x in sp.encode([t.decode() for t in batch.column("text").to_pylist()])]
            yield pa.record_batch([batch.column("doc_id"), pa.array(ids, pa.list_(pa.int32()))], names=["doc_id", "ids"])

    return run


def _texts(path: str | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sp = encoder(path)
        for batch in batches:
            texts = [sp.decode(np.array(x or [], "i8")) for x in batch.column("ids").to_pylist()]
            yield pa.record_batch([batch.column("doc_id"), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return run


def encode(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, ids."""
    return doc_text(docs).mapInArrow(_ids(path), "doc_id long, ids array<int>")


def decode(encoded: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, text of rows (doc_id, ids)."""
    return encoded.select("doc_id", "ids").mapInArrow(_texts(path), "doc_id long, text string")


def encode_digests(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, n_tokens, ids_crc32 (ids as little-endian unsigned 32-bit), decoded_crc32, round_trip, for each row of docs."""
    return doc_text(docs).mapInArrow(_digest(path), _OUT)
