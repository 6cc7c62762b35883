"""Token ids of the tokenizers library, with a cache of the pieces between spaces.

Both vocabularies of this module never join what a lone space or line feed separates, so a text is the
concatenation of its pieces, and most pieces repeat. A piece that the rules below can't place safely makes
the whole text go to the library in one call, so ids always equal those of the library on the whole text.
"""

from __future__ import annotations

import os
import sys
from array import array

import numpy as np

from congraph.llm.common import CACHES

#: Pieces that a worker keeps, in a vocabulary of words and in one of bytes; the cache starts anew beyond that.
CACHE_PIECES, CACHE_BYTE_PIECES = 600_000, 1_200_000
#: Letters below this code point lower-case to one letter and are stable under composition.
_PLAIN = "İ"
_PLAIN_END = frozenset(".,;:!?")


def _byte_map() -> dict[int, str]:
    """The printable stand-ins of byte-level vocabularies: fixed ranges stay, other bytes follow from U+0100."""
    keep = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in keep]
    return {b: chr(b) for b in keep} | {b: chr(256 + i) for i, b in enumerate(rest)}


_BYTES = _byte_map()


class PieceCache(dict):
    """Text piece to its ids as little-endian bytes; None: the piece touches white space, encode the text whole."""

    def __init__(self, path: str, words: bool):
        super().__init__()
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.model, self.words = self.tokenizer.model, words
        self.vocab_size = self.tokenizer.get_vocab_size()
        self.dtype = "<u2" if self.vocab_size <= 1 << 16 else "<u4"
        #: Array code of dtype, where the machine's own order is little-endian.
        self.code = {"<u2": "H", "<u4": "I"}[self.dtype] if sys.byteorder == "little" else None
        self.ends: dict[str, bytes] = {}

    def whole(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, self.dtype).tobytes()

    def _word(self, text: str) -> bytes:
        ids = [t.id for t in self.model.tokenize(text)]
        return array(self.code, ids).tobytes() if self.code else np.array(ids, self.dtype).tobytes()

    def _end(self, mark: str) -> bytes:
        if mark not in self.ends:
            self.ends[mark] = self._word(mark)
        return self.ends[mark]

    def _plain(self, piece: str, lead: str) -> bytes | None:
        """Ids of a word with at most one mark after it, straight from the model. A word that is there without the mark is
        not taken anew."""
        end = b""
        if piece[-1:] in _PLAIN_END:
            end, piece = self._end(piece[-1]), piece[:-1]
            if lead and end and (known := self.get(piece)) and piece.isalpha():
                return known + end
        if not piece.isalpha():
            return None
        if piece.isascii():
            # Printable ASCII stands for itself, a space for its stand-in.
            return self._word((_BYTES[0x20] if lead else "") + (piece.lower() if self.words else piece)) + end
        if max(piece) >= _PLAIN:
            return None
        return self._word((lead + (piece.lower() if self.words else piece)).encode().decode("latin-1").translate(_BYTES)) + end

    def __missing__(self, piece: str) -> bytes | None:
        if len(self) >= (CACHE_PIECES if self.words else CACHE_BYTE_PIECES):
            self.clear()
        if self.words:
            got = (self._plain(piece, "") if piece else b"") or (self.whole(piece) if piece else b"")
        elif piece[:1] == "\n":
            body = piece[1:]
            if not body or body[0].isspace() or body[-1].isspace():
                got = None
            else:
                rest = self._plain(body, "")
                got = self.whole(piece) if rest is None else self["\x01\n"] + rest
        elif piece[:1] == "\x01":
            got = self.whole(piece[1:])
        elif not piece or piece[0].isspace() or piece[-1].isspace() or "\x01" in piece:
            got = None
        else:
            got = self._plain(piece, " ") or self.whole(" " + piece)
        self[piece] = got
        return got

    def encode(self, text: str) -> bytes:
        """Ids of the whole text, as bytes of `dtype`."""
        if self.words:
            return b"".join(map(self.__getitem__, text.replace("\n", " ").split(" ")))
        pieces = text.replace("\n", " \n").split(" ")
        if pieces[0][:1] != "\n" and pieces[0]:
            if pieces[0][-1].isspace() or "\x01" in pieces[0]:
                return self.whole(text)
            pieces[0] = "\x01" + pieces[0]
        try:
            return b"".join(map(self.__getitem__, pieces))
        except TypeError:
            return self.whole(text)


_KEPT: dict[tuple[str, bool], PieceCache] = {}
CACHES.append(_KEPT)


def encoder(name: str, words: bool, path: str | None = None) -> PieceCache:
    """The worker's encoder for a public vocabulary file; path overrides where it lies."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path(name)
    return _KEPT.setdefault((path, words), PieceCache(path, words)) if (path, words) not in _KEPT else _KEPT[path, words]
