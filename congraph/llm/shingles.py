"""64-bit hashes of a text's word shingles, by one vectorised pass over its bytes."""

from __future__ import annotations

import numpy as np

from congraph.llm.common import SPACE_BYTES

WIDTH = 5
#: A to Z in lower case, every byte of white space a space.
FOLD = bytes(0x20 if b in SPACE_BYTES else b + 32 if 0x41 <= b <= 0x5A else b for b in range(256))

_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_POWERS: dict[str, np.ndarray] = {"up": np.ones(1, "u8"), "down": np.ones(1, "u8")}
_MIX = (np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB))


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POWERS["up"]) < n:
        size = max(n, 2 * len(_POWERS["up"]), 1 << 16)
        inverse = np.uint64(pow(int(_BASE), -1, 1 << 64))
        for name, base in (("up", _BASE), ("down", inverse)):
            steps = np.full(size, base, "u8")
            steps[0] = 1
            _POWERS[name] = np.multiply.accumulate(steps)
    return _POWERS["up"][:n], _POWERS["down"][:n]


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * _MIX[0]
    x = (x ^ (x >> np.uint64(27))) * _MIX[1]
    return x ^ (x >> np.uint64(31))


def shingle_set(text: bytes, width: int = WIDTH) -> np.ndarray:
    """Sorted distinct hashes of the shingles; fewer words than width: one of all; no words: none."""
    words = text.translate(FOLD).split()
    if not words:
        return np.empty(0, "u8")
    # One space after each word: equal word sequences are then equal bytes.
    flat = np.frombuffer(b" ".join(words) + b" ", "u1")
    stops = np.flatnonzero(flat == 0x20) + 1
    starts = np.concatenate(([0], stops[:-1]))
    if len(words) > width:
        starts, stops = starts[: len(words) - width + 1], stops[width - 1 :]
    else:
        starts, stops = starts[:1], stops[-1:]
    up, down = _powers(len(flat) + 1)
    total = np.concatenate((np.zeros(1, "u8"), np.cumsum((flat.astype("u8") + np.uint64(1)) * up[:-1])))
    hashes = (total[stops] - total[starts]) * down[starts] + (stops - starts).astype("u8") * _MIX[1]
    return np.unique(mixed(hashes))
