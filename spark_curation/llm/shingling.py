"""Words and hashed word shingles that the decontamination and passage operators share."""

from __future__ import annotations

import re

import numpy as np
from xxhash import xxh3_64_intdigest

_WORD = re.compile(rb"[0-9a-z\x80-\xff]+")
_STEP = np.uint64(0x9E3779B97F4A7C15)


def words(text: str | None) -> list[bytes]:
    """Runs of digits, letters a-z (A-Z in lower case) and other scripts."""
    return _WORD.findall((text or "").encode("utf-8", "surrogatepass").lower())


def word_hashes(ws: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxh3_64_intdigest, ws), np.uint64, len(ws))


def shingle_hashes(h: np.ndarray, width: int) -> np.ndarray:
    """Hashes of all runs of ``width`` hashed words, repeats included."""
    n = len(h) - width + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for j in range(width):
        out = out * _STEP + h[j : j + n]
        out ^= out >> np.uint64(29)
    return out * _STEP


def shingles(ws: list[bytes], width: int) -> list[bytes]:
    return [b" ".join(ws[i : i + width]) for i in range(len(ws) - width + 1)]
