"""Hashed words and word n-grams as numpy arrays."""

from __future__ import annotations

import re
import zlib

import numpy as np

WORDS = re.compile(r"\w+").findall
_seen: dict[str, int] = {}


def word_hashes(text: str) -> np.ndarray:
    """A 32-bit hash of each lower-case word, in order; a bounded memo holds the words seen."""
    words = WORDS(text.lower())
    if len(_seen) > 400_000:
        _seen.clear()
    try:
        return np.array([_seen[w] for w in words], dtype=np.uint64)
    except KeyError:
        for w in words:
            if w not in _seen:
                _seen[w] = zlib.crc32(w.encode("utf-8", "surrogatepass"))
        return np.array([_seen[w] for w in words], dtype=np.uint64)


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def pairs(h: np.ndarray, gap: int, kind: int) -> np.ndarray:
    """Hashes of the word pairs that lie ``gap`` apart."""
    return mix(h[:-gap] * np.uint64(0x9E3779B97F4A7C15) + h[gap:] * np.uint64(0xC2B2AE3D27D4EB4F) + np.uint64(kind)) if len(h) > gap else h[:0]
