"""64-bit hashes of a text's words, in a Python worker."""

from __future__ import annotations

import numpy as np
import xxhash

from .caches import claim

#: Words whose hash one worker keeps; emptied beyond that.
CACHE_WORDS = 300_000


class _Known(dict):
    def __missing__(self, word: bytes) -> int:
        h = self[word] = xxhash.xxh3_64_intdigest(word)
        return h


_known = _Known()


def word_hashes(text: str | None, lower: bool = False) -> np.ndarray:
    """uint64 hash of each word, in order; A to Z lower-cased first if asked for. Null has no words."""
    if not text:
        return np.zeros(0, np.uint64)
    claim("hashes", _known.clear)
    if len(_known) > CACHE_WORDS:
        _known.clear()
    raw = text.encode("utf-8", "surrogatepass")
    parts = (raw.lower() if lower else raw).split()
    return np.fromiter(map(_known.__getitem__, parts), np.uint64, len(parts))


def mixed(h: np.ndarray) -> np.ndarray:
    """A bijection of 64 bits that spreads every bit."""
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))
