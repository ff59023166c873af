"""Hashed character n-grams of many texts at once, in numpy."""

from __future__ import annotations

from functools import lru_cache

import numpy as np

_MIX = np.uint64(0x9E3779B97F4A7C15)
_STEP = np.uint64(0xC2B2AE3D27D4EB4F)


@lru_cache(maxsize=1)
def _letters() -> np.ndarray:
    """Which of all code points are letters."""
    return np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000)


class Grams:
    """n-grams of lower-cased texts in which each run of other characters than letters is one blank.

    Every text stands after ``longest`` blanks, so no n-gram holds letters of two texts and what a
    text gives doesn't depend on its neighbours.
    """

    def __init__(self, texts: list[str | None], longest: int):
        lower = [(t or "").lower() for t in texts]
        lens = np.array([len(t) for t in lower], np.int64)
        pad = " " * longest
        codes = np.frombuffer((pad + pad.join(lower) + pad).encode("utf-32-le", "surrogatepass"), "<u4") if texts else np.empty(0, "<u4")
        letter = _letters()[codes]
        owner = np.repeat(np.arange(len(lens)), lens + longest)
        self.has_letter = np.zeros(len(lens), bool)
        body = letter[: len(owner)]
        self.has_letter[owner[body]] = True
        # one blank of each run stays; the one before a text is its first
        stays = letter.copy()
        stays[:-1] |= letter[1:]
        stays[1:] |= letter[:-1] & ~letter[1:]
        double = ~letter & stays
        double[1:] &= double[:-1]
        stays &= ~double
        own = owner[stays[: len(owner)]]
        self.codes = np.where(letter, codes, 32)[stays].astype(np.uint64) * _MIX
        self.codes ^= self.codes >> np.uint64(29)
        self.owner = own
        self.starts = np.searchsorted(own, np.arange(len(lens) + 1))

    def buckets(self, n: int, bits: int) -> np.ndarray:
        """The bucket of the n-gram that begins at each position; those that reach past the end of a text have blanks there."""
        size = len(self.owner)
        h = np.full(size, n, np.uint64) * _STEP
        end = self.starts[1:][self.owner] if size else np.empty(0, np.int64)
        at = np.arange(size)
        blank = np.full(1, 32, np.uint64) * _MIX
        blank ^= blank >> np.uint64(29)
        for k in range(n):
            c = np.repeat(blank, size)
            c[: max(0, size - k)] = self.codes[k:size]
            if k:
                c[at + k >= end] = blank[0]
            h = (h ^ c) * _STEP
            h ^= h >> np.uint64(32)
        return (h * _MIX >> np.uint64(64 - bits)).astype(np.int64)
