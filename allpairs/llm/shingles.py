"""Sets of hashed word shingles of many texts at once, in numpy.

Words are runs of other bytes than blanks and the five ASCII breaks; A-Z count as a-z.  A word's hash
comes from running sums of its bytes, a shingle's from its words' hashes.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np

_FOLD = bytes(c + 32 if 65 <= c <= 90 else 32 if 9 <= c <= 13 else c for c in range(256))
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)
_PLACES = np.array([0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3, 0x589965CC75374CC3, 0x1D8E4E27C47D124F], np.uint64)


@lru_cache(maxsize=1)
def _values() -> np.ndarray:
    """A 64-bit value for each byte."""
    return mixed(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x2545F4914F6CDD1D))


@lru_cache(maxsize=2)
def _powers(base: int, size: int) -> np.ndarray:
    out = np.full(size, base, np.uint64)
    out[0] = 1
    return np.cumprod(out)


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def words(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all words of all texts, and where each text's begin."""
    data = np.frombuffer((b" ".join([*texts, b""]) if texts else b"").translate(_FOLD), np.uint8)
    size = 1 << max(20, int(len(data) + 1).bit_length())
    visible = np.concatenate([[False], data != 32, [False]])
    edges = np.flatnonzero(visible[1:] != visible[:-1])
    first, last = edges[::2], edges[1::2]
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_values()[data] * _powers(_BASE, size)[: len(data)])])
    h = (sums[last] - sums[first]) * _powers(_INVERSE, size)[first]
    h = mixed(h + (last - first).astype(np.uint64) * _PLACES[0])
    begins = np.cumsum([0, *(len(t) + 1 for t in texts)])
    return h, np.searchsorted(first, begins)


def shingle_sets(texts: list[bytes], k: int) -> list[np.ndarray]:
    """For each text its distinct shingles of ``k`` words in ascending order; all its words as one if they are fewer; none without words."""
    if k > len(_PLACES):
        raise ValueError(f"shingles have at most {len(_PLACES)} words")
    h, at = words(texts)
    whole = np.zeros(max(0, len(h) - k + 1), np.uint64)
    for j in range(k):
        whole += h[j : j + len(whole)] * _PLACES[j]
    whole = mixed(whole)
    out = []
    for s, e in zip(at[:-1], at[1:], strict=True):
        if e - s >= k:
            x = np.sort(whole[s : e - k + 1])
            out.append(x[np.concatenate([[True], x[1:] != x[:-1]])])
        elif e > s:
            out.append(mixed((h[s:e] * _PLACES[: e - s]).sum(keepdims=True) + np.uint64(e - s)))
        else:
            out.append(np.empty(0, np.uint64))
    return out
