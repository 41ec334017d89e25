"""Word sequences and shingle sets of whole texts as arrays of 64-bit hashes.

Words are the runs of bytes other than space and 0x09-0x0D, after A-Z are lower-cased.
Equal hashes stand for equal words or shingles: within a pair of documents a false match
has a chance of about (size * size) / 2**64.
"""

from __future__ import annotations

import numpy as np
import xxhash

_U = np.uint64
#: Odd multipliers of the words of a shingle (fixed values; any odd numbers would do).
_MIX = [_U(0x9E3779B97F4A7C15), _U(0xC2B2AE3D27D4EB4F), _U(0x165667B19E3779F9), _U(0xD6E8FEB86659FD93), _U(0xA0761D6478BD642F)]


def word_hashes(text: str | None) -> np.ndarray:
    """One hash per word, in order; hashing a word costs less than remembering it."""
    words = text.encode().lower().split() if text else []
    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), _U, len(words))


def finish(h: np.ndarray) -> np.ndarray:
    """Spreads the bits of a linear combination."""
    h = (h ^ (h >> _U(33))) * _U(0xFF51AFD7ED558CCD)
    h = (h ^ (h >> _U(33))) * _U(0xC4CEB9FE1A85EC53)
    return h ^ (h >> _U(33))


def runs(w: np.ndarray, k: int) -> np.ndarray:
    """Hashes of all sequences of ``k`` words; there must be as many."""
    n = len(w) - k + 1
    if k <= len(_MIX):
        h = w[:n] * _MIX[0]
        for i in range(1, k):
            h = h + w[i : i + n] * _MIX[i]
    else:
        h = np.zeros(n, _U)
        for i in range(k):
            h = h * _MIX[0] + w[i : i + n]
    return finish(h)


def shingle_set(text: str | None, k: int = 5) -> np.ndarray:
    """Sorted distinct shingles; the whole sequence as one if it is shorter; empty without words."""
    w = word_hashes(text)
    if not len(w):
        return w
    if len(w) < k:
        return runs(w, len(w)) + _U(len(w))
    s = np.sort(runs(w, k))
    return s[np.r_[True, s[1:] != s[:-1]]]


def digest(s: np.ndarray) -> int:
    """A set's name: a signed 64-bit integer."""
    return int(xxhash.xxh3_64_intdigest(s.tobytes())) - (1 << 63)
