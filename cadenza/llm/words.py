"""Words, their hashes and word shingles, in bytes and numpy."""

from __future__ import annotations

import numpy as np
import xxhash

#: Lower-cases A-Z and turns each byte that belongs to no word into a blank. The bytes of code points from U+0080 belong to words.
_WORD_BYTES = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))

SHINGLE_WORDS = 5
#: Hashes of words remembered by a worker.
REMEMBERED = 100_000

_U = np.uint64
_STEP = _U(0x9E3779B97F4A7C15)
_MIX_A, _MIX_B = _U(0xBF58476D1CE4E5B9), _U(0x94D049BB133111EB)


def word_list(data: bytes | None) -> list[bytes]:
    """Words of a UTF-8 text, A-Z lower-cased; null has none."""
    return data.translate(_WORD_BYTES).split() if data else []


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit integers."""
    x = (x ^ (x >> _U(30))) * _MIX_A
    x = (x ^ (x >> _U(27))) * _MIX_B
    return x ^ (x >> _U(31))


class _Hashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) > REMEMBERED:
            self.clear()
        h = self[word] = xxhash.xxh64_intdigest(word)
        return h


_hashes = _Hashes()
_WEIGHTS = mix(np.arange(1, 65, dtype=np.uint64) * _STEP) | _U(1)


def shingle_units(words: list[bytes], size: int = SHINGLE_WORDS) -> np.ndarray:
    """One sorted 64-bit key for each occurrence of a shingle of `size` words (fewer words: one shingle of them all).

    The i-th occurrence of a shingle has a key of its own, so sets of keys compare as multisets of shingles.
    """
    n = len(words)
    if not n:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(_hashes.__getitem__, words), np.uint64, n)
    size = min(size, n)
    m = n - size + 1
    s = np.full(m, size, np.uint64)
    for j in range(size):
        s += h[j : j + m] * _WEIGHTS[j]
    s = mix(s)
    s.sort()
    first = np.ones(m, bool)
    np.not_equal(s[1:], s[:-1], out=first[1:])
    if first.all():
        return s
    at = np.arange(m)
    nth = at - np.maximum.accumulate(np.where(first, at, 0))
    keys = np.where(first, s, mix(s + nth.astype(np.uint64) * _STEP))
    keys.sort()
    return keys


def weighted_jaccard(a: np.ndarray, b: np.ndarray) -> float:
    """Of two arrays of shingle_units(): sum of the smaller counts by sum of the larger; 0 if both are empty."""
    if not len(a) or not len(b):
        return 0.0
    both = np.concatenate([a, b])
    both.sort()
    common = int(np.count_nonzero(both[1:] == both[:-1]))
    return common / (len(a) + len(b) - common)
