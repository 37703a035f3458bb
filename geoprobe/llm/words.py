"""Vectorised hashing of white-space words over many documents at once."""

from __future__ import annotations

import numpy as np
import xxhash

#: Distinct words whose hashes a worker remembers.
REMEMBERED = 200_000


class _Hashes(dict):
    def __missing__(self, word: bytes) -> int:
        value = xxhash.xxh3_64_intdigest(word)
        if len(self) >= REMEMBERED:
            self.clear()
        self[word] = value
        return value


_HASHES = _Hashes()


def odd_constants(n: int, seed: int) -> np.ndarray:
    """n odd 64-bit multipliers, the same on every machine."""
    return np.array([xxhash.xxh3_64_intdigest(i.to_bytes(4, "little"), seed) | 1 for i in range(n)], np.uint64)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser (multiply and shift)."""
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


def split_words(texts: list[bytes]) -> list[list[bytes]]:
    """Words between ASCII white space (bytes 9 to 13 and 32)."""
    return [t.split() for t in texts]


def hashed(words: list[list[bytes]]) -> tuple[np.ndarray, np.ndarray]:
    """The hashes of all words, one document after the other, and the start of each document (with the end)."""
    ends = np.zeros(len(words) + 1, np.int64)
    np.cumsum([len(w) for w in words], out=ends[1:])
    get = _HASHES.__getitem__
    flat = np.fromiter((h for w in words for h in map(get, w)), np.uint64, int(ends[-1]))
    return flat, ends


def runs_of(flat: np.ndarray, size: int, constants: np.ndarray) -> np.ndarray:
    """Hash of every run of `size` consecutive words (also across documents, which callers mask)."""
    n = max(0, len(flat) - size + 1)
    out = np.zeros(n, np.uint64)
    for j in range(size):
        out += flat[j : j + n] * constants[j]
    return mix(out)


def sliding_minimum(x: np.ndarray, width: int) -> np.ndarray:
    """Minimum of every `width` consecutive values, by doubling."""
    size = 1
    while 2 * size <= width:
        x = np.minimum(x[:-size], x[size:])
        size *= 2
    return np.minimum(x[: len(x) - (width - size)], x[width - size :]) if width > size else x


class Powers:
    """Powers of an odd base modulo 2^64 and of its inverse, for the hash of any stretch of words from prefix sums."""

    def __init__(self, base: int):
        self.base, self.back = np.uint64(base), np.uint64(pow(base, -1, 1 << 64))
        self.up = self.down = np.ones(1, np.uint64)

    def grow(self, n: int) -> None:
        if len(self.up) < n:
            for name, base in (("up", self.base), ("down", self.back)):
                x = np.full(n, base, np.uint64)
                x[0] = 1
                setattr(self, name, np.cumprod(x, dtype=np.uint64))

    def stretches(self, flat: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
        """Hash of the words [first, last) for each pair of positions, equal for equal word sequences."""
        self.grow(len(flat) + 1)
        sums = np.zeros(len(flat) + 1, np.uint64)
        np.cumsum(flat * self.up[: len(flat)], out=sums[1:])
        return mix((sums[last] - sums[first]) * self.down[first] + (last - first).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
