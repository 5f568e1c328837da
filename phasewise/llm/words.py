"""Word hashes in Python workers.

``bytes.split`` cuts at the six characters x09-x0D and x20 and ``bytes.lower``
changes A-Z only, so both rules hold whatever else the text contains.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash

U = np.uint64
_MASK = (1 << 64) - 1


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift and multiply), element by element."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
        return x ^ (x >> U(31))


def odd_constants(n: int, seed: int = 1) -> np.ndarray:
    return mix(np.arange(1, n + 1, dtype=U) * U((0x9E3779B97F4A7C15 * (2 * seed + 1)) & _MASK)) | U(1)


class WordHashes(dict):
    """64-bit hashes of words, remembered for up to ``most`` different words."""

    def __init__(self, most: int = 400_000):
        super().__init__()
        self.most = most

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.most:
            self.clear()
        h = self[word] = xxhash.xxh3_64_intdigest(word)
        return h

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), dtype=U, count=len(words))


def texts(column: pa.Array) -> list[bytes | None]:
    return column.cast(pa.binary()).to_pylist()


def shingle_set(hashes: np.ndarray, k: int) -> np.ndarray:
    """Sorted hashes of the distinct k-word shingles; a shorter text is one shingle."""
    n = len(hashes)
    if n == 0:
        return hashes
    with np.errstate(over="ignore"):
        odd = odd_constants(k)
        if n < k:
            whole = (hashes * odd[:n]).sum(dtype=U) + U(n)
            return mix(np.array([whole], dtype=U))
        total = hashes[: n - k + 1] * odd[0]
        for i in range(1, k):
            total = total + hashes[i : n - k + 1 + i] * odd[i]
    return np.unique(mix(total))
