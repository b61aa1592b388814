"""Words, shingles and their 64-bit hashes, for the operators that run on Arrow batches.

A word is a maximal run without the six ASCII white-space characters, with A-Z lower-cased: just what
``bytes.lower().split()`` gives.
"""

from __future__ import annotations

import numpy as np
import xxhash

_MIX = np.uint64(0xFF51AFD7ED558CCD)
_STEP = np.uint64(0x9E3779B97F4A7C15)
_S33, _S29 = np.uint64(33), np.uint64(29)


class WordHashes(dict):
    """Word to 64-bit hash, with a bound on how many words it keeps."""

    LIMIT = 100_000

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.LIMIT:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value


def split_words(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").lower().split() if text else []


def word_hashes(words: list[bytes], cache: WordHashes) -> np.ndarray:
    return np.fromiter(map(cache.__getitem__, words), dtype=np.uint64, count=len(words))


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _S33)) * _MIX
    return x ^ (x >> _S29)


def gram_hashes(hashes: np.ndarray, n: int) -> np.ndarray:
    """Hash of every run of ``n`` words, in order; of the whole sequence if it has fewer; empty for none."""
    if not len(hashes):
        return hashes
    n = min(n, len(hashes))
    out = hashes[: len(hashes) - n + 1].copy()
    for k in range(1, n):
        out = mix(out + _STEP) + hashes[k : len(hashes) - n + 1 + k]
    # the length takes part, so that a short whole sequence never equals a run of another length
    return mix(out ^ np.uint64(n * 0x1000193))


def shingle_set(text: str | None, n: int, cache: WordHashes) -> np.ndarray:
    """Sorted distinct shingle hashes of a text."""
    return np.unique(gram_hashes(word_hashes(split_words(text), cache), n))
