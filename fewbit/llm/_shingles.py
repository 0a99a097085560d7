"""Word shingles of whole texts as 64-bit hashes, computed with numpy over many documents at once."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U = np.uint64
_BASE = 0x9E3779B97F4A7C15
_CHUNK = 1 << 18


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every input bit (the public splitmix64 finaliser)."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, U)
    out[0] = 1
    return np.multiply.accumulate(out)


class WordHasher:
    """Hashes of the words of texts: A-Z lower-cased, parted at the ASCII space characters."""

    def __init__(self):
        codes = np.arange(256, dtype=U)
        codes[65:91] += U(32)
        self.value = mix(codes + U(0x1234567))
        self.space = np.zeros(256, bool)
        self.space[[32, *range(9, 14)]] = True
        self.up = self.down = _powers(1, 1)

    def _grow(self, n: int) -> None:
        if len(self.up) < n:
            n = max(n, 2 * len(self.up))
            self.up, self.down = _powers(_BASE, n), _powers(pow(_BASE, -1, 1 << 64), n)

    def words(self, data: bytes) -> tuple[np.ndarray, np.ndarray]:
        """(hash of each word, byte where it begins) of one stretch of bytes."""
        raw = np.frombuffer(data, np.uint8)
        n = len(raw)
        self._grow(n + 1)
        gap = np.ones(n + 2, bool)
        gap[1:-1] = self.space[raw]
        begin = np.flatnonzero(gap[:-2] & ~gap[1:-1])
        end = np.flatnonzero(~gap[1:-1] & gap[2:]) + 1
        total = np.zeros(n + 1, U)
        np.cumsum(self.value[raw] * self.up[:n], out=total[1:])
        return mix((total[end] - total[begin]) * self.down[begin] + (end - begin).astype(U)), begin


def text_stretches(column: pa.Array, most: int = 2 << 20) -> Iterator[tuple[int, list[bytes]]]:
    """(first row, texts as bytes) of successive rows of a text column, `most` bytes together unless one text is longer."""
    column = column.cast(pa.large_binary())
    sizes = pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False)
    lo = 0
    while lo < len(column):
        hi, held = lo + 1, int(sizes[lo])
        while hi < len(column) and held + sizes[hi] <= most:
            held += int(sizes[hi])
            hi += 1
        yield lo, [t if t is not None else b"" for t in column.slice(lo, hi - lo).to_pylist()]
        lo = hi


def word_hashes(texts: Sequence[bytes], hasher: WordHasher) -> Iterator[np.ndarray]:
    """The word hashes of each text, in order; texts are joined so that numpy sees large arrays."""
    lo = 0
    while lo < len(texts):
        hi, size = lo, 0
        while hi < len(texts) and (hi == lo or size + len(texts[hi]) < _CHUNK):
            size += len(texts[hi]) + 1
            hi += 1
        starts = np.cumsum([0, *(len(t) + 1 for t in texts[lo:hi])])
        hashes, at = hasher.words(b" ".join(texts[lo:hi]))
        cut = np.searchsorted(at, starts)
        for i in range(hi - lo):
            yield hashes[cut[i] : cut[i + 1]]
        lo = hi


def shingle_set(words: np.ndarray, size: int) -> np.ndarray:
    """Sorted distinct shingle hashes; a text with fewer words than a shingle is one shingle, without words none."""
    n = len(words)
    if n == 0:
        return words
    if n < size:
        out = U(n)
        for w in words:
            out = mix(np.array([out], U) + w)[0]
        return np.array([out], U)
    out = words[: n - size + 1].copy()
    for k in range(1, size):
        out *= U(_BASE)
        out += words[k : n - size + 1 + k]
    return np.unique(mix(out))
