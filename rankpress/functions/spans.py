"""Bytes of batches of texts: words, and hashes of any byte spans."""

from __future__ import annotations

import ctypes

import numpy as np
import pyarrow as pa

#: Fixed value: the white space that separates words, as in [^\x20\x09-\x0D]+.
#: bytes.split() without arguments uses the same six bytes, and bytes.lower() maps A-Z only.
WORD_RE = "[^\\x20\\x09-\\x0D]+"


def as_bytes(texts, pad: bytes = b"") -> tuple[np.ndarray, np.ndarray]:
    """(data, starts): UTF-8 bytes of all texts one after the other, each followed by pad; null counts as empty."""
    parts = [(t or "").encode("utf-8", "surrogatepass") + pad for t in texts]
    starts = np.zeros(len(parts) + 1, np.int64)
    np.cumsum([len(p) for p in parts], out=starts[1:])
    return np.frombuffer(b"".join(parts), np.uint8), starts


def chunks(texts: list, limit: int = 1 << 20):
    """Ranges [i, j) of texts of about `limit` characters in all; a longer text stands alone."""
    i, size = 0, 0
    for j, t in enumerate(texts):
        n = len(t or "")
        if size and size + n > limit:
            yield i, j
            i, size = j, 0
        size += n
    if i < len(texts):
        yield i, len(texts)


_trim = getattr(ctypes.CDLL(None), "malloc_trim", None)


def spared(batches):
    """The batches one by one; before each, freed memory goes back to the machine. Allocators keep it otherwise, and a worker that serves
    many stages would hold on to the peak of each."""
    for b in batches:
        pa.default_memory_pool().release_unused()
        if _trim:
            _trim(0)
        yield b


_BASE = 0x9E3779B97F4A7C15
_INV = pow(_BASE, -1, 1 << 64)


class SpanHasher:
    """64-bit polynomial hashes of any byte spans of one buffer, each in constant time.

    Prefix sums of byte * base**position wrap modulo 2**64; multiplying a difference by the inverse power moves
    a span to the origin. A finaliser mixes in the length.
    """

    _kept = np.ones((2, 1), np.uint64)  # powers of the base and of its inverse, for buffers up to KEEP bytes
    KEEP = (1 << 21) - 1

    def __init__(self, data: np.ndarray):
        n = len(data)
        powers = self._kept
        if powers.shape[1] <= n:
            powers = np.ones((2, n + 1 if n > self.KEEP else min(self.KEEP, 2 * n) + 1), np.uint64)
            powers[0, 1:], powers[1, 1:] = _BASE, _INV
            np.cumprod(powers, axis=1, out=powers)
            if n <= self.KEEP:  # a very long text leaves no table behind
                SpanHasher._kept = powers
        self.inv = powers[1, : n + 1]
        self.s = np.zeros(n + 1, np.uint64)
        x = data.astype(np.uint64)
        x += np.uint64(1)
        x *= powers[0, :n]
        np.cumsum(x, out=self.s[1:])

    def __call__(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        h = (self.s[b] - self.s[a]) * self.inv[a]
        return mix(h + (b - a).astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F))


def mix(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h = h ^ (h >> np.uint64(27))
    h = h * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def lower_ascii(data: np.ndarray) -> np.ndarray:
    return _LOWER[data]


def word_spans(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the words of a buffer."""
    gap = np.ones(len(data) + 2, bool)
    gap[1:-1] = _SPACE[data]
    edge = np.flatnonzero(gap[1:] != gap[:-1])
    return edge[0::2], edge[1::2]
