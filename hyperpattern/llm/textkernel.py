"""Array kernels over the UTF-8 bytes of many texts at once: word bounds, word hashes, run hashes.

Texts are laid end to end, each followed by one zero byte, which is in no word. Hashes are polynomial, modulo 2**64, over
a random value for each byte, so the hash of any stretch is a difference of two prefix sums.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa

U = np.uint64
BASE = 0x9E3779B97F4A7C15
MIX1, MIX2 = U(0xBF58476D1CE4E5B9), U(0x94D049BB133111EB)


def mixed(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift and multiply)."""
    x = x ^ (x >> U(30))
    x *= MIX1
    x ^= x >> U(27)
    x *= MIX2
    x ^= x >> U(31)
    return x


@lru_cache(maxsize=2)
def byte_values(seed: int = 1) -> np.ndarray:
    return mixed(np.arange(1, 257, dtype=U) * U(BASE) + U(seed)) | U(1)


class Powers:
    """Powers of an odd base and of its inverse, grown as needed."""

    def __init__(self, base: int = BASE):
        self.base, self.inverse = base, pow(base, -1, 1 << 64)
        self.up = self.down = np.ones(1, U)

    def upto(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            n = max(n, 1 << 19)
            self.up, self.down = (np.concatenate([np.ones(1, U), np.cumprod(np.full(n - 1, b, U))]) for b in (self.base, self.inverse))
        return self.up[:n], self.down[:n]


POWERS = Powers()


def prefix_sums(b: np.ndarray, values: np.ndarray | None = None) -> np.ndarray:
    out = np.zeros(len(b) + 1, U)
    x = (byte_values() if values is None else values)[b]
    x *= POWERS.upto(len(b) + 1)[0][: len(b)]
    np.cumsum(x, out=out[1:])
    return out


def stretch_hashes(sums: np.ndarray, at: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hashes of bytes at .. end - 1."""
    return (sums[end] - sums[at]) * POWERS.upto(len(sums))[1][at]


def joined(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, starts): the texts (null: empty) end to end with a zero byte after each; starts has one entry more than texts."""
    raw = [(t.as_buffer() if t.is_valid else b"") for t in texts]
    lengths = np.fromiter((len(r) + 1 for r in raw), np.int64, len(raw))
    starts = np.concatenate([[0], np.cumsum(lengths)])
    return np.frombuffer(b"\0".join([*(memoryview(r) for r in raw), b""]), np.uint8), starts


@lru_cache(maxsize=1)
def word_bytes() -> tuple[np.ndarray, np.ndarray]:
    """(is in a word, lower-cased): digits, ASCII letters and all bytes beyond ASCII are in words; only A-Z change."""
    c = np.arange(256)
    inside = (c >= 128) | ((c >= 48) & (c <= 57)) | ((c >= 65) & (c <= 90)) | ((c >= 97) & (c <= 122))
    return inside, np.where((c >= 65) & (c <= 90), c + 32, c).astype(np.uint8)


def words(b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first bytes, end bytes, lower-cased bytes) of all words."""
    inside, lower = word_bytes()
    flag = np.zeros(len(b) + 2, np.int8)
    flag[1:-1] = inside[b]
    edge = np.flatnonzero(flag[1:] != flag[:-1])
    return edge[::2], edge[1::2], lower[b]


def parts(texts: pa.Array, most_bytes: int = 1 << 19):
    """Slices (first, count) of about most_bytes each; a longer text is a slice of its own."""
    sizes = np.array([len(t.as_buffer()) if t.is_valid else 0 for t in texts], np.int64)
    at = 0
    while at < len(sizes):
        n = max(1, int(np.searchsorted(np.cumsum(sizes[at:]), most_bytes, side="right")))
        yield at, n
        pa.default_memory_pool().release_unused()
        at += n
