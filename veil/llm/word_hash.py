"""Vectorised hashes of the words of UTF-8 texts.

A word's hash comes from prefix sums of a polynomial modulo 2**64, so a block
of texts is hashed by a few array operations, without a loop over words.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

#: Bytes hashed at once; longer texts are taken in segments cut at gaps.
BLOCK = 1 << 20
_P = np.uint64(0x9E3779B97F4A7C15)
LOWER = np.arange(256, dtype=np.uint64)
LOWER[65:91] += np.uint64(32)
SPACES = np.zeros(256, bool)
SPACES[[9, 10, 11, 12, 13, 32]] = True
#: Gaps of license scanning: every ASCII byte that is no letter or digit.
SIGNS = np.array([i < 128 and not chr(i).isalnum() for i in range(256)])


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective finisher of 64-bit hashes."""
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xA0761D6478BD642F)
    return x ^ (x >> np.uint64(32))


class _Powers:
    """Powers of an odd number modulo 2**64 and of its inverse, grown on demand."""

    def __init__(self) -> None:
        self.up = self.down = np.ones(1, np.uint64)

    def get(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            inverse = np.uint64(pow(int(_P), -1, 1 << 64))
            self.up = np.cumprod(np.concatenate([[np.uint64(1)], np.full(n, _P)]), dtype=np.uint64)
            self.down = np.cumprod(np.concatenate([[np.uint64(1)], np.full(n, inverse)]), dtype=np.uint64)
        return self.up, self.down


_POWERS = _Powers()


def word_hashes(data: bytes, gap: np.ndarray = SPACES) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of the lower-cased (A-Z) words of a text, with their start and end offsets."""
    b = np.frombuffer(data, np.uint8)
    word = ~gap[b]
    edge = np.flatnonzero(np.diff(np.concatenate([[False], word, [False]]).astype(np.int8)))
    starts, ends = edge[::2], edge[1::2]
    up, down = _POWERS.get(len(b) + 1)
    total = np.concatenate([[np.uint64(0)], np.cumsum((LOWER[b] + np.uint64(1)) * up[: len(b)], dtype=np.uint64)])
    h = (total[ends] - total[starts]) * down[starts]
    return mix(h + (ends - starts).astype(np.uint64) * np.uint64(0x9FB21C651E98DF25)), starts, ends


def segments(data: bytes, gap: np.ndarray = SPACES, size: int = BLOCK) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Word hashes and offsets of a text of any length, in segments cut at gaps."""
    at = 0
    while at < len(data):
        end = min(len(data), at + size)
        while end < len(data) and not gap[data[end]]:
            end += 1
        h, starts, ends = word_hashes(data[at:end], gap)
        yield h, starts + at, ends + at
        at = end
