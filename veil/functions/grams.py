"""Vectorised hashes of the distinct runs of words of whole texts.

A word's hash comes from prefix sums of a polynomial modulo 2**64, so a block
of texts is hashed by a few array operations, without a loop over words.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

#: Bytes of text hashed at once; a longer text is a block of its own.
BLOCK = 1 << 20
_P, _LENGTH = np.uint64(0x9E3779B97F4A7C15), np.uint64(0x9FB21C651E98DF25)
_INVERSE = np.uint64(pow(int(_P), -1, 1 << 64))
_STEP = np.uint64(0xC2B2AE3D27D4EB4F)
#: What ``\\s`` matches.
_WORD = np.ones(256, bool)
_WORD[[9, 10, 11, 12, 13, 32]] = False


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective finisher of 64-bit hashes."""
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xA0761D6478BD642F)
    return x ^ (x >> np.uint64(32))


def _powers(base: np.uint64, n: int) -> np.ndarray:
    return np.cumprod(np.concatenate([[np.uint64(1)], np.full(n, base)]), dtype=np.uint64)


_POWERS = [_powers(_P, 0), _powers(_INVERSE, 0)]


def _words(b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes and starts of the words of a block of bytes."""
    if len(_POWERS[0]) <= len(b):
        _POWERS[:] = [_powers(x, len(b)) for x in (_P, _INVERSE)]
    up, down = _POWERS
    word = np.zeros(len(b) + 2, bool)
    word[1:-1] = _WORD[b]
    edge = np.flatnonzero(word[1:] != word[:-1])
    starts, ends = edge[::2], edge[1::2]
    total = np.zeros(len(b) + 1, np.uint64)
    np.cumsum((b + np.uint64(1)) * up[: len(b)], dtype=np.uint64, out=total[1:])
    return mix((total[ends] - total[starts]) * down[starts] + (ends - starts).astype(np.uint64) * _LENGTH), starts


def _runs(b: np.ndarray, starts: np.ndarray, n: int) -> list[np.ndarray]:
    """Sorted distinct run hashes per text of a block; ``starts`` are the offsets of its texts, which no word crosses."""
    h, at = _words(b)
    first = np.searchsorted(at, starts)
    last = np.r_[first[1:], len(h)]
    run = h.copy()
    for i in range(1, n):
        run[: len(h) - i] = mix(run[: len(h) - i] * _STEP + h[i:]) if len(h) > i else run[:0]
    out = []
    for i, j in zip(first, last):
        if j - i >= n:
            out.append(np.unique(run[i : j - n + 1].view(np.int64)))
        else:  # one run of all words, told apart from runs of n words by its length
            x = np.full(min(j - i, 1), j - i, np.uint64)
            for w in h[i:j]:
                x = mix(x * _STEP + w)
            out.append(x.view(np.int64))
    return out


def run_hashes(texts: pa.Array, n: int) -> pa.Array:
    """Per text the sorted hashes of its distinct runs of ``n`` words; fewer words are one run, blank and null texts have none."""
    data = texts.cast(pa.large_binary())
    buffers = data.buffers()
    bounds = np.frombuffer(buffers[1], np.int64)[data.offset : data.offset + len(data) + 1]
    raw = np.frombuffer(buffers[2] or b"", np.uint8)
    null = data.is_null().to_numpy(zero_copy_only=False)
    sizes = np.where(null, 0, np.diff(bounds)).tolist()
    out: list[np.ndarray] = []
    i = 0
    while i < len(sizes):
        j, held = i + 1, sizes[i]
        while j < len(sizes) and held + sizes[j] <= BLOCK:
            held += sizes[j]
            j += 1
        block, starts, at = np.full(held + j - i, 32, np.uint8), np.zeros(j - i, np.int64), 0
        for k in range(i, j):  # a space after each text
            starts[k - i] = at
            block[at : at + sizes[k]] = raw[bounds[k] : bounds[k] + sizes[k]]
            at += sizes[k] + 1
        out += _runs(block, starts, n)
        i = j
    ends = np.cumsum([0, *map(len, out)])
    flat = np.concatenate(out) if out else np.zeros(0, np.int64)
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(flat, pa.int64()))
