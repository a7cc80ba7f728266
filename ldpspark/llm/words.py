"""Hashes of the words of texts, by running sums instead of a dictionary."""

from __future__ import annotations

import re
from functools import lru_cache

import numpy as np

SEGMENT, BLANK = (1 << 17) - (1 << 10), re.compile(rb"[\x20\x09-\x0D]")
M1 = np.uint64(0x9E3779B97F4A7C15)


@lru_cache(maxsize=2)
def _tables(size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Random number of each byte, powers of an odd number and of its inverse modulo 2^64, and which bytes are blank."""
    random = np.random.default_rng(20).integers(0, 1 << 63, 256, np.uint64) * np.uint64(2) + np.uint64(1)
    odd = int(M1)
    power = np.cumprod(np.full(size, odd, np.uint64)) * np.uint64(pow(odd, -1, 1 << 64))
    inverse = np.cumprod(np.full(size, pow(odd, -1, 1 << 64), np.uint64)) * M1
    blank = np.zeros(256, bool)
    blank[[32, *range(9, 14)]] = True
    return random, power, inverse, blank


def word_hashes(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hash and start of each word of a lower-cased text: differences of running sums of byte number * power.

    Long texts are taken in segments that end between words, so what is held at once doesn't grow with them.
    """
    hashes, starts, at = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)], 0
    while at < len(raw):
        end = at + SEGMENT
        if end < len(raw):
            found = BLANK.search(raw, end)
            end = found.start() if found else len(raw)
        a = np.frombuffer(raw, np.uint8, min(end, len(raw)) - at, at)
        random, power, inverse, blank = _tables(1 << max(17, len(a).bit_length()))
        inside = np.zeros(len(a) + 2, bool)
        inside[1:-1] = ~blank[a]
        first, last = np.flatnonzero(inside[1:-1] & ~inside[:-2]), np.flatnonzero(inside[1:-1] & ~inside[2:])
        total = np.zeros(len(a) + 1, np.uint64)
        np.cumsum(random[a] * power[: len(a)], out=total[1:])
        hashes.append((total[last + 1] - total[first]) * inverse[first])
        starts.append(first + at)
        at = end
    return np.concatenate(hashes), np.concatenate(starts)
