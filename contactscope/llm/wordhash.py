"""Words of many texts as 64-bit hashes, and hashes of runs of words: numpy over whole batches.

A word is a run of digits, ASCII letters (either case alike) and bytes from 0x80 on."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from contactscope.llm.common import pieces

MIX = np.uint64(0x9E3779B97F4A7C15)
UNMIX = np.uint64(pow(int(MIX), -1, 1 << 64))
ONE = np.uint64(1)
#: Bytes that are hashed at once.
CHUNK = 1 << 18


def spread(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(29))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


def powers(n: int, factor: np.uint64) -> np.ndarray:
    """1, factor, factor^2 ... (n + 1 values, modulo 2^64)."""
    return np.concatenate(([ONE], np.cumprod(np.full(n, factor))))


class Hasher:
    """Words of texts as 64-bit hashes: a polynomial over a word's bytes, from prefix sums over a whole chunk of texts."""

    def __init__(self):
        values = spread((np.arange(256, dtype=np.uint64) + ONE) * MIX)
        self.letter = np.zeros(256, bool)
        for low, high in ((48, 58), (65, 91), (97, 123), (128, 256)):
            self.letter[low:high] = True
        values[65:91] = values[97:123]
        self.value = np.where(self.letter, values, np.uint64(0))
        self.up, self.down = powers(CHUNK, MIX), powers(CHUNK, UNMIX)

    def chunk(self, data: np.ndarray, edges: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of all words of the texts data[edges[i]:edges[i + 1]], and where each text's begin."""
        n = len(data)
        up, down = (self.up, self.down) if n < len(self.up) else (powers(n, MIX), powers(n, UNMIX))
        letter = np.zeros(n + 2, bool)
        letter[1:-1] = self.letter[data]
        inner = letter[1:-1]
        before, after = letter[:-2].copy(), letter[2:].copy()
        cut = edges[(edges > 0) & (edges < n)]
        before[cut] = False
        after[cut - 1] = False
        starts, ends = np.flatnonzero(inner & ~before), np.flatnonzero(inner & ~after) + 1
        sums = np.zeros(n + 1, np.uint64)
        np.cumsum(self.value[data] * up[:n], out=sums[1:])
        return spread((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(np.uint64)), np.searchsorted(starts, edges)

    def text(self, text: bytes) -> np.ndarray:
        found = [self.chunk(np.frombuffer(p, np.uint8), np.array([0, len(p)]))[0] for p in pieces(text, CHUNK - 1)]
        return np.concatenate(found)

    def texts(self, texts: list[bytes]) -> Iterator[np.ndarray]:
        """Word hashes of each text, short texts hashed together."""
        at = 0
        while at < len(texts):
            end, size = at, 0
            while end < len(texts) and size + len(texts[end]) < CHUNK:
                size += len(texts[end])
                end += 1
            if end == at:
                yield self.text(texts[at])
                at += 1
                continue
            edges = np.cumsum([0, *map(len, texts[at:end])])
            hashes, first = self.chunk(np.frombuffer(b"".join(texts[at:end]), np.uint8), edges)
            yield from np.split(hashes, first[1:-1])
            at = end


def shingles(words: np.ndarray, k: int) -> np.ndarray:
    n = len(words) - k + 1
    h = np.zeros(n, np.uint64)
    for j in range(k):
        h = h * MIX + words[j : j + n] + ONE
    return spread(h)
