"""Word-shingle sets of whole texts as sorted 64-bit hashes, computed over batches with numpy.

Words are runs of bytes outside space and 9-13, with A-Z lower-cased. A set has the distinct shingles of `width` words; a
text with fewer words has its whole sequence as one; a text without words has none. Hashes of 64 bits stand for the
shingles: a wrong overlap needs two of a pair's shingles to collide, about one chance in 10**13 for documents of 1,000.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

WIDTH = 5
_RNG = np.random.default_rng(20240229)
_BYTE = _RNG.integers(1, 2**63, 256, dtype=np.uint64) | np.uint64(1)
_BASE = np.uint64(0x9E3779B97F4A7C15)
_BLANK = np.zeros(256, bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True
_BYTE[65:91] = _BYTE[97:123]
#: Bytes of text that are in arrays at once.
PIECE = 1 << 20


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of 64-bit values."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def distinct(x: np.ndarray) -> np.ndarray:
    """The sorted distinct values: faster than np.unique, which hashes first."""
    x = np.sort(x)
    return x[np.concatenate(([True], x[1:] != x[:-1]))] if len(x) else x


def _powers(n: int) -> np.ndarray:
    return np.cumprod(np.concatenate(([np.uint64(1)], np.full(max(0, n - 1), _BASE))), dtype=np.uint64)


_POWER = _powers(1 << 12)


def _hashes(flat: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash and start of each word of some bytes."""
    global _POWER
    word = ~_BLANK[flat]
    edge = np.diff(np.concatenate(([False], word, [False])).astype(np.int8))
    starts, ends = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    if not len(starts):
        return np.zeros(0, np.uint64), starts
    lengths = ends - starts
    if lengths.max() > len(_POWER):
        _POWER = _powers(1 << int(lengths.max()).bit_length())
    at = np.flatnonzero(word)
    values = _BYTE[flat[at]] * _POWER[at - np.repeat(starts, lengths)]
    first = np.concatenate(([0], np.cumsum(lengths)[:-1]))
    return mix(np.add.reduceat(values, first) + lengths.astype(np.uint64)), starts


def word_hashes(text: bytes) -> np.ndarray:
    """Word hashes of one text, piece by piece between words."""
    out, at = [], 0
    flat = np.frombuffer(text, np.uint8)
    while at < len(flat):
        end = min(len(flat), at + PIECE)
        while end < len(flat) and not _BLANK[flat[end]]:
            end += 1
        out.append(_hashes(flat[at:end])[0])
        at = end
    return np.concatenate(out) if out else np.zeros(0, np.uint64)


def shingle_hashes(words: np.ndarray, width: int = WIDTH) -> np.ndarray:
    """Hashes of each run of `width` words, or of the whole sequence if it is shorter."""
    n = len(words)
    if not n:
        return words
    k = min(n, width)
    total = np.full(n - k + 1, k, np.uint64)
    for j in range(k):
        total += words[j : n - k + 1 + j] * _POWER[j + 1]
    return mix(total)


def shingle_sets(texts: list[bytes], width: int = WIDTH) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each text; short texts share the arrays of a piece."""
    with np.errstate(over="ignore"):
        start = 0
        while start < len(texts):
            end, size = start, 0
            while end < len(texts) and (end == start or size + len(texts[end]) <= PIECE):
                size += len(texts[end]) + 1
                end += 1
            if end - start == 1:
                yield distinct(shingle_hashes(word_hashes(texts[start]), width))
            else:
                words, at = _hashes(np.frombuffer(b" ".join(texts[start:end]), np.uint8))
                bounds = np.searchsorted(at, np.cumsum([0, *(len(t) + 1 for t in texts[start:end])]))
                for a, b in zip(bounds[:-1], bounds[1:], strict=True):
                    yield distinct(shingle_hashes(words[a:b], width))
            start = end
