"""Vectorised kernels over the UTF-8 bytes of many texts at once.

Words are runs of bytes other than blank and 0x09-0x0D; A-Z count as a-z.  A word's 64-bit
hash mixes its bytes eight at a time, starting from its length, so words of up to eight
bytes never share one; five-word shingles combine the hashes of their words by position.
``Words`` holds one text's words themselves, for tests that must not rest on hashes.
"""

from __future__ import annotations

import numpy as np
import xxhash

from gridlake.llm.common import CHUNK_BYTES, mixed

WORDS = 5
_rng = np.random.default_rng(20_250_101)
_VALUE = _rng.integers(1, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_VALUE[65:91] = _VALUE[97:123]
_ODD = _rng.integers(1, 2**63, WORDS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_R = 0x9E3779B97F4A7C15 | 1
_R_INV = pow(_R, -1, 2**64)
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] = _LOWER[97:123]
#: Longer words, in bytes, are hashed one by one.
LONG = 256
#: Of the eight bytes at a place, those of a word that has so many left.
_MASK = np.array([(1 << (8 * k)) - 1 for k in range(8)] + [2**64 - 1], np.uint64)
_powers: list[np.ndarray] = []


def _tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse modulo 2^64; tables for very long texts aren't kept."""
    if n > CHUNK_BYTES + 1:
        return tuple(np.cumprod(np.concatenate(([np.uint64(1)], np.full(n - 1, x, np.uint64)))) for x in (_R, _R_INV))
    if not _powers or len(_powers[0]) < n:
        size = max(n, CHUNK_BYTES + 1)
        _powers[:] = [np.cumprod(np.concatenate(([np.uint64(1)], np.full(size - 1, x, np.uint64)))) for x in (_R, _R_INV)]
    return _powers[0], _powers[1]


def word_places(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First bytes of all words and the bytes behind them; ``offsets`` begin at 0."""
    word = ~_SPACE[data]
    begin = word.copy()
    begin[1:] &= ~word[:-1]
    edge = offsets[1:-1][offsets[1:-1] < len(data)]
    begin[edge] = word[edge]
    end = word.copy()
    end[:-1] &= ~word[1:]
    before = edge[edge > 0] - 1
    end[before] = word[before]
    return np.flatnonzero(begin), np.flatnonzero(end) + 1


def lanes(low: np.ndarray) -> np.ndarray:
    """The eight bytes from every place as one number; zeros behind the end."""
    padded = np.concatenate((low, np.zeros(8, np.uint8)))
    return np.ndarray((len(low),), "<u8", padded.data, strides=(1,))


def hashed(low: np.ndarray, starts: np.ndarray, stops: np.ndarray) -> np.ndarray:
    """Hashes of words in lower case."""
    view, lens = lanes(low), stops - starts
    h = mixed(lens.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))
    long = np.flatnonzero(lens > LONG)
    active, at = (np.arange(len(starts)) if not len(long) else np.flatnonzero(lens <= LONG)), 0
    while len(active):
        part = view[starts[active] + at] & _MASK[np.minimum(lens[active] - at, 8)]
        h[active] = mixed((h[active] ^ part) * np.uint64(_R))
        at += 8
        active = active[lens[active] > at]
    for i in long.tolist():
        h[i] = xxhash.xxh3_64_intdigest(low[starts[i] : stops[i]].data, seed=1)
    return h


def word_hashes(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all words in order, and where each text's words begin (len + 1)."""
    data = data[int(offsets[0]) : int(offsets[-1])]
    offs = offsets - int(offsets[0])
    if not len(data):
        return np.zeros(0, np.uint64), np.zeros(len(offsets), np.int64)
    starts, stops = word_places(data, offs)
    return hashed(_LOWER[data], starts, stops), np.searchsorted(starts, offs)


def plain_texts(data: np.ndarray, offsets: np.ndarray) -> list[bytes]:
    """Each text's words in lower case with one blank between them."""
    data = data[int(offsets[0]) : int(offsets[-1])]
    offs = offsets - int(offsets[0])
    word = ~_SPACE[data]
    keep = word.copy()
    keep[1:] |= word[:-1]
    inner = offs[:-1][offs[:-1] < len(data)]
    keep[inner] = word[inner]  # no blank for a word of the text before
    out = np.where(word, _LOWER[data], np.uint8(0x20))[keep].tobytes()
    cut = np.concatenate(([0], np.cumsum(keep)))[offs].tolist()
    return [out[a:b].rstrip(b" ") for a, b in zip(cut[:-1], cut[1:], strict=True)]


class Words:
    """One text's words, their hashes and its shingles' hashes in order."""

    def __init__(self, text: bytes):
        self.low = _LOWER[np.frombuffer(text, np.uint8)]
        ends = np.array([0, len(self.low)])
        self.starts, self.stops = word_places(self.low, ends) if len(self.low) else (np.zeros(0, np.int64),) * 2
        self.hashes = hashed(self.low, self.starts, self.stops)
        self.shingles = shingle_hashes(self.hashes, np.array([0, len(self.hashes)]))[0]
        self.set = np.unique(self.shingles)

    def list(self) -> list[bytes]:
        return [self.low[a:b].tobytes() for a, b in zip(self.starts.tolist(), self.stops.tolist(), strict=True)]

    def exact(self) -> set[tuple[bytes, ...]]:
        """The shingles themselves."""
        own = self.list()
        return {tuple(own[k : k + WORDS]) for k in range(len(own) - WORDS + 1)} if len(own) >= WORDS else {tuple(own)} if own else set()


def _groups(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places in order of their value, and for each the first place with that value."""
    order = np.argsort(x, kind="stable")
    if not len(x):
        return order, order
    head = np.concatenate(([True], x[order][1:] != x[order][:-1]))
    return order, order[np.flatnonzero(head)][np.cumsum(head) - 1]


def unmixed(a: Words, b: Words) -> bool:
    """Whether no two different words, and no two different shingles, of both texts share a
    hash: then what the hashes say of the two sets is what the words say."""
    low = np.concatenate((a.low, b.low))
    starts, stops = np.concatenate((a.starts, b.starts + len(a.low))), np.concatenate((a.stops, b.stops + len(a.low)))
    hashes = np.concatenate((a.hashes, b.hashes))
    own, first = _groups(hashes)
    own, first = own[own != first], first[own != first]
    lens = stops - starts
    if (lens[own] != lens[first]).any():
        return False
    view, at, active = lanes(low), 0, np.flatnonzero(lens[own] <= LONG)
    while len(active):
        mask = _MASK[np.minimum(lens[own[active]] - at, 8)]
        if ((view[starts[own[active]] + at] ^ view[starts[first[active]] + at]) & mask).any():
            return False
        at += 8
        active = active[lens[own[active]] > at]
    for k in np.flatnonzero(lens[own] > LONG).tolist():
        if not np.array_equal(low[starts[own[k]] : stops[own[k]]], low[starts[first[k]] : stops[first[k]]]):
            return False
    n, m = len(a.hashes), len(b.hashes)
    if n < WORDS or m < WORDS:
        return np.array_equal(a.hashes, b.hashes) or not overlap(a.set, b.set)
    begin = np.concatenate((np.arange(n - WORDS + 1), n + np.arange(m - WORDS + 1)))
    own, first = _groups(np.concatenate((a.shingles, b.shingles)))
    return all((hashes[begin[own] + k] == hashes[begin[first] + k]).all() for k in range(WORDS))


def overlap(small: np.ndarray, large: np.ndarray) -> int:
    """Common values of two sorted sets."""
    if not len(small) or not len(large):
        return 0
    return int((np.take(large, np.searchsorted(large, small), mode="clip") == small).sum())


def similar(a: Words, b: Words, threshold: int) -> tuple[int, bool]:
    """The sets' common hashes, and whether the sets of words themselves are similar enough
    (in hundredths)."""
    small, large = (a.set, b.set) if len(a.set) <= len(b.set) else (b.set, a.set)
    common = overlap(small, large)
    if not len(small) or 100 * common < threshold * (len(small) + len(large) - common):
        return common, False
    if unmixed(a, b):
        return common, True
    x, y = a.exact(), b.exact()
    return common, 100 * len(x & y) >= threshold * len(x | y)


def shingle_hashes(words: np.ndarray, bounds: np.ndarray, size: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all shingles in order, repeated ones too, and each text's bounds.

    A text with fewer words has them all as one shingle; one without words has none.
    """
    m = np.diff(bounds)
    count = np.where(m >= size, m - size + 1, (m > 0).astype(np.int64))
    out_bounds = np.concatenate(([0], np.cumsum(count)))
    n = len(words)
    if not n:
        return np.zeros(0, np.uint64), out_bounds
    rolled = np.zeros(max(0, n - size + 1), np.uint64)
    for k in range(size):
        rolled += words[k : n - size + 1 + k] * _ODD[k] if len(rolled) else np.uint64(0)
    long = np.flatnonzero(m >= size)
    out = np.empty(int(out_bounds[-1]), np.uint64)
    if len(long):
        into = _ranges(out_bounds[long], count[long])
        out[into] = rolled[_ranges(bounds[long], count[long])]
    for i in np.flatnonzero((m > 0) & (m < size)):
        own = words[bounds[i] : bounds[i + 1]]
        out[out_bounds[i]] = (int(np.sum(own * _ODD[: len(own)], dtype=np.uint64)) + len(own) * 0x632BE59BD9B4E019) & (2**64 - 1)
    return mixed(out), out_bounds


def _ranges(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The concatenation of ``range(start, start + count)``."""
    total = int(counts.sum())
    if not total:
        return np.zeros(0, np.int64)
    shift = np.repeat(starts - np.concatenate(([0], np.cumsum(counts)[:-1])), counts)
    return np.arange(total) + shift
