"""Word and shingle hashes of many texts at once, in numpy."""

from __future__ import annotations

import numpy as np

SPACES = np.zeros(256, bool)
SPACES[[0x20, *range(0x09, 0x0E)]] = True
BLOCK = 4096


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective scramble of 64-bit words."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)


_LOW = _powers(0x5851F42D4C957F2D, BLOCK)


def hash_words(data: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts, ends and hashes of the words in UTF-8 bytes."""
    inside = ~SPACES[data]
    edge = np.flatnonzero(np.diff(np.concatenate(([False], inside, [False])).view(np.int8)))
    starts, ends = edge[::2], edge[1::2]
    if not len(starts):
        return starts, ends, np.zeros(0, np.uint64)
    sizes = ends - starts
    at = np.flatnonzero(inside)
    within = np.arange(len(at)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    terms = (data[at].astype(np.uint64) + np.uint64(1)) * _LOW[within & (BLOCK - 1)]
    if (longest := int(sizes.max())) > BLOCK:
        terms *= _powers(0xD1342543DE82EF95, longest // BLOCK + 1)[within // BLOCK]
    sums = np.add.reduceat(terms, np.cumsum(sizes) - sizes)
    return starts, ends, mix(sums + sizes.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))


def joined(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """All texts as one byte array with a blank after each, and the start of each."""
    raws = [t.encode("utf-8", "surrogatepass") for t in texts]
    sizes = np.fromiter(map(len, raws), np.int64, len(raws)) + 1
    return np.frombuffer(b" ".join([*raws, b""]), np.uint8), np.cumsum(sizes) - sizes


def shingle_lists(texts: list[str], width: int) -> list[np.ndarray]:
    """Sorted hashes of all ``width``-word windows per text; of a shorter text all its words are its one shingle; none without words."""
    data, begins = joined(texts)
    starts, _, words = hash_words(data)
    bounds = np.append(np.searchsorted(starts, begins), len(starts))
    rolled = np.zeros(max(0, len(words) - width + 1), np.uint64)
    for k in range(width):
        rolled = mix(rolled ^ words[k : k + len(rolled)]) + np.uint64(k)
    out = []
    for lo, hi in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
        if hi - lo >= width:
            own = rolled[lo : hi - width + 1].copy()
            own.sort()
        elif hi > lo:
            h = np.zeros(1, np.uint64)
            for k in range(lo, hi):
                h = mix(h ^ words[k : k + 1]) + np.uint64(hi - lo + 64)
            own = h
        else:
            own = np.zeros(0, np.uint64)
        out.append(own)
    return out


def multiset_jaccard(a: np.ndarray, b: np.ndarray) -> float:
    """Sum of the smaller counts over sum of the larger counts of two sorted lists; 0 for two empty ones."""
    if not len(a) or not len(b):
        return 0.0
    values, counts = np.unique(a, return_counts=True)
    others, others_counts = np.unique(b, return_counts=True)
    at = np.searchsorted(values, others)
    at[at == len(values)] = 0
    common = int(np.minimum(counts[at], others_counts)[values[at] == others].sum())
    return common / (len(a) + len(b) - common)
