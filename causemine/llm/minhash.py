"""One-permutation hashing with optimal densification over sets of word shingles."""

from __future__ import annotations

import numpy as np
import xxhash

from .shared import mix


class Signer:
    """Banded signatures of sets of 64-bit hashes.

    The hash space is cut into `bins`; a bin's value is its least hash. An empty bin copies the
    value of the first filled bin in a random order of its own, so each empty bin draws on its own.
    """

    def __init__(self, bands: int = 32, rows: int = 4, seed: int = 20_11) -> None:
        self.bands, self.rows, self.bins = bands, rows, bands * rows
        if self.bins & (self.bins - 1):
            raise ValueError("bands * rows must be a power of two")
        self.shift = np.uint64(64 - self.bins.bit_length() + 1)
        order = np.random.default_rng(seed)
        #: rank[i, j]: when bin i, if it is empty, asks bin j.
        self.rank = np.stack([order.permutation(self.bins) for _ in range(self.bins)]).astype(np.int16)
        self.salt = mix(np.arange(self.bins, dtype=np.uint64) + np.uint64(seed))

    def values(self, hashes: np.ndarray) -> np.ndarray:
        """The value of each bin, for a sorted array of distinct hashes, not empty."""
        bin_of = (hashes >> self.shift).astype(np.int64)
        first = np.flatnonzero(np.diff(bin_of, prepend=-1))
        filled = bin_of[first]
        least = np.zeros(self.bins, np.uint64)
        least[filled] = hashes[first]
        if len(filled) < self.bins:
            empty = np.setdiff1d(np.arange(self.bins), filled, assume_unique=True)
            least[empty] = least[filled[self.rank[np.ix_(empty, filled)].argmin(axis=1)]]
        return least

    def band_keys(self, hashes: np.ndarray) -> np.ndarray:
        """One 64-bit key for each band."""
        with np.errstate(over="ignore"):
            mixed = mix(self.values(hashes) ^ self.salt).reshape(self.bands, self.rows)
            return mix(mixed.sum(axis=1, dtype=np.uint64) + np.arange(self.bands, dtype=np.uint64))


def word_hashes(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """A 64-bit hash of each word of the texts, one after the other, and where each text starts.

    A-Z is lower-cased and words end at ASCII white space, which is what bytes do.
    """
    known: dict[bytes, int] = {}
    codes, ends = [], [0]
    for text in texts:
        own = [known.setdefault(w, len(known)) for w in (text or "").encode().lower().split()]
        codes += own
        ends.append(len(codes))
    hashes = np.fromiter(map(xxhash.xxh3_64_intdigest, known), np.uint64, len(known))
    return hashes[np.array(codes, np.int64)], np.array(ends)


def shingle_sets(texts: list[str | None], size: int) -> list[np.ndarray]:
    """The sorted distinct hashes of each text's shingles of `size` words. A text with fewer words
    has its whole sequence as one shingle; a text without words has none."""
    words, ends = word_hashes(texts)
    with np.errstate(over="ignore"):
        rolled = mix(words)
        for k in range(1, size):
            rolled = mix(rolled[: len(words) - k] * np.uint64(0x100000001B3) + words[k:]) if len(words) > k else rolled[:0]
    found = []
    for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True):
        if b - a >= size:
            found.append(np.unique(rolled[a : b - size + 1]))
        elif b > a:
            with np.errstate(over="ignore"):
                own = mix(words[a : a + 1])
                for k in range(a + 1, b):
                    own = mix(own * np.uint64(0x100000001B3) + words[k : k + 1])
                found.append(mix(own + np.uint64(b - a)))
        else:
            found.append(np.empty(0, np.uint64))
    return found
