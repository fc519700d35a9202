"""Averaged hashed subword embeddings with a linear softmax, in numpy."""

from __future__ import annotations

from functools import lru_cache

import numpy as np

BUCKETS = 1 << 16
_SIZES = (2, 3, 4)
_FACTORS = np.array([0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D, 0x27D4EB2F], np.uint32)


@lru_cache(maxsize=1)
def _folded() -> np.ndarray:
    """The lower case of each letter's code point; 0 for what is no letter."""
    fold = np.zeros(0x110000, np.uint32)
    for c in range(0x110000):
        x = chr(c)
        if x.isalpha():
            low = x.lower()
            fold[c] = ord(low) if len(low) == 1 else c
    return fold


def subwords(texts: list[str]) -> tuple[list[np.ndarray], np.ndarray]:
    """For the texts joined: the bucket of the character n-gram that starts at each place (-1 for
    none), one array for each n, and where each text starts.

    An n-gram lies inside a word with the word's two edges; words are runs of letters, lower-cased.
    """
    joined = "\n".join(["", *texts, ""])
    code = _folded()[np.frombuffer(joined.encode("utf-32-le", "replace"), np.uint32)]
    starts = np.cumsum([1, *(len(t) + 1 for t in texts)]) - 1
    letter = code != 0
    found = []
    for n in _SIZES:
        m = max(0, len(code) - n + 1)
        hashed = np.full(m, 0x811C9DC5 + n, np.uint32)
        good = letter[:m] | letter[n - 1 : n - 1 + m]
        for k in range(n):
            hashed ^= code[k : k + m] * _FACTORS[k]
            hashed *= np.uint32(0x01000193)
            if 0 < k < n - 1:
                good &= letter[k : k + m]
        hashed ^= hashed >> np.uint32(15)
        place = (hashed & np.uint32(BUCKETS - 1)).astype(np.int32)
        place[~good] = -1
        found.append(np.concatenate((place, np.full(len(code) - m, -1, np.int32))))
    return found, starts


class LanguageModel:
    """labels, a value of each bucket for each label (embedding times weights), and a calibration."""

    def __init__(self, labels: list[str], table: np.ndarray, bias: np.ndarray, temperature: float = 1.0, least: float = 0.0) -> None:
        self.labels, self.bias, self.temperature, self.least = labels, bias, temperature, least
        # The last row stands for places without an n-gram; the last column counts n-grams.
        self.table = np.zeros((len(table) + 1, table.shape[1] + 1), np.float32)
        self.table[:-1, :-1], self.table[:-1, -1] = table, 1

    def logits(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Logits of each text, and whether it has a letter."""
        places, starts = subwords(texts)
        total = np.zeros((len(texts), self.table.shape[1]))
        for place in places:
            for c in range(self.table.shape[1]):
                total[:, c] += np.add.reduceat(self.table[:, c][place], starts[:-1]) if len(texts) else 0
        n = total[:, -1:]
        return total[:, :-1] / np.maximum(n, 1) + self.bias, n[:, 0] > 0

    def predict(self, texts: list[str]) -> tuple[list[str], np.ndarray]:
        """The label (und without a letter) and its calibrated probability (then 0)."""
        z, some = self.logits(texts)
        if not self.labels:
            return ["und"] * len(texts), np.zeros(len(texts))
        p = _softmax(z / self.temperature)
        best = p.argmax(axis=1)
        return [self.labels[b] if s else "und" for b, s in zip(best, some, strict=True)], np.where(some, p[np.arange(len(p)), best], 0.0)


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


def _snippets(texts: list[str], labels: np.ndarray, words: int, most: int) -> tuple[list[str], np.ndarray]:
    """Training samples: runs of words, so that short texts are learned too."""
    out, of = [], []
    for text, label in zip(texts, labels.tolist(), strict=True):
        own = text.split()
        runs = [" ".join(own[i : i + words]) for i in range(0, len(own), words)]
        step = max(1, len(runs) // most)
        out += runs[::step]
        of += [label] * len(runs[::step])
    return out, np.array(of)


def train(texts: list[str], names: list[str], dim: int = 12, epochs: int = 3, rate: float = 4.0, seed: int = 7, words: int = 30, precision: float = 0.99) -> LanguageModel:
    """Stochastic gradient descent over snippets; every fifth text calibrates."""
    labels = sorted(set(names))
    if not labels:
        return LanguageModel([], np.zeros((BUCKETS, 0), np.float32), np.zeros(0))
    y = np.array([labels.index(n) for n in names])
    draw = np.random.default_rng(seed)
    order = draw.permutation(len(texts))
    held = order[: len(order) // 5]
    own = order[len(order) // 5 :] if len(order) >= 5 else order
    x, t = _snippets([texts[i] for i in own], y[own], words, 12)
    e = draw.normal(0, 1 / dim, (BUCKETS, dim)).astype(np.float32)
    w, b = np.zeros((dim, len(labels)), np.float32), np.zeros(len(labels), np.float32)
    size, step = 64, 0
    total = epochs * -(-len(x) // size)
    weight = len(t) / (len(labels) * np.maximum(1, np.bincount(t, minlength=len(labels))))  # classes count alike
    for _ in range(epochs):
        mixed = draw.permutation(len(x))
        for i in range(0, len(mixed), size):
            some = mixed[i : i + size]
            places, starts = subwords([x[k] for k in some])
            at = np.concatenate([p[p >= 0] for p in places])
            of = np.concatenate([np.searchsorted(starts, np.flatnonzero(p >= 0), "right") - 1 for p in places])
            n = np.maximum(1, np.bincount(of, minlength=len(some)))
            mean = np.stack([np.bincount(of, weights=e[at, d], minlength=len(some)) for d in range(dim)], axis=1) / n[:, None]
            p = _softmax(mean @ w + b)
            p[np.arange(len(some)), t[some]] -= 1
            p *= weight[t[some]][:, None] / len(some)
            lr = rate * (1 - step / total)
            back = (p @ w.T) / n[:, None]
            for d in range(dim):
                e[:, d] -= (lr * np.bincount(at, weights=back[of, d], minlength=BUCKETS)).astype(np.float32) * len(some)
            w -= (lr * mean.T @ p).astype(np.float32)
            b -= (lr * 0.1 * p.sum(axis=0)).astype(np.float32)
            step += 1
    model = LanguageModel(labels, e @ w, b)
    if len(held):
        z, some = model.logits([texts[i] for i in held])
        z, truth = z[some], y[held][some]
        if len(z):
            grid = np.geomspace(0.05, 20, 60)
            loss = [-np.log(np.maximum(_softmax(z / c)[np.arange(len(z)), truth], 1e-12)).mean() for c in grid]
            model.temperature = float(grid[int(np.argmin(loss))])
            p = _softmax(z / model.temperature)
            score, right = p.max(axis=1), p.argmax(axis=1) == truth
            down = np.argsort(-score, kind="stable")
            good = np.flatnonzero(np.cumsum(right[down]) >= precision * np.arange(1, len(down) + 1))
            # The least score down to which the wanted precision holds.
            model.least = float(score[down][good[-1]]) if len(good) else 1.0
    return model
