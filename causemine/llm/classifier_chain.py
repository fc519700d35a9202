"""A chain of linear models over the words of texts and their beginnings, in numpy."""

from __future__ import annotations

import numpy as np

from .automaton import words


def _logistic(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -35, 35)))


def _fit(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, rounds: int = 25) -> np.ndarray:
    """Logistic regression by Newton steps; the last weight is the intercept."""
    x = np.hstack([x, np.ones((len(x), 1))])
    w, penalty = np.zeros(x.shape[1]), np.full(x.shape[1], ridge)
    penalty[-1] = 1e-6
    for _ in range(rounds):
        p = _logistic(x @ w)
        g = x.T @ (p - y) + penalty * w
        h = (x * (p * (1 - p))[:, None]).T @ x + np.diag(penalty + 1e-9)
        step = np.linalg.solve(h, g)
        w -= step
        if np.abs(step).max() < 1e-6:
            break
    return w


#: Lengths in bytes of the word beginnings that are features beside whole words.
PREFIXES = (3, 4, 5, 6, 7)


def _marks(own: set[bytes]) -> set[bytes]:
    """A text's features: its words, and their beginnings, marked by a hat."""
    found = set(own)
    for n in PREFIXES:
        found |= {b"^" + w[:n] for w in own if len(w) >= n}
    return found


def _telling(texts: list[str | None], y: np.ndarray, most: int, least_chi: float) -> list[list[bytes]]:
    """For each category the features that tell it best by chi-square; each occurs in several texts
    and in a hundredth of the category's own at least."""
    seen: dict[bytes, int] = {}  # how many texts have it, and from bit 40 * (c + 1) on how many of category c
    step = [1 + sum(int(v) << (40 * (c + 1)) for c, v in enumerate(row)) for row in y]
    for text, k in zip(texts, step, strict=True):
        for mark in _marks(set(words(text))):
            seen[mark] = seen.get(mark, 0) + k
    n, found = len(y), []
    for c in range(y.shape[1]):
        pos, best = int(y[:, c].sum()), []
        for mark, k in seen.items():
            a, b = k & 0xFFFFFFFFFF, (k >> (40 * (c + 1))) & 0xFFFFFFFFFF
            if a >= 4 and b * 100 >= pos and 0 < pos < n and a < n:
                chi = n * (b * (n - a - pos + b) - (a - b) * (pos - b)) ** 2 / (a * (n - a) * pos * (n - pos))
                if chi >= least_chi and b * n > a * pos:
                    best.append((-chi, mark))
        found.append([mark for _, mark in sorted(best)[:most]])
    return found


class Chain:
    """One logistic model for each category, in order. A later model sees the words and the
    probabilities of the categories before it; it was trained with out-of-fold ones."""

    def __init__(self, categories: list[str], vocabulary: list[bytes], weights: list[np.ndarray], thresholds: list[float]) -> None:
        self.categories, self.vocabulary, self.weights, self.thresholds = categories, vocabulary, weights, thresholds
        self.place = {w: i for i, w in enumerate(vocabulary)}
        self.known = frozenset(w for w in vocabulary if not w.startswith(b"^"))
        beginnings = [w[1:] for w in vocabulary if w.startswith(b"^")]
        self.by_length = {n: frozenset(w for w in beginnings if len(w) == n) for n in {len(w) for w in beginnings}}

    def features(self, texts: list[str | None]) -> np.ndarray:
        x = np.zeros((len(texts), len(self.vocabulary)))
        for i, text in enumerate(texts):
            own = set(words(text))
            for w in self.known & own:
                x[i, self.place[w]] = 1
            for n, some in self.by_length.items():
                for w in some & {w[:n] for w in own}:
                    x[i, self.place[b"^" + w]] = 1
        return x

    def predict(self, texts: list[str | None]) -> np.ndarray:
        """A probability for each text and category."""
        x = self.features(texts)
        for w in self.weights:
            p = _logistic(x @ w[:-1] + w[-1])
            x = np.hstack([x, p[:, None]])
        return x[:, len(self.vocabulary) :]


def train(texts: list[str], y: np.ndarray, categories: list[str], most: int = 200, least_chi: float = 30.0, folds: int = 5, seed: int = 3, precision: float = 0.98) -> Chain:
    """Fit a chain; y has a 0/1 column for each category.

    A category's threshold is the least out-of-fold probability, not under 0.3, from which up
    the wanted precision holds.
    """
    vocabulary = list(dict.fromkeys(w for own in _telling(texts, y, most, least_chi) for w in own))
    chain = Chain(categories, vocabulary, [], [])
    x = chain.features(texts)
    fold = np.random.default_rng(seed).permutation(len(texts)) % folds
    inside = x
    for c in range(len(categories)):
        t = y[:, c].astype(float)
        out = np.full(len(t), t.mean() if len(t) else 0.0)
        for f in range(folds if len(t) >= folds else 0):
            own = fold != f
            w = _fit(inside[own], t[own])
            out[~own] = _logistic(inside[~own] @ w[:-1] + w[-1])
        chain.weights.append(_fit(inside, t) if len(t) else np.zeros(inside.shape[1] + 1))
        down = np.argsort(-out, kind="stable")
        good = np.flatnonzero(np.cumsum(t[down]) >= precision * np.arange(1, len(t) + 1))
        chain.thresholds.append(max(0.3, float(out[down][good[-1]])) if len(good) and t.sum() else 1.0)
        inside = np.hstack([inside, out[:, None]])
    return chain
