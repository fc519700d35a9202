"""A generalised suffix automaton over words of benchmark items, and its matches in texts."""

from __future__ import annotations

import numpy as np

#: A-Z lower-cased; what is no ASCII letter, digit or non-ASCII byte ends a word.
_WORDS = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b > 127 else 32 for b in range(256))


def words(text: str | None) -> list[bytes]:
    return (text or "").encode().translate(_WORDS).split()


class SuffixAutomaton:
    """All runs of consecutive words of all items.

    A window is a run of `window` words of an item, or a whole item of fewer. `match` gives the
    words of a text that lie inside occurrences of windows, and the items they come from.
    """

    def __init__(self, items: list[tuple[str, list[bytes]]], window: int = 13) -> None:
        self.window = window
        self.code: dict[bytes, int] = {}
        self.length, self.link, self.next = [0], [-1], [{}]
        coded = [(name, [self.code.setdefault(w, len(self.code)) for w in own]) for name, own in items if own]
        for _, own in coded:
            last = 0
            for w in own:
                last = self._extend(last, w)
        self.shortest = min([window, *(len(own) for _, own in coded)], default=window)
        found: list[set[str]] = [set() for _ in self.link]
        whole: list[list[tuple[int, str]]] = [[] for _ in self.link]
        for name, own in coded:
            state = 0
            for w in own:
                state = up = self.next[state][w]
                while up > 0 and name not in found[up]:
                    found[up].add(name)
                    up = self.link[up]
            if len(own) < window:
                whole[state].append((len(own), name))
        # By state: the items with its run of `window` words, and the short items that end there.
        order = sorted(range(1, len(self.link)), key=self.length.__getitem__)
        self.items: list[frozenset[str]] = [frozenset()] * len(self.link)
        self.short: list[list[tuple[int, str]]] = [[] for _ in self.link]
        for s in order:
            up = self.link[s]
            self.short[s] = self.short[up] + whole[s]
            if self.length[s] >= window:
                self.items[s] = self.items[up] if self.length[up] >= window else frozenset(found[s])
        pairs = sorted({(a, b) for _, own in coded for a, b in zip(own, own[1:], strict=False)})
        self.pairs = np.array([a * len(self.code) + b for a, b in pairs], np.int64)

    def _extend(self, last: int, w: int) -> int:
        to = self.next[last].get(w)
        if to is not None:  # the run is there already, from an item before
            return to if self.length[to] == self.length[last] + 1 else self._split(last, w, to)
        own = len(self.length)
        self.length.append(self.length[last] + 1)
        self.link.append(0)
        self.next.append({})
        at = last
        while at >= 0 and w not in self.next[at]:
            self.next[at][w] = own
            at = self.link[at]
        if at >= 0:
            to = self.next[at][w]
            self.link[own] = to if self.length[to] == self.length[at] + 1 else self._split(at, w, to)
        return own

    def _split(self, at: int, w: int, to: int) -> int:
        """A state for the shorter runs of `to`, those that end the run of `at` and w."""
        copy = len(self.length)
        self.length.append(self.length[at] + 1)
        self.link.append(self.link[to])
        self.next.append(dict(self.next[to]))
        self.link[to] = copy
        while at >= 0 and self.next[at].get(w) == to:
            self.next[at][w] = copy
            at = self.link[at]
        return copy

    def match(self, codes: list[int], first: int = 0) -> tuple[list[tuple[int, int]], set[str]]:
        """Spans [start, end) inside the text, of which codes are the words from number first on,
        and items."""
        spans: list[tuple[int, int]] = []
        items: set[str] = set()
        state = length = 0
        for i, w in enumerate(codes, first):
            while state and w not in self.next[state]:
                state = self.link[state]
                length = self.length[state]
            to = self.next[state].get(w)
            if to is None:
                state = length = 0
                continue
            state, length = to, length + 1
            size = 0
            if length >= self.window:
                size = self.window
                items |= self.items[state]
            for n, name in self.short[state]:
                if n <= length:
                    size = max(size, n)
                    items.add(name)
            if size:
                start = i + 1 - size
                if spans and start <= spans[-1][1]:
                    spans[-1] = (min(spans[-1][0], start), i + 1)
                else:
                    spans.append((start, i + 1))
        return _joined(spans), items

    def matches(self, texts: list[list[bytes]]) -> list[tuple[list[tuple[int, int]], set[str]]]:
        """`match` for each text. Only runs in which all neighbouring words are neighbours in some
        item go through the automaton; a run shorter than the shortest window cannot hold one."""
        found: list[tuple[list[tuple[int, int]], set[str]]] = [([], set()) for _ in texts]
        if not self.code:
            return found
        get = self.code.get
        ends = np.cumsum([len(t) + 1 for t in texts])
        codes = np.fromiter((c for t in texts for c in (*[get(w, -1) for w in t], -1)), np.int64, int(ends[-1]) if len(ends) else 0)
        known = codes >= 0
        goes_on = known[:-1] & known[1:]
        at = np.flatnonzero(goes_on)
        goes_on[at] = np.isin(codes[at] * len(self.code) + codes[at + 1], self.pairs)
        # Runs of known words, cut where two neighbours are none in any item.
        starts = np.flatnonzero(known & ~np.concatenate(([False], goes_on)))
        stops = np.flatnonzero(known & ~np.concatenate((goes_on, [False]))) + 1
        for a, b in zip(starts.tolist(), stops.tolist(), strict=True):
            if b - a >= self.shortest:
                text = int(np.searchsorted(ends, a, "right"))
                first = a - (int(ends[text - 1]) if text else 0)
                spans, items = self.match(codes[a:b].tolist(), first)
                if spans:
                    found[text] = (found[text][0] + spans, found[text][1] | items)
        return found


def _joined(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Spans in order, with those that overlap or touch made one."""
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out
