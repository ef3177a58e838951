"""Generalised suffix automaton over sequences of word numbers, in plain Python, small enough to be broadcast."""

from __future__ import annotations

from collections.abc import Iterable


class SuffixAutomaton:
    """States are lists: ``next`` (dict per state), ``link``, ``len``; ``items`` holds, per state, which sequences contain
    its strings. Strings are added one after the other, sharing states."""

    def __init__(self) -> None:
        self.next: list[dict[int, int]] = [{}]
        self.link, self.len, self.items = [-1], [0], [set()]
        self.whole: dict[int, list[int]] = {}  # state -> short sequences that are exactly its string of their length
        self.sizes: list[int] = []

    def _new(self, length: int, link: int, moves: dict[int, int]) -> int:
        self.next.append(moves)
        self.len.append(length)
        self.link.append(link)
        self.items.append(set())
        return len(self.len) - 1

    def _split(self, p: int, c: int, q: int) -> int:
        copy = self._new(self.len[p] + 1, self.link[q], dict(self.next[q]))
        self.link[q] = copy
        while p >= 0 and self.next[p].get(c) == q:
            self.next[p][c] = copy
            p = self.link[p]
        return copy

    def _extend(self, last: int, c: int) -> int:
        if (q := self.next[last].get(c)) is not None:
            return q if self.len[q] == self.len[last] + 1 else self._split(last, c, q)
        cur, p = self._new(self.len[last] + 1, 0, {}), last
        while p >= 0 and c not in self.next[p]:
            self.next[p][c] = cur
            p = self.link[p]
        if p >= 0:
            q = self.next[p][c]
            self.link[cur] = q if self.len[q] == self.len[p] + 1 else self._split(p, c, q)
        return cur

    def add(self, sequence: Iterable[int]) -> int:
        """Number of the sequence within the automaton."""
        last, n = 0, 0
        for n, c in enumerate(sequence, 1):  # noqa: B007
            last = self._extend(last, c)
        self.sizes.append(n)
        return len(self.sizes) - 1

    def settle(self, sequences: list[list[int]], window: int) -> None:
        """Fill ``items`` and ``whole`` once all sequences are in."""
        for i, seq in enumerate(sequences):
            s = 0
            for c in seq:
                s = self.next[s][c]
                t = s
                while t > 0 and i not in self.items[t]:
                    self.items[t].add(i)
                    t = self.link[t]
            if 0 < len(seq) < window:
                self.whole.setdefault(s, []).append(i)
        # nearest state up the links, itself included, at which a short sequence ends
        self.short = [-1] * len(self.len)
        for s in sorted(range(1, len(self.len)), key=self.len.__getitem__):
            self.short[s] = s if s in self.whole else self.short[self.link[s]]

    def matches(self, words: list[int], window: int):
        """Yields (end, length, item numbers) for every place where the last ``length`` words are a window of an item.

        The running match is the longest suffix that is a substring of some item; ``window`` long suffixes of it are
        windows, and so are the short items among its suffixes."""
        nxt, link, length = self.next, self.link, self.len
        s = n = 0
        for at, c in enumerate(words, 1):
            while s and c not in nxt[s]:
                s = link[s]
                n = length[s]
            t = nxt[s].get(c)
            if t is None:
                s = n = 0
                continue
            s, n = t, n + 1
            if n >= window:
                u = s
                while length[link[u]] >= window:
                    u = link[u]
                yield at, window, self.items[u]
            u = self.short[s]
            while u > 0:
                hit = [i for i in self.whole[u] if self.sizes[i] <= n]
                if hit:
                    yield at, self.sizes[hit[0]], hit
                u = self.short[link[u]]

    def statistics(self, words: list[int]) -> list[int]:
        """Matching statistics: length of the longest match that ends at each word."""
        out, s, n = [], 0, 0
        for c in words:
            while s and c not in self.next[s]:
                s = self.link[s]
                n = self.len[s]
            t = self.next[s].get(c)
            s, n = (0, 0) if t is None else (t, n + 1)
            out.append(n)
        return out
