"""Suffix automaton of many word sequences, with occurrence counts."""

from __future__ import annotations

from collections.abc import Iterable, Sequence


class SuffixAutomaton:
    """Accepts every factor of the sequences added; each state knows how often its factors occur.

    Sequences are added with a weight and don't run into each other.  ``settle`` must be called before counts are read.
    """

    def __init__(self):
        self.next: list[dict] = [{}]
        self.link: list[int] = [-1]
        self.length: list[int] = [0]
        self.count: list[int] = [0]

    def __len__(self) -> int:
        return len(self.next)

    def add(self, words: Sequence, weight: int = 1) -> None:
        nexts, links, lengths, counts = self.next, self.link, self.length, self.count
        last = 0
        for w in words:
            to = nexts[last].get(w)
            if to is not None and lengths[to] == lengths[last] + 1:
                last = to
                counts[to] += weight
                continue
            if to is not None:
                last = self._split(last, w, to)
                counts[last] += weight
                continue
            new = len(nexts)
            nexts.append({})
            lengths.append(lengths[last] + 1)
            counts.append(weight)
            links.append(0)
            p = last
            while p >= 0:
                row = nexts[p]
                if w in row:
                    break
                row[w] = new
                p = links[p]
            if p >= 0:
                q = nexts[p][w]
                links[new] = q if lengths[q] == lengths[p] + 1 else self._split(p, w, q)
            last = new

    def _split(self, p: int, w, q: int) -> int:
        """The state of those factors of q that end in w behind p."""
        nexts, links, lengths = self.next, self.link, self.length
        copy = len(nexts)
        nexts.append(nexts[q].copy())
        lengths.append(lengths[p] + 1)
        links.append(links[q])
        self.count.append(0)
        links[q] = copy
        while p >= 0 and nexts[p].get(w) == q:
            nexts[p][w] = copy
            p = links[p]
        return copy

    def settle(self) -> None:
        """Adds each state's count to that of its suffixes, longest first."""
        links, counts, lengths = self.link, self.count, self.length
        buckets: list[list[int]] = [[] for _ in range(max(lengths) + 1)]
        for state, n in enumerate(lengths):
            buckets[n].append(state)
        for bucket in reversed(buckets[1:]):
            for state in bucket:
                counts[links[state]] += counts[state]

    def matches(self, words: Iterable, most: int) -> Iterable[tuple[int, int]]:
        """Matching statistics: after each word the length, at most ``most``, of the longest suffix read that is a
        factor, and the number of times that it occurs."""
        nexts, links, lengths, counts = self.next, self.link, self.length, self.count
        state = size = 0
        for w in words:
            while state and w not in nexts[state]:
                state = links[state]
                size = lengths[state]
            to = nexts[state].get(w)
            if to is None:
                yield 0, 0
                continue
            state, size = to, size + 1
            if size > most:
                size = most
            while lengths[links[state]] >= size:
                state = links[state]
            yield size, counts[state]
