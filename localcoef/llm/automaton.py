"""A suffix automaton over word hashes, with weighted occurrence counts and streaming of matching statistics."""

from __future__ import annotations

from collections.abc import Iterable, Sequence


class SuffixAutomaton:
    """All runs of words of the added sequences; ``count`` of a state is the weight of the places where its runs end."""

    def __init__(self):
        self.length, self.link, self.next, self.count = [0], [-1], [{}], [0]

    def _state(self, length: int, weight: int) -> int:
        self.length.append(length)
        self.link.append(-1)
        self.next.append({})
        self.count.append(weight)
        return len(self.length) - 1

    def _split(self, p: int, q: int, word: int, weight: int) -> int:
        """A state for the shorter runs of ``q`` that are reached from ``p``."""
        new = self._state(self.length[p] + 1, weight)
        self.next[new] = dict(self.next[q])
        self.link[new] = self.link[q]
        self.link[q] = new
        while p >= 0 and self.next[p].get(word) == q:
            self.next[p][word] = new
            p = self.link[p]
        return new

    def add(self, words: Iterable[int], weight: int = 1) -> None:
        length, link, nxt = self.length, self.link, self.next
        last = 0
        for word in words:
            q = nxt[last].get(word)
            if q is not None:
                if length[q] == length[last] + 1:
                    self.count[q] += weight
                    last = q
                else:
                    last = self._split(last, q, word, weight)
                continue
            new = self._state(length[last] + 1, weight)
            p = last
            while p >= 0 and word not in nxt[p]:
                nxt[p][word] = new
                p = link[p]
            if p < 0:
                link[new] = 0
            else:
                q = nxt[p][word]
                link[new] = q if length[q] == length[p] + 1 else self._split(p, q, word, 0)
            last = new

    def finish(self) -> SuffixAutomaton:
        """Sums the weights up the suffix links."""
        for s in sorted(range(1, len(self.length)), key=self.length.__getitem__, reverse=True):
            self.count[self.link[s]] += self.count[s]
        return self

    def stream(self, words: Sequence[int], width: int, least: int) -> list[int]:
        """Starts of the runs of ``width`` words that end at places of weight ``least`` or more.

        The matching statistics are followed word by word; of a longer match only the state of its last ``width``
        words is kept.
        """
        length, link, nxt, count = self.length, self.link, self.next, self.count
        state = size = 0
        out = []
        for i, word in enumerate(words):
            while state and word not in nxt[state]:
                state = link[state]
                size = length[state]
            if word not in nxt[state]:
                continue
            state = nxt[state][word]
            size += 1
            while length[link[state]] >= width:
                state = link[state]
            size = min(size, length[state])
            if size >= width and count[state] >= least:
                out.append(i - width + 1)
        return out
