"""A suffix automaton over several token sequences, for matching statistics with the smallest owner of a match."""

from __future__ import annotations


class SuffixAutomaton:
    """All substrings of the added sequences; each state knows the smallest owner among its occurrences."""

    def __init__(self):
        self.next: list[dict] = [{}]
        self.link, self.length, self.least = [-1], [0], [None]
        self.final = False

    def _state(self, length: int, link: int, moves: dict, least) -> int:
        self.next.append(moves)
        self.length.append(length)
        self.link.append(link)
        self.least.append(least)
        return len(self.length) - 1

    def _split(self, p: int, token, q: int) -> int:
        """A state of its own for what of q ends here."""
        clone = self._state(self.length[p] + 1, self.link[q], dict(self.next[q]), self.least[q])
        self.link[q] = clone
        while p >= 0 and self.next[p].get(token) == q:
            self.next[p][token] = clone
            p = self.link[p]
        return clone

    def add(self, tokens, owner) -> None:
        last = 0
        for token in tokens:
            q = self.next[last].get(token)
            if q is not None:  # known from another sequence
                last = q if self.length[q] == self.length[last] + 1 else self._split(last, token, q)
                if self.least[last] is None or owner < self.least[last]:
                    self.least[last] = owner
                continue
            new = self._state(self.length[last] + 1, 0, {}, owner)
            p = last
            while p >= 0 and token not in self.next[p]:
                self.next[p][token] = new
                p = self.link[p]
            if p >= 0:
                q = self.next[p][token]
                self.link[new] = q if self.length[q] == self.length[p] + 1 else self._split(p, token, q)
            last = new

    def finish(self) -> None:
        """Owners go from longer matches to their suffixes."""
        for v in sorted(range(1, len(self.length)), key=self.length.__getitem__, reverse=True):
            up = self.link[v]
            if up > 0 and (self.least[up] is None or self.least[v] < self.least[up]):
                self.least[up] = self.least[v]
        self.final = True

    def statistics(self, tokens, enough: int):
        """For each position: the smallest owner of the `enough` tokens that end there, or None."""
        v, have = 0, 0
        for token in tokens:
            while v and token not in self.next[v]:
                v = self.link[v]
                have = self.length[v]
            if token in self.next[v]:
                v, have = self.next[v][token], have + 1
            if have < enough:
                yield None
                continue
            while self.length[self.link[v]] >= enough:
                v = self.link[v]
                have = self.length[v]
            yield self.least[v]
