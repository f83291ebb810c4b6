"""A suffix automaton over words: built from passages, asked for the matching statistics of other passages."""

from __future__ import annotations

from collections.abc import Hashable, Iterable, Sequence


class SuffixAutomaton:
    """Holds every run of words of the passages that were added; no run reaches over the edge of a passage.

    Most states have one transition, so that is kept in two flat lists; only states with more get a dictionary.
    """

    def __init__(self):
        self.length, self.link = [0], [-1]
        self.word, self.target, self.more = [None], [-1], {}
        self.last = 0

    def _step(self, state: int, word: Hashable) -> int:
        if self.word[state] == word and self.target[state] >= 0:
            return self.target[state]
        branches = self.more.get(state)
        return -1 if branches is None else branches.get(word, -1)

    def _set(self, state: int, word: Hashable, to: int) -> None:
        if self.target[state] < 0 or self.word[state] == word:
            self.word[state], self.target[state] = word, to
        else:
            self.more.setdefault(state, {})[word] = to

    def _new(self, length: int, like: int = -1) -> int:
        state = len(self.length)
        self.length.append(length)
        self.link.append(-1 if like < 0 else self.link[like])
        self.word.append(None if like < 0 else self.word[like])
        self.target.append(-1 if like < 0 else self.target[like])
        if like >= 0 and like in self.more:
            self.more[state] = dict(self.more[like])
        return state

    def _split(self, p: int, word: Hashable, q: int) -> int:
        """The state for the longest run of p extended by the word, taken out of q if q also holds longer ones."""
        if self.length[p] + 1 == self.length[q]:
            return q
        clone = self._new(self.length[p] + 1, like=q)
        self.link[q] = clone
        while p >= 0 and self._step(p, word) == q:
            self._set(p, word, clone)
            p = self.link[p]
        return clone

    def add(self, passage: Iterable[Hashable]) -> None:
        last = 0
        for word in passage:
            q = self._step(last, word)
            if q >= 0:  # the run is already known from an earlier passage
                last = self._split(last, word, q)
                continue
            state, p = self._new(self.length[last] + 1), last
            while p >= 0 and (q := self._step(p, word)) < 0:
                self._set(p, word, state)
                p = self.link[p]
            self.link[state] = 0 if p < 0 else self._split(p, word, q)
            last = state

    def matches(self, words: Sequence[Hashable]) -> list[int]:
        """For each place, the length of the longest run that ends there and occurs in a passage."""
        state, n, out = 0, 0, []
        length, link, first, target, more = self.length, self.link, self.word, self.target, self.more
        for word in words:
            while True:
                if first[state] == word and target[state] >= 0:
                    state, n = target[state], n + 1
                    break
                if (branches := more.get(state)) is not None and word in branches:
                    state, n = branches[word], n + 1
                    break
                if (state := link[state]) < 0:
                    state, n = 0, 0
                    break
                n = length[state]
            out.append(n)
        return out

    def covered(self, words: Sequence[Hashable], least: int) -> list[tuple[int, int]]:
        """The maximal (start, end) whose words lie in runs of at least ``least`` words that occur in a passage."""
        out: list[tuple[int, int]] = []
        for end, n in enumerate(self.matches(words), 1):
            if n >= least:
                if out and end - n <= out[-1][1]:
                    out[-1] = (min(out[-1][0], end - n), end)
                else:
                    out.append((end - n, end))
        return out
