"""A suffix automaton over characters: longest common substrings and frequent substrings of a group of rows."""

from __future__ import annotations


class SuffixAutomaton:
    """Of one or several strings. A state stands for substrings with the same end places; length is its longest one."""

    def __init__(self, *texts: str):
        self.next: list[dict[str, int]] = [{}]
        self.link, self.length, self.sample = [-1], [0], [(0, 0)]
        self.texts = texts
        for number, text in enumerate(texts):
            last = 0
            for at, c in enumerate(text):
                last = self._append(last, c, (number, at + 1))

    def _state(self, length: int, out: dict[str, int], link: int, sample: tuple[int, int]) -> int:
        self.next.append(out), self.link.append(link), self.length.append(length), self.sample.append(sample)
        return len(self.next) - 1

    def _exact(self, p: int, c: str) -> int:
        q = self.next[p][c]
        if self.length[q] == self.length[p] + 1:
            return q
        copy = self._state(self.length[p] + 1, dict(self.next[q]), self.link[q], self.sample[q])
        self.link[q] = copy
        while p >= 0 and self.next[p].get(c) == q:
            self.next[p][c] = copy
            p = self.link[p]
        return copy

    def _append(self, last: int, c: str, sample: tuple[int, int]) -> int:
        if c in self.next[last]:
            return self._exact(last, c)
        state, p = self._state(self.length[last] + 1, {}, 0, sample), last
        while p >= 0 and c not in self.next[p]:
            self.next[p][c] = state
            p = self.link[p]
        if p >= 0:
            self.link[state] = self._exact(p, c)
        return state

    def text_of(self, state: int) -> str:
        """The longest substring of a state."""
        number, end = self.sample[state]
        return self.texts[number][end - self.length[state]:end]

    def longest_in(self, other: str) -> tuple[int, int]:
        """Length of the longest substring shared with `other`, and where it ends there (the first such place)."""
        state = n = best = end = 0
        for at, c in enumerate(other):
            while state and c not in self.next[state]:
                state = self.link[state]
                n = self.length[state]
            if c in self.next[state]:
                state, n = self.next[state][c], n + 1
                if n > best:
                    best, end = n, at + 1
        return best, end

    def support(self) -> list[int]:
        """In how many of the strings each state's substrings occur."""
        count, seen = [0] * len(self.next), [-1] * len(self.next)
        for number, text in enumerate(self.texts):
            state = 0
            for c in text:
                state = up = self.next[state][c]
                while up > 0 and seen[up] != number:
                    seen[up] = number
                    count[up] += 1
                    up = self.link[up]
        return count

    def maximal(self, least: float) -> list[tuple[str, int]]:
        """Substrings in at least `least` of the strings that no such substring extends, with their support."""
        count = self.support()
        good = [s > 0 and count[s] >= least for s in range(len(self.next))]
        grows = [False] * len(self.next)
        for s in range(1, len(self.next)):
            if good[s]:
                if self.link[s] > 0:
                    grows[self.link[s]] = True
                if any(good[t] for t in self.next[s].values()):
                    grows[s] = True
        return sorted((self.text_of(s), count[s]) for s in range(1, len(self.next)) if good[s] and not grows[s])

    def supported(self, patterns, least: float) -> list[tuple[str, int]]:
        """Those of the given substrings of the strings that at least `least` of the strings hold, with their support."""
        count, out = self.support(), []
        for pattern in patterns:
            state = 0
            for c in pattern:
                state = self.next[state][c]
            if count[state] >= least:
                out.append((pattern, count[state]))
        return sorted(out)

    def frequent(self, least: float) -> list[tuple[str, int]]:
        """All substrings in at least `least` of the strings, with their support."""
        count, out = self.support(), {}
        for s in range(1, len(self.next)):
            if count[s] >= least:
                longest = self.text_of(s)
                for n in range(self.length[self.link[s]] + 1, self.length[s] + 1):
                    out[longest[-n:]] = count[s]
        return sorted(out.items())


def lcs_length(a: str, b: str) -> int:
    return SuffixAutomaton(a).longest_in(b)[0] if a and b else 0


def lcs_string(a: str, b: str) -> str:
    """The longest common substring that comes first in a."""
    if not a or not b:
        return ""
    n, end = SuffixAutomaton(b).longest_in(a)
    return a[end - n:end]
