"""LCS lengths of one text against many at once, in numpy."""

from __future__ import annotations

import numpy as np

from .automaton import SuffixAutomaton

#: Longest text that the table compares; a longer one takes an automaton.
LONGEST = 254
#: Texts that are compared in one step, so that its arrays stay in the processor's cache.
STEP = 2048


class LcsTable:
    """Distinct texts in columns of characters, those of like length together; about a tenth of a microsecond a pair of
    18-character texts, where an automaton takes four."""

    def __init__(self, texts: list[str]):
        order = sorted(range(len(texts)), key=lambda i: len(texts[i]))
        self.n, self.texts = len(texts), texts
        self.steps: list[tuple[np.ndarray, np.ndarray, dict]] = []
        letters = sorted(set("".join(t for t in texts if len(t) <= LONGEST)))
        self.code = {c: i + 1 for i, c in enumerate(letters)}
        short = [i for i in order if 0 < len(texts[i]) <= LONGEST]
        self.long = [(i, texts[i]) for i in order if len(texts[i]) > LONGEST]
        for s in range(0, len(short), STEP):
            part = short[s:s + STEP]
            width = len(texts[part[-1]])
            chars = np.zeros((len(part), width), dtype=np.uint32)
            for row, i in enumerate(part):
                chars[row, :len(texts[i])] = [self.code[c] for c in texts[i]]
            self.steps.append((np.array(part), np.ascontiguousarray(chars.T), {}))

    def _walk(self, text: str, chars: np.ndarray, masks: dict, ends: bool) -> tuple[np.ndarray, np.ndarray | None]:
        width, n = chars.shape
        runs, after = np.zeros((width + 1, n), dtype=np.uint8), np.zeros((width + 1, n), dtype=np.uint8)
        best = np.zeros((width, n), dtype=np.uint8)
        longest, end = np.zeros(n, dtype=np.uint8), np.zeros(n, dtype=np.int32) if ends else None
        for at, c in enumerate(text):
            mask = masks.get(c)
            if mask is None:
                code = self.code.get(c, 0)
                mask = masks[c] = np.where(chars == code, np.uint8(255), np.uint8(0)) if code else np.zeros((width, n), dtype=np.uint8)
            np.add(runs[:-1], 1, out=after[1:])
            np.bitwise_and(after[1:], mask, out=after[1:])
            if ends:
                here = after[1:].max(axis=0)
                longer = here > longest
                end[longer] = at + 1
                np.maximum(longest, here, out=longest)
            else:
                np.maximum(best, after[1:], out=best)
            runs, after = after, runs
        return (longest if ends else best.max(axis=0)), end

    def lengths(self, text: str) -> np.ndarray:
        """LCS length of the text with each of the texts."""
        return self.longest(text, ends=False)[0]

    def longest(self, text: str, ends: bool = True) -> tuple[np.ndarray, np.ndarray]:
        """(lengths, where in `text` the first longest common substring ends)."""
        out, end = np.zeros(self.n, dtype=np.int32), np.zeros(self.n, dtype=np.int32)
        if not text:
            return out, end
        if len(text) <= LONGEST:
            for rows, chars, masks in self.steps:
                n, e = self._walk(text, chars, masks, ends)
                out[rows] = n
                if ends:
                    end[rows] = e
                if len(masks) * chars.size > 64_000_000:
                    masks.clear()
        else:
            own = SuffixAutomaton(text)
            for row, other in enumerate(self.texts):
                if 0 < len(other) <= LONGEST:
                    if ends:
                        out[row], end[row] = SuffixAutomaton(other).longest_in(text)
                    else:
                        out[row] = own.longest_in(other)[0]
        for row, other in self.long:
            out[row], end[row] = _long_automaton(self, row, other).longest_in(text)
        return out, end


def _long_automaton(table: LcsTable, row: int, text: str) -> SuffixAutomaton:
    """Kept while they are few: one takes some hundred bytes a character."""
    kept = table.__dict__.setdefault("automata", {})
    if row not in kept:
        if sum(len(t) for a in kept.values() for t in a.texts) + len(text) > 1_000_000:
            kept.clear()
        kept[row] = SuffixAutomaton(text)
    return kept[row]
