"""Benchmark decontamination with a generalised suffix automaton over words.

The automaton of all items (words lower-cased in A-Z, cut at anything but ASCII letters, digits and non-ASCII) follows a
document's words in one pass and always knows the longest suffix of the words read that occurs in some item. Where that
length reaches the window, the window's words are hit, and the state that stands for the window names its items. Items
shorter than a window count as one window of their own length.

Documents are never shuffled. The automaton is broadcast and has a bounded size: items beyond MAX_WORDS words are dealt
over several automata that the documents pass one after the other, a longer item in pieces that overlap by a window.

Defined edge results: null and empty texts have no words and no hits; items without words never match; repeated items
and repeated documents are treated alike, each document for itself; item ids count once; other columns are passed on, and
the operator's own take a prefix (common.free_prefix gives one that clashes with none).
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import ALNUM_TABLE, alnum_words, as_bytes, free_prefix, small, with_fields

WINDOW = 10
#: Words of benchmark items in one broadcast automaton (about 300 bytes each).
MAX_WORDS = 500_000


class Automaton:
    """Of word sequences: link, length and outgoing words of each state; which items a window-long state belongs to."""

    def __init__(self, items: list[tuple[str, list[bytes]]], window: int):
        self.window = window
        self.words: dict[bytes, int] = {}
        self.next: list[dict[int, int]] = [{}]
        self.link, self.length = [-1], [0]
        self.items: dict[int, set[str]] = {}
        self.short: dict[int, list[tuple[int, str]]] = {}
        items = [(i, w) for i, w in items if w]
        self.least = min((min(window, len(w)) for _, w in items), default=0)
        coded = [(i, [self.words.setdefault(w, len(self.words)) for w in ws]) for i, ws in items]
        for _, seq in coded:
            last = 0
            for c in seq:
                last = self._extend(last, c)
        for name, seq in coded:
            for end, state, _ in self.walk(seq):
                if len(seq) < window:
                    if end == len(seq) - 1:
                        self.short.setdefault(self._holding(state, len(seq)), []).append((len(seq), name))
                elif end >= window - 1:
                    self.items.setdefault(self._holding(state, window), set()).add(name)

    def _new(self, length: int, out: dict[int, int], link: int) -> int:
        self.length.append(length), self.next.append(out), self.link.append(link)
        return len(self.length) - 1

    def _split(self, p: int, c: int) -> int:
        """The state reached from p by c in exactly one more word, cloned off if that state holds longer strings too."""
        q = self.next[p][c]
        if self.length[q] == self.length[p] + 1:
            return q
        clone = self._new(self.length[p] + 1, dict(self.next[q]), self.link[q])
        self.link[q] = clone
        while p >= 0 and self.next[p].get(c) == q:
            self.next[p][c] = clone
            p = self.link[p]
        return clone

    def _extend(self, last: int, c: int) -> int:
        if c in self.next[last]:
            return self._split(last, c)
        state = self._new(self.length[last] + 1, {}, 0)
        p = last
        while p >= 0 and c not in self.next[p]:
            self.next[p][c] = state
            p = self.link[p]
        if p >= 0:
            self.link[state] = self._split(p, c)
        return state

    def _holding(self, state: int, n: int) -> int:
        """The state for the last n words of what `state` has matched."""
        while self.length[self.link[state]] >= n:
            state = self.link[state]
        return state

    def walk(self, seq) -> Iterator[tuple[int, int, int]]:
        """(position, state, matched length) after each word."""
        state = n = 0
        for at, c in enumerate(seq):
            while state and c not in self.next[state]:
                state = self.link[state]
                n = self.length[state]
            if c in self.next[state]:
                state = self.next[state][c]
                n += 1
            yield at, state, n

    def scan(self, words: list[bytes]) -> tuple[list[tuple[int, int]], set[str]]:
        """Merged spans [a, b) of hit words, and the items with occurring windows."""
        spans: list[tuple[int, int]] = []
        found: set[str] = set()
        if not self.least or len(words) < self.least:
            return spans, found
        codes = np.fromiter(map(self.words.get, words, repeat(-1)), np.int64, len(words))
        # only runs of known words that are long enough for the shortest window can match
        edge = np.flatnonzero(np.diff(np.r_[False, codes >= 0, False].astype(np.int8)))
        for a, b in zip(edge[::2].tolist(), edge[1::2].tolist()):
            if b - a < self.least:
                continue
            for at, state, n in self.walk(codes[a:b].tolist()):
                longest = 0
                if n >= self.window:
                    longest = self.window
                    found |= self.items[self._holding(state, self.window)]
                if self.short:
                    up = state
                    while up > 0:
                        for length, name in self.short.get(up, ()):
                            if length <= n:
                                found.add(name)
                                longest = max(longest, length)
                        up = self.link[up]
                if longest:
                    start, end = a + at - longest + 1, a + at + 1
                    while spans and spans[-1][1] >= start:
                        start = min(start, spans.pop()[0])
                    spans.append((start, end))
        return spans, found


def _shards(benchmark: DataFrame, window: int, max_words: int) -> Iterator[Automaton]:
    """Automata of at most max_words words (and a window) each; at least one."""
    given = benchmark.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("i"), F.coalesce("text", F.lit("")).alias("t"))
    held, size = [], 0
    for r in given.toLocalIterator():
        words = alnum_words(r["t"].encode())
        for at in range(0, max(1, len(words) - window + 1), max_words):
            piece = words[at:at + max_words + window - 1]
            if held and size + len(piece) > max_words:
                yield Automaton(held, window)
                held, size = [], 0
            held.append((r["i"], piece))
            size += len(piece)
    yield Automaton(held, window)


def cut_spans(text: bytes, spans: list[tuple[int, int]]) -> bytes:
    """text without the given word spans (from the first byte of the first word to the last byte of the last)."""
    at = [m.span() for m in re.finditer(rb"[^ \t\n\x0b\x0c\r]+", text.translate(ALNUM_TABLE))]
    kept, here = [], 0
    for a, b in spans:
        kept.append(text[here:at[a][0]])
        here = at[b - 1][1]
    return b"".join([*kept, text[here:]])


def scan_documents(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, max_words: int = MAX_WORDS,
                   max_coverage: float = 0.8, least_span: int = 1, clean: bool = True, prefix: str = "") -> DataFrame:
    """docs (doc_id, text, ...) -> the same columns and n_words, n_hit, n_items, items_sha256, contaminated, and with
    `clean`: clean_text (hit spans of least_span words or more removed) and over_coverage (n_hit > max_coverage * n_words);
    the names of the new columns begin with `prefix`."""
    spark = docs.sparkSession
    names = docs.columns
    text_at = names.index("text")
    span = T.StructType().add("a", "integer").add("b", "integer")
    own_prefix = free_prefix(docs, ["spans", "items"])
    between = (f"{own_prefix}spans", f"{own_prefix}items")
    spans_schema = with_fields(docs.schema, **dict(zip(between, (T.ArrayType(span), T.ArrayType(T.StringType())))))
    span_kind = pa.list_(pa.struct([("a", pa.int32()), ("b", pa.int32())]))
    found = dict(zip(["n_words", "n_hit", "n_items", "items_sha256", "contaminated"], [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.bool_()]))
    if clean:
        found |= {"clean_text": pa.string(), "over_coverage": pa.bool_()}
    found = {prefix + name: kind for name, kind in found.items()}
    kinds = ["long", "long", "long", "string", "boolean", "string", "boolean"]
    out_schema = with_fields(docs.schema, **dict(zip(found, kinds)))

    def stage(shared, first: bool, last: bool):
        """One automaton's pass; the first starts without spans, the last makes the result of them."""
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            auto = shared.value
            for b in small(batches):
                texts = as_bytes(b.column(text_at))
                before = [((), ())] * len(b) if first else list(zip(b.column(len(names)).to_pylist(), b.column(len(names) + 1).to_pylist()))
                own = b.columns[:len(names)]
                rows = []
                for text, (old, had) in zip(texts, before):
                    words = alnum_words(text) if text else []
                    spans, items = auto.scan(words)
                    if old:
                        spans = merged(spans + [(x["a"], x["b"]) for x in old])
                    items = sorted(items | set(had))
                    if not last:
                        rows.append(([{"a": x, "b": y} for x, y in spans], items))
                        continue
                    hit = sum(y - x for x, y in spans)
                    row = [len(words), hit, len(items), hashlib.sha256(",".join(items).encode()).hexdigest(), hit > 0]
                    if clean:
                        long = [x for x in spans if x[1] - x[0] >= least_span]
                        row += [(cut_spans(text, long) if long else text or b"").decode("utf-8", "replace") if text is not None else None, hit > max_coverage * len(words)]
                    rows.append(row)
                target = list(found.values()) if last else [span_kind, pa.list_(pa.string())]
                cols = list(zip(*rows)) or [()] * len(target)
                yield pa.RecordBatch.from_arrays([*own, *(pa.array(c, t) for c, t in zip(cols, target))], [*names, *(found if last else between)])

        return run

    work, waiting, first = docs, None, True
    for automaton in _shards(benchmark, window, max_words):
        if waiting is not None:
            work, first = work.mapInArrow(stage(waiting, first, False), spans_schema), False
        waiting = spark.sparkContext.broadcast(automaton)
    return work.mapInArrow(stage(waiting, first, True), out_schema)


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and out[-1][1] >= a:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out
