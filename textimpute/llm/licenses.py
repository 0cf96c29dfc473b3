"""License scans with a positional rare-token index over licence templates.

Words are lower-cased runs of ASCII letters, digits and non-ASCII characters. From all documents the document frequency of
every template word is counted (the vocabulary is that of the templates, so it is bounded). Each template has postings (template,
position) of its rarest places, so many of them that an alignment of enough score has two at least among them, however
frequent they are, and all of them are looked up wherever they stand in a text: postings that agree on the relative position vote for an alignment. An alignment with two votes counts if every mandatory
phrase of the template stands near its place; its score is the share of the template's words found at their aligned places.
Besides, the base phrases are looked for everywhere in the text.

Defined edge results: null and empty texts have no words, no labels and score 0; ties between alignments are settled by
score, then by template order; every place is examined, however long the text; repeated documents get the same labels; of
the documents' columns only text is read, and the operator's own take a prefix (common.free_prefix gives one that clashes
with none).
"""

from __future__ import annotations

from collections import Counter, defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import alnum_words, as_bytes, small, with_fields

#: Base phrases and their labels.
BASE = (("mit license", "mit"), ("apache license", "apache"), ("general public license", "gpl"))

#: Label, template text, mandatory phrases.
TEMPLATES = (
    ("mit-license", "Released under the MIT License", ("mit license",)),
    ("mit-license", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction", ("permission is hereby granted", "without restriction")),
    ("apache-2.0", "Licensed under the Apache License, Version 2.0", ("apache license", "version 2 0")),
    ("gpl-3.0", "This work is licensed under the GNU General Public License, version 3", ("gnu general public license", "version 3")),
    ("gpl-2.0", "This work is licensed under the GNU General Public License, version 2", ("gnu general public license", "version 2")),
    ("lgpl", "This library is licensed under the GNU Lesser General Public License", ("lesser general public license",)),
    ("agpl-3.0", "Licensed under the GNU Affero General Public License, version 3", ("affero general public license",)),
    ("cc-by-nc-4.0", "Licensed under CC BY-NC 4.0", ("cc by nc",)),
    ("cc-by-nc-4.0", "Creative Commons Attribution-NonCommercial 4.0 International", ("attribution noncommercial",)),
    ("cc-by-sa-4.0", "Licensed under CC BY-SA 4.0", ("cc by sa",)),
    ("cc-by-4.0", "Licensed under CC BY 4.0", ("cc by 4 0",)),
    ("cc0-1.0", "CC0 1.0 Universal Public Domain Dedication", ("cc0 1 0",)),
    ("bsd", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met", ("redistribution and use in source and binary forms",)),
    ("mpl-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0", ("mozilla public license",)),
    ("isc", "Permission to use, copy, modify, and or distribute this software for any purpose with or without fee is hereby granted", ("permission to use copy modify",)),
    ("mit-license", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.", ("permission is hereby granted", "substantial portions of the software")),
    ("apache-2.0", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.", ("apache license", "except in compliance with the license")),
    ("gpl-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.", ("gnu general public license", "either version 3")),
    ("gpl-2.0", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version.", ("gnu general public license", "either version 2")),
    ("lgpl", "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version.", ("gnu lesser general public license",)),
    ("agpl-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.", ("gnu affero general public license",)),
    ("bsd", "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.", ("redistributions of source code must retain", "redistributions in binary form must reproduce")),
    ("zlib", "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions", ("without any express or implied warranty", "including commercial applications")),
    ("bsl-1.0", "Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license", ("person or organization obtaining a copy",)),
    ("epl-2.0", "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0", ("eclipse public license 2 0",)),
    ("unlicense", "Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means", ("anyone is free to copy modify publish",)),
    ("unlicense", "This is free and unencumbered software released into the public domain", ("free and unencumbered software",)),
)
#: Share of a template's words that have to stand at their aligned places.
LEAST_SCORE = 0.6


@dataclass
class Index:
    labels: list[str]
    texts: list[list[bytes]]
    phrases: list[list[list[bytes]]]
    postings: dict[bytes, list[tuple[int, int]]] = field(default_factory=dict)
    votes: list[int] = field(default_factory=list)
    mandatory: list[set[bytes]] = field(default_factory=list)

    @classmethod
    def of(cls, templates) -> Index:
        cut = lambda s: alnum_words(s.encode())
        return cls([t[0] for t in templates], [cut(t[1]) for t in templates], [[cut(p) for p in t[2]] for t in templates])

    def weighed(self, frequency: dict[bytes, int]) -> Index:
        """Keeps postings of each template's rarest places: as many as the score lets miss, and two (the votes)."""
        postings = defaultdict(list)
        self.votes, self.mandatory = [], [{w for p in phrases for w in p} for phrases in self.phrases]
        for t, words in enumerate(self.texts):
            hits = next(n for n in range(len(words) + 1) if n / len(words) >= LEAST_SCORE)
            rarest = sorted(range(len(words)), key=lambda p: (frequency.get(words[p], 0), words[p], p))
            for p in rarest[:len(words) - hits + 2]:
                postings[words[p]].append((t, p))
            self.votes.append(min(2, hits))
        self.postings = dict(postings)
        return self

    def scan(self, words: list[bytes], slack: int = 3) -> tuple[set[str], float]:
        """Labels of accepted alignments and the best score."""
        present = set(words)
        labels, best = set(), 0.0
        # a template can only count where all words of its mandatory phrases stand
        open_ = {t for t, m in enumerate(self.mandatory) if m <= present}
        if not open_:
            return labels, best
        postings = {w: near for w in self.postings.keys() & present if (near := [x for x in self.postings[w] if x[0] in open_])}
        votes: Counter[tuple[int, int]] = Counter()
        for at, w in enumerate(words):
            if w in postings:
                for t, p in postings[w]:
                    votes[t, at - p] += 1
        for (t, offset), n in sorted(votes.items()):
            if n < self.votes[t]:
                continue
            template = self.texts[t]
            lo, hi = max(0, offset - slack), offset + len(template) + slack
            near = words[lo:hi]
            if not all(places(near, p) for p in self.phrases[t]):
                continue
            score = sum(0 <= offset + k < len(words) and words[offset + k] == w for k, w in enumerate(template)) / len(template)
            if score >= LEAST_SCORE:
                labels.add(self.labels[t])
                best = max(best, score)
        return labels, best


def places(words: list[bytes], phrase: list[bytes]) -> list[int]:
    """Starts of all places where the phrase's words stand one after the other."""
    out, at, n = [], -1, len(phrase)
    while True:
        try:
            at = words.index(phrase[0], at + 1)
        except ValueError:
            return out
        if words[at:at + n] == phrase:
            out.append(at)


def frequencies(docs: DataFrame, vocabulary: set[bytes]) -> dict[bytes, int]:
    """In how many of all documents each word of the vocabulary stands."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = Counter()
        for b in small(batches):
            for text in as_bytes(b.column(0)):
                if text:
                    seen.update(vocabulary.intersection(alnum_words(text)))
        yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.binary()), pa.array(list(seen.values()), pa.int64())], ["word", "n"])

    rows = docs.select("text").mapInArrow(run, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n")).collect()
    return {bytes(r["word"]): r["n"] for r in rows}


def scanned(docs: DataFrame, templates=TEMPLATES, base=BASE, prefix: str = "") -> DataFrame:
    """docs (text, ...) and n_words, n_base, first_word, last_word, base_labels, labels, score, named with the prefix."""
    index = Index.of(templates)
    index.weighed(frequencies(docs, {w for t in index.texts for w in t}))
    shared = docs.sparkSession.sparkContext.broadcast(index)
    place = docs.columns.index("text")
    phrases = [(alnum_words(p.encode()), label) for p, label in base]
    # a phrase is looked for by its last word; texts without any of these words need no search
    lasts = {p[-1] for p, _ in phrases}
    names = [prefix + n for n in ("n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score")]
    kinds = ["long"] * 4 + ["string", "string", "double"]
    arrow = [pa.int64()] * 4 + [pa.string(), pa.string(), pa.float64()]
    schema = with_fields(docs.schema, **dict(zip(names, kinds)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ix = shared.value
        for b in small(batches):
            rows = []
            for text in as_bytes(b.column(place)):
                words = alnum_words(text) if text else []
                found, hits = set(), []
                if not lasts.isdisjoint(words):
                    for phrase, label in phrases:
                        if at := places(words, phrase):
                            found.add(label)
                            hits += at
                more, score = ix.scan(words)
                rows.append((len(words), len(hits), min(hits, default=None), max(hits, default=None), ",".join(sorted(found)), ",".join(sorted(found | more)), score))
            cols = list(zip(*rows)) or [()] * len(names)
            yield pa.RecordBatch.from_arrays([*b.columns, *(pa.array(c, t) for c, t in zip(cols, arrow))], schema.names)

    return docs.mapInArrow(run, schema)
