"""Each operator against a plain version of it, and on nulls, empty and long texts, ties, repeats and empty tables."""

import gzip
import hashlib
import math
import random
import re
import struct
import urllib.parse
import zlib
from collections import Counter

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from textimpute.llm import chat, decontam, langid, licenses, lm, packing, quality, simhash, urlfilter, warc
from textimpute.llm.common import alnum_words, read_table, written
from textimpute.llm.components import connected_components

DOC = "doc_id long, text string, lang string, source string, n_chars long"


def docs_of(spark, rows, extra=False):
    df = spark.createDataFrame([(i, t, "en", "s", None if t is None else len(t)) for i, t in rows], DOC)
    # columns whose names an operator might use itself
    return df.withColumns({"score": F.lit(1.5), "key": F.lit("k"), "count": F.lit(2), "kept": F.lit("x")}) if extra else df


def speak(rng, n, stem=""):
    syllables = ["ba", "ke", "lo", "mi", "nu", "ra", "se", "ti", "vo", "zu"]
    return " ".join(stem + "".join(rng.choice(syllables) for _ in range(rng.randint(1, 4))) for _ in range(n))


ODD = [(1, None), (2, ""), (3, " \n\t "), (4, "word"), (5, "é日本 — ✓ 😀"), (6, "a b c d e f " * 3000), (7, "word"), (7, "word"), (None, "no id at all here")]


# ---------------------------------------------------------------- chat
def test_chat_round_trip_and_masks(spark):
    nasty = ["", None, "\\", "<|", "<\\|", "\\<|im_end|>", "<|im_end|><|im_start|>assistant ok", "a\nb", "<<||", "é😀", "\\n", "x" * 5000]
    rows = []
    rng = random.Random(1)
    for c in range(40):
        for t in range(rng.randint(1, 6)):
            rows.append((c, t, rng.choice(["user", "assistant", "system", None, "odd\nrole", "\\n<|x"]), rng.choice(nasty)))
    rows += [(90, 1, "user", "tie"), (90, 1, "user", "tie"), (90, 1, "assistant", "b"), (None, 0, "assistant", "no id"), (91, None, "user", "null turn"), (91, 0, "assistant", "x")]
    df = spark.createDataFrame(rows, "conv_id long, turn int, role string, text string").withColumn("example", F.lit("clash"))
    got = {r["conv_id"]: r for r in chat.read_back(chat.examples(df)).collect()}
    for c in {r[0] for r in rows}:
        turns = sorted(((-1 if r[1] is None else r[1], r[2] or "", r[3] or "") for r in rows if r[0] == c), key=lambda x: (x[0], x[1].encode(), x[2].encode()))
        said = "".join(f"{r}\n{t}\n" for _, r, t in turns)
        loss = "".join(t for _, r, t in turns if r == "assistant")
        assert got[c]["n_turns"] == len(turns)
        assert got[c]["turns_sha256"] == hashlib.sha256(said.encode()).hexdigest()
        assert (got[c]["loss_chars"], got[c]["loss_sha256"]) == (len(loss), hashlib.sha256(loss.encode()).hexdigest())
    examples = chat.examples(df.filter("conv_id = 90")).orderBy("example").collect()
    assert examples[0]["text"].endswith("<|im_end|>\n") and examples[0]["loss_chars"] == 1
    assert chat.read_back(chat.examples(df.limit(0))).count() == 0


def test_only_the_reply_is_trainable(spark):
    df = spark.createDataFrame([(1, 0, "user", "hi"), (1, 1, "assistant", "yo <|x|>"), (1, 2, "user", "more"), (1, 3, "assistant", "end"), (1, 4, "user", "bye")], "conv_id long, turn int, role string, text string")
    rows = chat.examples(df).orderBy("example").collect()
    assert [r["loss_chars"] for r in rows] == [len("yo <\\|x|>"), 3, None]
    assert [r["text"][r["loss_start"]:r["loss_start"] + r["loss_chars"]] for r in rows[:2]] == ["yo <\\|x|>", "end"]
    assert rows[1]["text"].startswith(rows[0]["text"]) and rows[2]["is_last"]


# ---------------------------------------------------------------- language ID
def test_language_accuracy_on_held_out_rows(spark, sf):
    docs = read_table(spark, sf, "documents")
    model = langid.fit(langid.learning_rows(docs))
    rows = langid.predicted(docs.select("doc_id", "text", "lang"), model).collect()
    held = [r for r in rows if zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2]
    assert np.mean([r["lang"] == r["lang_pred"] for r in held]) > 0.95
    assert all(0 <= r["score"] <= 1 for r in rows) and np.mean([r["rejected"] for r in rows]) < 0.05


def test_language_edges(spark):
    rng = random.Random(2)
    rows = [(i, speak(rng, 40, "x" if i % 2 else "q"), "xx" if i % 2 else "qq", "s", 1) for i in range(200)]
    model = langid.fit(spark.createDataFrame(rows, DOC))
    got = langid.predicted(docs_of(spark, [*ODD, (9, "12 34 !?")]), model).collect()
    assert [(r["lang_pred"], r["score"]) for r in got if r["text"] is None or not any(c.isalpha() for c in r["text"])] == [("und", 0.0)] * 4
    assert all(r["lang_pred"] in ("xx", "qq") for r in got if r["text"] and any(c.isalpha() for c in r["text"]))
    nothing = langid.fit(spark.createDataFrame([], DOC))
    assert {r["lang_pred"] for r in langid.predicted(docs_of(spark, ODD), nothing).collect()} == {"und"}
    assert langid.predicted(docs_of(spark, ODD).limit(0), model).count() == 0


def test_language_learns_where_a_passage_is_common_to_all_languages(spark):
    rng = random.Random(4)
    line = speak(rng, 6)
    rows = [(k, " ".join([line] * 5) + " " + speak(rng, 3, stem="qxwz"[k % 4]), f"l{k % 4}") for k in range(800)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = langid.fit(docs)
    got = langid.predicted(docs, model).collect()
    assert np.isfinite(model.table).all() and math.isfinite(model.threshold)
    assert all(0 <= r["score"] <= 1 for r in got)
    assert sum(r["lang_pred"] == r["lang"] for r in got) > 0.95 * len(got)


# ---------------------------------------------------------------- packing
def test_encoder_equals_the_tokenizer_file():
    e = packing.Encoder()
    for x in ["", " a b", "  ", "a  b", "a \n b", "\n x", "x\n y é", "日本 語", "<|endoftext|> a", "it's o'clock 12 3", "a b", "tab\there", "x ", "Ünïcode wörds", "😀"]:
        ids = e.full.encode(x, add_special_tokens=False).ids
        assert e.encode(x) == struct.pack(f"<{len(ids)}I", *ids)


def test_packing_is_a_gapless_partition(spark):
    rng = random.Random(3)
    rows = [(i + 1000, speak(rng, rng.choice([1, 5, 60, 200, 900]))) for i in range(300)]
    df = docs_of(spark, rows + ODD, extra=True)
    out = packing.packed(df.select("doc_id", "text"), keep_ids=True).collect()
    e = packing.Encoder()
    whole = Counter((i, (e.encode(t or "") + struct.pack("<I", 2))) for i, t in rows + ODD)
    by_doc = {}
    for r in out:
        assert 1 <= r["length"] <= 1024 and zlib.crc32(r["ids"]) == r["ids_crc32"] and len(r["ids"]) == 4 * r["length"]
        by_doc.setdefault(r["doc_id"], []).append(r)
    unique = {i: t for (i, t), n in whole.items() if n == 1}
    for i, data in unique.items():
        parts = sorted(by_doc[i], key=lambda r: r["piece"])
        assert b"".join(p["ids"] for p in parts) == data and all(p["length"] == 1024 for p in parts[1:])
        assert [p["start"] for p in parts] == list(np.cumsum([0, *(p["length"] for p in parts[:-1])]))
    bins = {}
    for r in out:
        bins.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for places in bins.values():
        at = 0
        for offset, length in sorted(places):
            assert offset == at
            at += length
        assert at <= 1024
    total = sum(r["length"] for r in out)
    assert len(bins) <= -(-total // 1024) * 1.02 + 1
    assert packing.packed(df.limit(0).select("doc_id", "text")).count() == 0


def test_bin_completion_beats_or_equals_best_fit():
    def optimum(sizes, capacity):
        """Branch and bound over single items, for a few of them."""
        best = len(sizes)

        def place(k, rooms):
            nonlocal best
            if len(rooms) >= best:
                return
            if k == len(sizes):
                best = len(rooms)
                return
            for j in {r: j for j, r in enumerate(rooms)}.values():
                if rooms[j] >= sizes[k]:
                    place(k + 1, [r - sizes[k] if i == j else r for i, r in enumerate(rooms)])
            place(k + 1, [*rooms, capacity - sizes[k]])

        place(0, [])
        return best

    for seed in range(12):
        rng = random.Random(seed)
        sizes = sorted((rng.randint(10, 70) for _ in range(11)), reverse=True)
        counts = dict(Counter(sizes))
        found = packing.bin_completion(counts, 100)
        used = Counter()
        for fill, times in found:
            assert sum(s * n for s, n in fill.items()) <= 100
            for s, n in fill.items():
                used[s] += n * times
        assert used == Counter(sizes)
        n = sum(t for _, t in found)
        assert n <= sum(t for _, t in packing.best_fit_decreasing(counts, 100)) and n == optimum(sizes, 100)
    with pytest.raises(ValueError):
        packing.bin_completion({101: 1}, 100)


# ---------------------------------------------------------------- WARC
def test_warc_round_trip(spark):
    same = "<p>" + "same " * 400
    rows = [(1, "http://a/x", same), (2, "http://b/é y\r\nz", same), (3, None, None), (4, "http://c", ""), (5, "u", "short"), (6, "u", "short"), (7, "http://d", "é" * 3000), (2, "again", "other" * 300), (None, "n", same)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("keeper", F.lit(1))
    for split in (200, 1 << 20):
        archives = warc.write_archives(warc.duplicates(pages.select("page_id", "url", "html")), archive_bytes=600)
        got = warc.read_archives(spark, archives, split_bytes=split).collect()
        assert len(got) == len(rows)
        kinds = {(r["page_id"], r["payload_bytes"]): (r["record_type"], r["refers_to"]) for r in got}
        n = len(same)
        assert kinds[1, n] == ("revisit", 2) and kinds[2, n] == ("response", None) and kinds[None, n] == ("revisit", 2)
        assert kinds[5, 5] == kinds[6, 5] == ("response", None) and kinds[3, 0] == ("response", None)
        want = Counter((i, hashlib.sha1((h or "").encode()).hexdigest()) for i, _, h in rows)
        assert Counter((r["page_id"], r["payload_digest"]) for r in got) == want
        assert {r["payload"] for r in got if r["page_id"] == 7} == {("é" * 3000).encode()}
    assert warc.read_archives(spark, warc.write_archives(warc.duplicates(pages.select("page_id", "url", "html").limit(0)))).count() == 0


def test_warc_ranges_own_each_record_once_and_skip_damage(tmp_path):
    rng = random.Random(4)
    members = [warc.member(i, f"http://x/{i}", bytes(rng.randrange(32, 127) for _ in range(rng.choice([0, 10, 3000]))), None) for i in range(60)]
    broken = bytearray(members[20])
    broken[len(broken) // 2] ^= 255
    data = b"".join([*members[:20], bytes(broken), b"\x1f\x8b\x08noise", *members[21:]])
    path = tmp_path / "a.warc.gz"
    path.write_bytes(data)
    from pyarrow import fs

    for split in (37, 500, 5000, 1 << 20):
        ids = []
        with fs.LocalFileSystem().open_input_file(str(path)) as f:
            for start in range(0, len(data), split):
                ids += [int(h["X-Page-Id"]) for _, h, _ in warc.RangeReader(f, len(data)).records(start, min(len(data), start + split))]
        assert ids == [i for i in range(60) if i != 20]
    assert gzip.decompress(members[0]).startswith(b"WARC/1.1\r\n")


def test_warc_headers_of_any_length_and_record_count(spark):
    rng = random.Random(5)
    long = "".join(chr(rng.randrange(0x4E00, 0x9FFF)) for _ in range(30_000))
    rows = [(1, "http://a/1", "one"), (2, f"http://b/{long}", "two"), (3, "http://c/?" + "x" * 300_000, "three"), (4, "http://d", None)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").coalesce(1)
    archives = warc.write_archives(warc.duplicates(pages))
    for split in (1000, 1 << 20):
        got = warc.complete(warc.read_archives(spark, archives, split_bytes=split), archives).collect()
        assert sorted((r["page_id"], r["payload"]) for r in got) == [(1, b"one"), (2, b"two"), (3, b"three"), (4, b"")]
        assert [r["url"] for r in got if r["page_id"] == 3] == [rows[2][1]]
    with pytest.raises(RuntimeError):
        warc.complete(warc.read_archives(spark, archives).filter("page_id <> 2"), archives)


# ---------------------------------------------------------------- quality
def test_base_counts_against_plain_version():
    rng = random.Random(5)
    for n in (0, 1, 3, 10, 200):
        text = "\n".join(" ".join(rng.choice(["a", "b", "c#", "é$", "<d>"]) for _ in range(rng.randint(0, 6))) for _ in range(n))
        words = text.split()
        windows = Counter(tuple(words[i:i + 3]) for i in range(len(words) - 2))
        hit = {i + k for i in range(len(words) - 2) if windows[tuple(words[i:i + 3])] > 1 for k in range(3)}
        lines = [x for x in text.split("\n") if x.strip(" \t\n\x0b\x0c\r")]
        assert quality.base_counts(text.encode()) == (len(words), sum(map(len, words)), sum(text.count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(hit))


def test_quality_verdicts(spark, sf):
    docs, labels = read_table(spark, sf, "documents"), read_table(spark, sf, "labels")
    rows = quality.judged(docs, quality.fit(docs, labels)).join(labels, "doc_id").collect()
    sound = [r for r in rows if not r["base_failed"]]
    good, bad = ([r["kept"] for r in sound if r["quality"] == q] for q in (1, 0))
    assert np.mean(good) == 1.0 and np.mean(bad) < 0.5
    odd = quality.judged(docs_of(spark, ODD), quality.fit(docs, labels)).collect()
    assert [r["n_words"] for r in odd if r["text"] is None] == [0] and not any(r["kept"] for r in odd)
    assert quality.fit(docs.limit(0), labels) is None
    assert quality.judged(docs, None).filter("kept = base_failed").count() == 0


# ---------------------------------------------------------------- decontamination
def test_automaton_against_brute_force(spark):
    rng = random.Random(6)
    vocabulary = ["a", "b", "c", "dd"]
    items = [(i, " ".join(rng.choice(vocabulary) for _ in range(rng.choice([0, 2, 4, 5, 9])))) for i in range(14)]
    documents = [(i, " ".join(rng.choice([*vocabulary, "zz"]) for _ in range(rng.randint(0, 60)))) for i in range(60)] + ODD
    bench = spark.createDataFrame([*items, (99, None), (3, items[3][1])], "item_id long, text string")
    for most in (500_000, 4):  # one automaton, and many
        got = decontam.scan_documents(docs_of(spark, documents), bench, window=4, max_words=most).collect()
        for r in got:
            words = alnum_words((r["text"] or "").encode())
            hit, found = set(), set()
            for i, t in items:
                w = alnum_words(t.encode())
                size = min(4, len(w))
                for k in range(len(w) - size + 1 if w else 0):
                    for at in range(len(words) - size + 1):
                        if words[at:at + size] == w[k:k + size]:
                            hit |= set(range(at, at + size))
                            found.add(str(i))
            assert (r["n_words"], r["n_hit"], r["n_items"], r["contaminated"]) == (len(words), len(hit), len(found), bool(hit))
            assert r["items_sha256"] == hashlib.sha256(",".join(sorted(found)).encode()).hexdigest()
            left = alnum_words((r["clean_text"] or "").encode())
            assert len(left) == len(words) - len(hit)
    assert decontam.scan_documents(docs_of(spark, documents), bench.limit(0)).filter("contaminated").count() == 0


# ---------------------------------------------------------------- licences
def test_license_labels(spark):
    filler = speak(random.Random(7), 300)
    rows = [(1, f"{filler} Released under the MIT License. {filler}"), (2, "mit-license MIT license the apache\nlicense"), (3, f"{filler} Licensed under CC BY-NC 4.0."),
            (4, "GNU General Public License, version 3: This work is licensed under the GNU General Public License, version 3."), (5, "a mitlicense, not the MIT's license"), *[(i + 10, t) for i, t in ODD if i]]
    rows += [(100 + k, speak(random.Random(k), 50)) for k in range(40)]
    got = {r["doc_id"]: r for r in licenses.scanned(docs_of(spark, rows).select("doc_id", "text")).collect()}
    assert (got[1]["n_base"], got[1]["first_word"], got[1]["base_labels"], got[1]["labels"]) == (1, 303, "mit", "mit,mit-license")
    assert (got[2]["n_base"], got[2]["first_word"], got[2]["last_word"], got[2]["base_labels"]) == (3, 0, 5, "apache,mit")
    assert got[3]["labels"] == "cc-by-nc-4.0" and got[3]["score"] == 1.0 and got[3]["base_labels"] == ""
    assert got[4]["n_base"] == 2 and got[4]["labels"] == "gpl,gpl-3.0"
    assert got[5]["n_base"] == 0 and got[5]["first_word"] is None
    assert got[11]["n_words"] == 0 and got[11]["score"] == 0


def test_license_lines_beside_a_long_notice(spark):
    texts = {label: [t[1] for t in licenses.TEMPLATES if t[0] == label][-1] for label in ("mit-license", "bsd", "isc", "cc-by-nc-4.0", "gpl-3.0", "apache-2.0")}
    texts["cc-by-nc-4.0"] = "Licensed under CC BY-NC 4.0."
    pairs = [(a, b) for a in ("mit-license", "bsd", "isc") for b in ("cc-by-nc-4.0", "gpl-3.0", "apache-2.0")]
    rows = [(k, f"{texts[a]}. {speak(random.Random(k), 30)} {texts[b]}") for k, (a, b) in enumerate(pairs)]
    # the short lines stand in further documents, so that their words are less rare than those of the notices
    rows += [(50 + k, texts[("cc-by-nc-4.0", "gpl-3.0", "apache-2.0")[k % 3]]) for k in range(15)]
    rows += [(100 + k, speak(random.Random(k), 50)) for k in range(400)]
    got = {r["doc_id"]: r for r in licenses.scanned(docs_of(spark, rows).select("doc_id", "text")).collect()}
    for k, pair in enumerate(pairs):
        assert set(pair) <= set(got[k]["labels"].split(",")), pair
    assert not any(got[100 + k]["labels"] for k in range(400))


def test_license_lines_that_a_third_of_the_documents_carry(spark):
    lines = ["Licensed under CC BY 4.0.", "Released under the MIT License."]
    rows = [(k, speak(random.Random(k), 40) + (f" {lines[k // 3 % 2]} " if not k % 3 else " ") + speak(random.Random(-k), 20)) for k in range(90)]
    got = {r["doc_id"]: r for r in licenses.scanned(docs_of(spark, rows).select("doc_id", "text")).collect()}
    assert all(got[k]["labels"] == (("cc-by-4.0", "mit,mit-license")[k // 3 % 2] if not k % 3 else "") for k in range(90))


# ---------------------------------------------------------------- language model
def test_scores_against_plain_counts(spark):
    rng = random.Random(8)
    rows = [(i, speak(rng, rng.randint(0, 50))) for i in range(300)] + ODD
    got = lm.scored(docs_of(spark, rows).select("doc_id", "text"), hot=20).collect()
    counts, out = Counter(), lambda i: zlib.crc32(str(i).encode()) % 10 == 0
    for i, t in rows:
        if i is not None and not out(i):
            counts.update(lm.tokens((t or "").encode()))
    n, v = sum(counts.values()), len(counts)
    want = Counter()
    for i, t in rows:
        ts = lm.tokens((t or "").encode())
        want[i, i is not None and out(i), len(ts), sum(w in counts for w in ts), n, round(sum(np.log10((counts[w] + 0.1) / (n + 0.1 * (v + 1))) for w in ts), 6)] += 1
    assert Counter((r["doc_id"], r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"], round(r["base_score"], 6)) for r in got) == want
    assert all(r["score"] < 0 for r in got)


def test_scores_against_a_plain_walk_and_alike_for_every_broadcast_bound(spark, monkeypatch):
    rng = random.Random(9)
    texts = [(i, speak(rng, rng.randint(0, 60))) for i in range(250)] + ODD
    monkeypatch.setattr(lm, "train_units", lambda *a, f=lm.train_units: f(*a, steps=300))
    monkeypatch.setattr(lm, "train", lambda *a, f=lm.train: f(*a, steps=200))
    docs = docs_of(spark, texts).select("doc_id", "text")
    by_bound = [sorted((str(r["doc_id"]), r["n_tokens"], r["n_known"], round(r["base_score"], 6), round(r["score"], 6)) for r in lm.scored(docs, hot=h).collect()) for h in (1, 40, 100_000)]
    assert by_bound[0] == by_bound[1] == by_bound[2]

    kept = [t for i, t in texts if i is not None and zlib.crc32(str(i).encode()) % 10]
    walk = lambda t: [*(t or "").lower().encode().split(), b""]
    counts = Counter(w for t in kept for w in walk(t))
    own = {w: 1 + k for k, (_, w) in enumerate(sorted((-n, w) for w, n in counts.items() if w)[:lm.OWN])}
    unit_of = lambda w: 0 if not w else own.get(w) or lm.TAIL + zlib.crc32(w[-3:]) % 64
    class_of = lambda w: 0 if not w else own[w] if own.get(w, 99) <= lm.SINGLE else 32 + zlib.crc32(w[-3:]) % 32
    trigrams, pairs, classes = np.zeros((64,) * 3, np.int64), np.zeros((1024,) * 2, np.int64), np.zeros(1024, np.int64)
    for u in range(lm.TAIL, 1024):
        classes[u] = 32 + (u - lm.TAIL) % 32
    for w, u in own.items():
        classes[u] = class_of(w)
    for t in kept:
        older = near = before = 0
        for w in walk(t):
            trigrams[older, near, class_of(w)] += 1
            pairs[before, unit_of(w)] += 1
            older, near, before = near, class_of(w), unit_of(w)
    table, units = lm.train(trigrams), lm.train_units(pairs, classes)
    assert np.allclose((10.0**table).sum(-1), 1)
    for c in set(classes.tolist()):
        assert np.allclose((10.0**units[:, classes == c]).sum(1), 1)
    total, distinct = Counter(), Counter()
    for w, n in counts.items():
        total[unit_of(w)] += n
        distinct[unit_of(w)] += 1
    want = []
    for i, t in texts:
        older = near = before = 0
        score = 0.0
        for w in walk(t):
            u = unit_of(w)
            score += table[older, near, class_of(w)] + units[before, u]
            if u >= lm.TAIL:
                score += math.log10((counts[w] + 0.1) / (total[u] + 0.1 * (distinct[u] + 1)))
            older, near, before = near, class_of(w), u
        want.append((str(i), score))
    for (i, score), (j, *_, got) in zip(sorted(want), sorted((x[0], x[-1]) for x in by_bound[0])):
        assert i == j and abs(score - got) < 1e-3 * max(1, abs(score) / 100)


def test_model_is_normalised_and_better_than_unigrams():
    rng = np.random.default_rng(1)
    c = lm.CLASSES
    follow = rng.dirichlet(np.full(c, 0.05), c)  # each class has a few likely successors
    trigrams = np.zeros((c, c, c), np.int64)
    a = b = 0
    for _ in range(60_000):
        w = rng.choice(c, p=follow[b])
        trigrams[a, b, w] += 1
        a, b = b, w
    table = lm.train(trigrams)
    assert np.allclose((10**table).sum(-1), 1)
    unigram = np.log10((trigrams.sum((0, 1)) + 0.1) / (trigrams.sum() + 0.1 * c))
    assert (table * trigrams).sum() > (unigram * trigrams).sum() * 0.9


# ---------------------------------------------------------------- urls
def test_rules_and_aliases(spark):
    link = '<html><link href="{}" rel="canonical">'
    refresh = "<meta http-equiv=refresh content='0; url={}'>"
    rows = [(1, "http://X.example.org/es/1", ""), (2, "http://q.net/a", link.format("http://x.example.org/es/1")), (3, "http://q.net/b", refresh.format("/a")),
            (4, "https://ok.org/", None), (5, "http://r.net/1", link.format("https://ok.org/")), (6, "http://r.net/2", link.format("http://r.net/1") + link.format("http://x.example.org/es/9")),
            (7, None, "x"), (8, "no scheme", "y"), (9, "http://a.com/de/1?x=/fr/", ""), (10, "http://a.com/fr/", link.format("http://b.com/de/")), (11, "http://example.org/en/12", ""), (12, "http://q.net/a", "")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumns({"node": F.lit(1), "component": F.lit(2), "u": F.lit(3)})
    got = {r["page_id"]: r for r in urlfilter.judge(pages.select("page_id", "url", "html")).collect()}
    assert (got[1]["host"], got[1]["path"], got[1]["rule"], got[1]["verdict"]) == ("x.example.org", "/es/1", "example.org/es/", "block")
    assert got[2]["verdict"] == got[3]["verdict"] == got[12]["verdict"] == "block" and got[2]["rule"] is None
    assert got[4]["rule"] == "org/" and got[5]["verdict"] == got[6]["verdict"] == "allow"  # allow outranks the block it also meets
    assert (got[7]["host"], got[7]["path"], got[7]["verdict"]) == ("", "", "allow") and got[8]["host"] == ""
    assert got[9]["rule"] == "com/de/" and got[10]["verdict"] == "allow" and got[11]["rule"] == "example.org/en/1"
    assert urlfilter.judge(pages.limit(0).select("page_id", "url", "html")).count() == 0


def test_components_of_paths_stars_and_cycles(spark):
    rng = random.Random(9)
    edges = [(i, i + 1) for i in range(300)] + [(1000, 1000 + i) for i in range(1, 200)] + [(rng.randrange(2000, 2200), rng.randrange(2000, 2200)) for _ in range(150)] + [(5, 5), (None, 3)]
    parent = {}

    def find(x):
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    for a, b in edges:
        if a is not None and a != b:
            x, y = find(a), find(b)
            parent[max(x, y)] = min(x, y)
    got = {r["node"]: r["component"] for r in connected_components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert got == {x: find(x) for x in parent}


def test_aliases_against_a_plain_search(spark):
    """Random pages with every kind of link target, against urllib's resolution and a search of the link graph."""
    rng = random.Random(31)
    hosts = ["a.example.org", "b.com", "c.net", "d.io", "shop.e.com"]
    urls = [f"http://{rng.choice(hosts)}{rng.choice(['', '/', '/es/x', '/en/1', '/fr/', '/de/q/z.html', '/p/q/r', '/p/q/'])}" for _ in range(60)]
    kinds = ["c.html", "../x", "./y", "?id=3&amp;k=1", "//c.net/p/q/r", "/de/q/z.html", "http://B.com/fr/", "#top", "", "mailto:me@b.com", "../../../up/", "z/../w/."]
    rows = []
    for k, u in enumerate(urls):
        t = rng.choice([*kinds, *urls, *urls])
        tag = rng.choice([f'<link rel="canonical" href="{t}">', f"<META http-equiv=refresh content='0; url={t}'>", "", None])
        rows.append((k, u, tag))
    got = {r["page_id"]: r["verdict"] for r in urlfilter.judge(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}

    def key(u):
        p = urllib.parse.urlsplit(u)
        return (p.netloc.lower() + (p.path or "/") + (f"?{p.query}" if p.query else "")) if p.netloc else None

    def rule(k):
        host, _, path = k.partition("/")
        path = "/" + path.split("?")[0]
        fit = [(len(h) + len(q), a) for a, h, q in urlfilter.RULES if (host == h or host.endswith("." + h)) and path.startswith(q)]
        return max(fit)[1] if fit else None

    parent = {}

    def find(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for _, u, tag in rows:
        find(key(u))
        if tag:
            t = re.search(r"href=\"([^\"]*)|url=([^']*)", tag)
            t = (t[1] if t[1] is not None else t[2]).replace("&amp;", "&")
            full = urllib.parse.urljoin(u if urllib.parse.urlsplit(u).path else u + "/", t) if t else None
            if full and key(full):
                parent[find(key(full))] = find(key(u))
    verdicts = {}
    for k in list(parent):
        verdicts.setdefault(find(k), set()).add(rule(k))
    for page, u, _ in rows:
        shared = verdicts[find(key(u))]
        own = rule(key(u)) if urllib.parse.urlsplit(u).path else None
        assert got[page] == (own or ("allow" if "allow" in shared else "block" if "block" in shared else "allow")), (page, u)
    assert {"allow", "block"} <= set(got.values())


# ---------------------------------------------------------------- plain versions of the models
def test_language_model_against_a_plain_average(spark):
    rng = random.Random(32)
    rows = [(k, " ".join(rng.choice(["über", "straße", "nicht"] if k % 2 else ["the", "house", "street"]) for _ in range(30)), "de" if k % 2 else "en") for k in range(120)]
    rows += [(0, "the the the", "de"), (0, "the the the", "en")]  # one id, several rows
    labelled = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = langid.fit(labelled)
    again = langid.fit(labelled.repartition(5))
    assert np.array_equal(model.table, again.table) and model.threshold == again.threshold
    for text in ("The house, in 1999!", "straße", "x", "nicht the über"):
        c = langid.code_points(text.encode())
        total = np.zeros(len(model.languages))
        for row in langid.buckets(c):
            for b in row:
                total += model.table[b]
        z = (total / (len(langid.ORDERS) * len(c)) + model.bias) / model.temperature
        p = np.exp(z - z.max()) / np.exp(z - z.max()).sum()
        lang, score = model.predict([text.encode()])
        assert lang == [model.languages[int(p.argmax())]] and abs(score[0] - p.max()) < 1e-4


def test_every_language_is_learned(spark):
    rows = [(k, f"{'abcdefghijklmnopqrstuvwxyz'[k % 26]}{'aeiou'[k % 5]}{'bcdfg'[k % 230 // 46]} " * 20, f"l{k % 230:03}") for k in range(460)]
    assert len(langid.fit(spark.createDataFrame(rows, "doc_id long, text string, lang string"), epochs=1).languages) == 230


def test_ratio_against_plain_multinomials(spark):
    rng = random.Random(33)
    rows = [(k, speak(rng, 70, "q" if k % 3 else "")) for k in range(90)] + [(200, None), (201, "")]
    labels = [(k, int(k % 3 == 0)) for k in range(60)] + [(None, 1)]
    docs = docs_of(spark, rows, extra=True)
    got = {r["doc_id"]: r for r in quality.judged(docs.select("doc_id", "text"), quality.fit(docs, spark.createDataFrame(labels, "doc_id long, quality int"))).collect()}
    raw, good = Counter(), Counter()
    grams = {k: quality.ngram_buckets((t or "").lower().encode().split()).tolist() if t else [] for k, t in rows}
    trusted = {k for k, q in labels if q and k is not None}
    for k, g in grams.items():
        raw.update(g)
        if k in trusted:
            good.update(g)
    n, m, s, size = sum(raw.values()), sum(good.values()), quality.SMOOTHING, quality.BUCKETS
    p_raw = lambda b: (raw[b] + s) / (n + s * size)
    p_good = lambda b: (good[b] + s * size * p_raw(b)) / (m + s * size)
    for k, g in grams.items():
        score = sum(math.log(p_good(b) / p_raw(b)) for b in g) / len(g) if g else 0.0
        assert abs(got[k]["score"] - score) < 1e-5
        assert got[k]["kept"] == (not got[k]["base_failed"] and got[k]["score"] >= quality.THRESHOLD)
    assert {r["kept"] for r in got.values()} == {True, False}


def test_licences_against_every_alignment(spark):
    rng = random.Random(34)
    cut = lambda s: alnum_words(s.encode())
    rows = []
    for k in range(150):
        words = speak(rng, rng.randint(0, 40)).split()
        for t in rng.sample(licenses.TEMPLATES, rng.choice([0, 1, 1, 2])):
            notice = t[1].split()
            for _ in range(rng.choice([0, 1, 2, len(notice) // 3])):
                notice[rng.randrange(len(notice))] = rng.choice(["other", "the", "license"])
            if rng.random() < 0.2:
                del notice[rng.randrange(len(notice))]
            at = rng.randint(0, len(words))
            words[at:at] = notice
        rows.append((k, " ".join(words)))
    got = {r["doc_id"]: r for r in licenses.scanned(docs_of(spark, rows).select("doc_id", "text")).collect()}
    labels_seen = set()
    for k, text in rows:
        words, labels, best = cut(text), set(), 0.0
        for label, template, phrases in licenses.TEMPLATES:
            t = cut(template)
            for offset in range(-len(t), len(words) + 1):
                score = sum(0 <= offset + i < len(words) and words[offset + i] == w for i, w in enumerate(t)) / len(t)
                near = words[max(0, offset - 3):max(0, offset + len(t) + 3)]
                if score >= licenses.LEAST_SCORE and all(licenses.places(near, cut(p)) for p in phrases):
                    labels.add(label)
                    best = max(best, score)
        base = set(filter(None, got[k]["base_labels"].split(",")))
        assert set(filter(None, got[k]["labels"].split(","))) == labels | base and abs(got[k]["score"] - best) < 1e-12
        labels_seen |= labels
    assert len(labels_seen) > 8


def test_long_items_are_cut_without_losing_windows(spark):
    rng = random.Random(35)
    item = speak(rng, 400)
    benchmark = spark.createDataFrame([("long", item), ("short", "only four words here"), ("none", ""), (None, speak(rng, 30))], "item_id string, text string")
    words = item.split()
    docs = docs_of(spark, [(k, " ".join(words[k:k + 10 + k % 3])) for k in range(0, 380, 7)] + [(1000, "x only four words here y"), (1001, None)])
    clash = docs.withColumns({c: F.lit(1) for c in ("n_words", "contaminated", "clean_text", "__spans", "__items", "spans")})
    whole = decontam.scan_documents(docs.select("doc_id", "text"), benchmark).drop("text").collect()
    cut = decontam.scan_documents(docs.select("doc_id", "text"), benchmark, max_words=25).drop("text").collect()
    assert sorted(map(str, whole)) == sorted(map(str, cut)) and sum(r["contaminated"] for r in whole) == len(whole) - 1
    prefixed = decontam.scan_documents(clash, benchmark, max_words=25, prefix="_d_").select("doc_id", "_d_n_hit", "_d_items_sha256").collect()
    assert sorted((r[0], r[1], r[2]) for r in prefixed) == sorted((r["doc_id"], r["n_hit"], r["items_sha256"]) for r in whole)


# ---------------------------------------------------------------- packing, continued
def test_best_fit_decreasing_against_one_piece_at_a_time():
    rng = random.Random(21)
    for _ in range(300):
        capacity = rng.choice([20, 50, 100])
        sizes = [rng.randint(1, capacity) for _ in range(rng.randint(1, 50))]
        rooms = []
        for s in sorted(sizes, reverse=True):
            fits = [r for r in rooms if r >= s]
            if fits:
                rooms.remove(min(fits))
            rooms.append((min(fits) if fits else capacity) - s)
        patterns = packing.best_fit_decreasing(dict(Counter(sizes)), capacity)
        assert sorted(capacity - sum(s * n for s, n in f.items()) for f, t in patterns for _ in range(t)) == sorted(rooms)
        used = sum(t for _, t in packing.bin_completion(dict(Counter(sizes)), capacity))
        assert packing.lower_bound(dict(Counter(sizes)), capacity) <= used <= len(rooms)


def test_dominance_against_all_subsets():
    rng = random.Random(22)
    for _ in range(400):
        capacity = 40
        left = Counter(rng.randint(1, 25) for _ in range(8))
        head = max(left)
        fill, room = Counter([head]), capacity - head
        for s in rng.sample(sorted(left.elements()), 5):
            if s <= room and fill[s] < left[s]:
                fill[s] += 1
                room -= s
        others = list((fill - Counter([head])).elements())
        sets = [[o for k, o in enumerate(others) if mask >> k & 1] for mask in range(1 << len(others))]
        outside = [s for s in left if left[s] > fill[s]]
        want = any(sum(some) <= o <= sum(some) + room and some != [o] for o in outside for some in sets)
        open_ = sum(1 << s for s in outside)
        assert packing.dominated(open_, head, room, dict(fill)) == want


def test_long_runs_of_blanks_and_letters_are_encoded():
    encoder = packing.Encoder()
    for text in (" " * 1_000_000, "a" + "\n" * 900_000 + "b", "x" * 200_000, "- " * 300_000):
        ids = encoder.full.encode(text, add_special_tokens=False).ids
        assert encoder.encode(text) == np.array(ids, "<u4").tobytes()


# ---------------------------------------------------------------- near-duplicates
def plain_print(text):
    words = (text or "").encode().lower().split()
    grams = [b" ".join(words[i:i + 4]) for i in range(max(1, len(words) - 3))] if words else []
    hashes = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


@pytest.mark.parametrize("chunk", [2000, 7])
def test_linked_against_all_pairs(spark, monkeypatch, chunk):
    monkeypatch.setattr(simhash, "shard_edges", lambda *a, f=simhash.shard_edges, **k: f(*a, **k | {"chunk": chunk}))
    rng = random.Random(10)
    rows, base = list(ODD), speak(rng, 250)
    for i in range(20, 200):
        words = base.split() if i % 3 else speak(rng, 80).split()
        for _ in range(rng.choice([0, 1, 1, 2])):
            words[rng.randrange(len(words))] = speak(rng, 1)
        rows.append((i, " ".join(words)))
    got = simhash.linked(docs_of(spark, rows, extra=True).select("doc_id", "text")).collect()
    prints = [(i, plain_print(t)) for i, t in rows]
    assert sorted((str(r["doc_id"]), r["fingerprint"]) for r in got) == sorted((str(i), f"{f:016x}") for i, f in prints)
    known = [(i, f) for i, f in prints if i is not None]
    parent = {i: i for i, _ in known}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, fa in known:
        for b, fb in known:
            if (fa ^ fb).bit_count() <= 4:
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    assert {r["doc_id"]: r["component_id"] for r in got if r["doc_id"] is not None} == {i: find(i) for i in parent}
    assert simhash.linked(docs_of(spark, rows).limit(0)).count() == 0


def test_bk_tree_finds_all_pairs():
    rng = np.random.default_rng(11)
    f = rng.integers(0, 1 << 63, (1, 2), dtype=np.uint64) ^ (np.uint64(1) << rng.integers(0, 63, (400, 2)).astype(np.uint64))
    f = np.concatenate([f, rng.integers(0, 1 << 63, (300, 2), dtype=np.uint64)])
    for radius in (0, 2, 4, 40):
        got = {(int(a), int(b)) for i, j in simhash.close_pairs(f, radius) for a, b in zip(i, j)}
        d = simhash.distances(f[:, None], f[None])
        want = {(int(a), int(b)) for a, b in zip(*np.nonzero(d <= radius)) if a < b}
        assert got == want


def test_trees_of_shards_find_what_all_pairs_of_the_shards_hold():
    rng = np.random.default_rng(12)
    base = rng.integers(0, 1 << 63, 20, dtype=np.uint64)
    f = np.unique(base[rng.integers(0, 20, 700)] ^ (np.uint64(1) << rng.integers(0, 64, 700).astype(np.uint64)) ^ (np.uint64(1) << rng.integers(0, 64, 700).astype(np.uint64)))
    f = rng.permutation(f)[:, None]
    shard = rng.integers(0, 5, len(f))
    trees = simhash.Trees(f, shard)
    got = {(int(a), int(b)) for q, r in trees.within(np.arange(len(f)), 4) for a, b in zip(q, r)}
    near = (simhash.distances(f[:, None], f[None]) <= 4) & (shard[:, None] == shard[None])
    assert got == {(int(a), int(b)) for a, b in zip(*np.nonzero(near))}
    assert trees.visited < (shard[:, None] == shard[None]).sum()
    assert len(simhash.Trees(f[:0], shard[:0]).stars(4)[0]) == 0


def test_whole_table_is_searched_through_trees(spark):
    """At sf0.1 every fingerprint walks trees of many nodes, and the layout's trees find every close pair."""
    docs = read_table(spark, "/root/testdata/sf0.1", "documents")
    f = simhash.fingerprints(docs, 4).select("f0").distinct().toPandas()["f0"].to_numpy().view(np.uint64)[:, None]
    got, visited, wide = set(), 0, 0
    for positions in simhash.block_layout(64, 4, len(f)):
        key = sum((f[:, 0] >> np.uint64(p) & np.uint64(1)) << np.uint64(k) for k, p in enumerate(positions.tolist()))
        shard = np.unique(key, return_inverse=True)[1]
        trees = simhash.Trees(f, shard)
        got |= {(int(a), int(b)) for q, r in trees.within(np.arange(len(f)), 4) for a, b in zip(q, r) if a < b}
        visited, wide = visited + trees.visited, wide + (np.bincount(shard).astype(float) ** 2).sum()
    assert 20 * len(f) < visited < 0.5 * wide
    want = set()
    for at in range(0, len(f), 500):
        i, j = np.nonzero(simhash.distances(f[at:at + 500, None], f[None]) <= 4)
        want |= {(int(a), int(b)) for a, b in zip(i + at, j) if a < b}
    assert got == want


@pytest.mark.parametrize("rows", [0, 1, 256, 257, 10**5, 10**8, 10**12])
def test_layout_loses_no_pair_within_the_radius(rows):
    rng = np.random.default_rng(rows % 97)
    keys = simhash.block_layout(64, 4, rows)
    assert len(keys) <= 500 and len({len(k) for k in keys}) == 1
    for _ in range(300):
        flipped = set(rng.choice(64, 4, replace=False).tolist())
        assert any(flipped.isdisjoint(k.tolist()) for k in keys)


def test_one_of_each_tells_rows_by_id_and_text(spark):
    rng = random.Random(15)
    a, b, c = (speak(rng, 80) for _ in range(3))
    rows = [(3, a), (7, a), (7, b), (9, c), (9, c), (11, c + " end"), (None, a), (12, None), (13, None)]
    for extra in (False, True):
        df = docs_of(spark, rows, extra)
        if extra:
            df = df.withColumns({x: F.lit(0) for x in ("__gone", "__again", "__doc", "__mark", "mark", "seq", "component_id", "stays", "id", "first")})
        kept = simhash.one_of_each(df, simhash.near_duplicates(df.select("doc_id", "text")))
        assert kept.columns == df.columns
        assert sorted((str(r["doc_id"]), r["text"]) for r in kept.collect() if r["text"]) == sorted([("3", a), ("7", b), ("9", c), ("None", a)])
        assert [r["doc_id"] for r in kept.collect() if r["text"] is None] == [12]


def test_a_doc_id_of_two_texts_joins_nothing(spark):
    rng = random.Random(16)
    a, b = speak(rng, 60), speak(rng, 60)
    got = {(r["doc_id"], r["fingerprint"]): r["component_id"] for r in simhash.linked(docs_of(spark, [(5, a), (5, b), (6, a), (9, b)])).collect()}
    assert sorted(got.values()) == [5, 5, 5, 5] and len(got) == 4
    got = {(r["doc_id"], r["fingerprint"]): r["component_id"] for r in simhash.linked(docs_of(spark, [(5, a), (5, b), (4, a), (9, b)])).collect()}
    assert sorted(got.values()) == [4, 4, 5, 5]


def test_near_duplicates_recall_and_one_of_each(spark):
    rng = random.Random(12)
    rows, group = [], {}
    for g in range(40):
        words = speak(rng, 120).split()
        for c in range(rng.choice([1, 2, 4])):
            copy = list(words)
            for _ in range(c):
                copy[rng.randrange(len(copy))] = speak(rng, 1)
            rows.append((len(rows), " ".join(copy)))
            group[len(rows) - 1] = g
    rows += [(500, rows[0][1]), (501, rows[0][1].upper() + " "), (502, None), (503, ""), (None, "x"), (504, "twice"), (504, "twice")]
    df = docs_of(spark, rows, extra=True)
    found = written(simhash.near_duplicates(df.select("doc_id", "text")), "groups")
    part = {r["doc_id"]: r["component_id"] for r in found.collect()}
    shingles = {i: {tuple(t.lower().split()[k:k + 5]) for k in range(max(1, len(t.split()) - 4))} for i, t in rows if t and i is not None}
    links = [(a, b) for a in shingles for b in shingles if a < b and len(shingles[a] & shingles[b]) >= 0.8 * len(shingles[a] | shingles[b])]
    assert len(links) > 30 and np.mean([part[a] == part[b] for a, b in links]) >= 0.99
    assert part[500] == part[501] == 0 and part[502] == part[503]
    assert all(group[a] == group[b] for a in group for b in group if part[a] == part[b])
    kept = simhash.one_of_each(df, found)
    assert kept.columns == df.columns
    ids = [r["doc_id"] for r in kept.collect()]
    assert 500 not in ids and 0 in ids and ids.count(504) == 1 and ids.count(None) == 1


def test_pairs_among_many_siblings_of_one_template(spark):
    # each text shares 350 shingles with all others and most of the rest with one partner: 0.83 to it, about 0.7 to others
    rng = random.Random(13)
    stem, rows = speak(rng, 354, "t"), []
    for g in range(120):
        both = speak(rng, 42, "p")
        rows += [(2 * g + k, f"{stem} {both} {speak(rng, 38, 'o')}") for k in range(2)]
    part = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(docs_of(spark, rows).select("doc_id", "text")).collect()}
    assert sum(part[2 * g] == part[2 * g + 1] for g in range(120)) >= 119
    assert len(set(part.values())) >= 119


def test_prefix_pairs_hold_every_similar_pair(spark):
    rng = random.Random(17)
    stem = rng.sample(range(10**6), 90)
    sets = {}
    for k in range(150):
        base = set(rng.sample(stem, rng.randint(70, 90))) | set(rng.sample(range(10**6, 2 * 10**6), rng.randint(0, 25))) if k % 3 or not k else set(rng.sample(sorted(sets[k - 1]), len(sets[k - 1]) - rng.randint(0, 12)))
        sets[k] = base
    sets[150], sets[151] = set(), {5}
    component = {k: k // 4 for k in sets}
    rows = [(k, sorted(x), component[k]) for k, x in sets.items()]
    got = {(r["u"], r["v"]) for r in simhash.prefix_pairs(spark.createDataFrame(rows, "id long, shingles array<int>, component long"), 0.8).collect()}
    want = {(a, b) for a in sets for b in sets if a > b and component[a] != component[b] and sets[a] and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])}
    every = sum(1 for a in sets for b in sets if a > b and component[a] != component[b])
    assert want and want <= got and len(got) < 0.8 * every


def test_copies_that_differ_in_how_often_a_passage_repeats(spark):
    rng = random.Random(14)
    rows = []
    for g in range(30):
        text, passage = speak(rng, 400), speak(rng, 50)
        rows += [(2 * g, f"{text} {passage}"), (2 * g + 1, f"{text} {' '.join([passage] * 8)}")]
    part = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(docs_of(spark, rows).select("doc_id", "text")).collect()}
    assert part == {i: i - i % 2 for i in range(60)}
