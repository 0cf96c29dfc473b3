"""Language-model scoring with a log-bilinear model trained by noise-contrastive estimation.

Tokens are lower-cased words between ASCII blanks, then one end token a text. Counts of all tokens of all training texts
are gathered in a table (it grows with the corpus). Tokens fall into UNITS units: the end, the OWN most frequent words each
by itself, and units of the other words by a hash of their last bytes; units fall into CLASSES classes (the end and the
SINGLE most frequent words each by itself, the others by the same hash). The model has three factors:

1. the token's class after the two classes before it: the contexts' embeddings, mapped linearly and added, meet the class's
   embedding and bias (log-bilinear);
2. its unit, among those of its class, after the unit before it: the embedding of that unit, mapped linearly, meets the
   unit's embedding and bias (log-bilinear, over words);
3. the token in its unit: 1 for a word of its own, else its smoothed share of the unit's count, with one slot for unknown
   tokens.

Both log-bilinear parts are trained in numpy by noise-contrastive estimation against unigrams, on the counts of class
trigrams and of unit pairs over the whole training corpus (at most CLASSES^3 and UNITS^2 numbers); matrix products over all
contexts then give exactly normalised log-probabilities, tables of CLASSES^3 and UNITS^2 numbers. The score is their sum
over the text. Which tokens have units of their own depends on the counts alone.

Texts are never shuffled. Counts of the HOT most frequent tokens at most are broadcast (chosen by a count threshold from a
histogram, so their number is bounded), and those of words with units of their own; the other, rare tokens of a text are
joined to the count table by token. They have no skew, because every token with a large share of the rows is hot. The bound
changes what travels, not the scores.

Defined edge results: null and empty texts are the end token alone; a null id is neither learned from nor held out; repeated
rows are learned from and scored each by itself; equally frequent words are ranked by their bytes; with no training text
every token is unknown; only doc_id and text are read, so other columns may have any name.
"""

from __future__ import annotations

import math
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_bytes, blank_words, crc_mod, small, written

CLASSES = 64
SINGLE = 31  # words that are a class of their own; class 0 is the end
UNITS = 1024
OWN = 959  # words that are a unit of their own, the single ones among them; unit 0 is the end
TAIL = 1 + OWN  # the first unit of words that share one
HOT = 200_000
DIM = 24
NOISE = 20
SMOOTHING = 0.1
FLUSH = 200_000
END = b""


def tokens(text: bytes | None) -> list[bytes]:
    return [*(blank_words(text.lower()) if text else ()), END]


def count_tokens(training: DataFrame) -> DataFrame:
    """(text) -> token binary, c long."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter[bytes] = Counter()

        def out():
            return pa.RecordBatch.from_arrays([pa.array(list(seen), pa.binary()), pa.array(list(seen.values()), pa.int64())], ["token", "c"])

        for b in small(batches):
            for t in as_bytes(b.column(0)):
                seen.update(tokens(t))
                if len(seen) > FLUSH:
                    yield out()
                    seen.clear()
        yield out()

    return training.select("text").mapInArrow(run, "token binary, c long").groupBy("token").agg(F.sum("c").alias("c"))


def _spread(word: bytes) -> int:
    return zlib.crc32(word[-3:])


def tail_unit(word: bytes) -> int:
    """The unit of a word that has none of its own."""
    return TAIL + _spread(word) % (UNITS - TAIL)


def class_of(unit: int, word: bytes) -> int:
    """The class of a unit; `word` is the unit's own word, if it has one."""
    if unit <= SINGLE:
        return unit
    return 1 + SINGLE + (_spread(word) if unit < TAIL else unit - TAIL) % (CLASSES - 1 - SINGLE)


@dataclass
class Lexicon:
    hot: dict[bytes, int]  # token -> number
    counts: np.ndarray  # of hot tokens
    units: np.ndarray  # of hot tokens
    classes: np.ndarray  # of units
    total: int
    distinct: int
    unit_total: np.ndarray  # tokens and distinct tokens of each unit
    unit_distinct: np.ndarray

    def codes(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Hot number (or -1) and unit of each word."""
        number = np.fromiter(map(self.hot.get, words, repeat(-1)), np.int64, len(words))
        unit = self.units[number]
        for i in np.flatnonzero(number < 0).tolist():
            unit[i] = tail_unit(words[i]) if words[i] else 0
        return number, unit


def hot_threshold(counts: DataFrame, most: int) -> int:
    """The least count such that at most `most` tokens have it or more."""
    step = F.when(F.col("c") < 64, F.col("c")).otherwise(64 + F.floor(F.log2(F.col("c") / 64) * 8)).cast("int")
    have, least = 0, None
    for r in sorted(counts.groupBy(step.alias("step")).agg(F.count("*").alias("n"), F.min("c").alias("low")).collect(), key=lambda r: -r["step"]):
        have += r["n"]
        if have > most:
            break
        least = r["low"]
    return least if least is not None else (1 << 62)


def lexicon(counts: DataFrame, most: int = HOT) -> tuple[Lexicon, int]:
    """The lexicon, and the count from which on every token is hot."""
    least = hot_threshold(counts, most)
    top = counts.filter(F.length("token") > 0).orderBy(F.desc("c"), "token").limit(OWN).toArrow().to_pydict()
    own = {w: 1 + k for k, w in enumerate(top["token"])}
    counted = dict(zip(top["token"], top["c"])) | {END: 0}
    for part in (counts.filter(F.col("c") >= least), counts.filter(F.length("token") == 0)):
        rows = part.toArrow().to_pydict()
        counted |= dict(zip(rows["token"], rows["c"]))
    words = sorted(counted, key=lambda w: (-counted[w], w))
    unit_of = lambda w: own.get(w) or (tail_unit(w) if w else 0)
    classes = np.zeros(UNITS, np.int64)
    classes[TAIL:] = [class_of(u, b"") for u in range(TAIL, UNITS)]
    for w, u in own.items():
        classes[u] = class_of(u, w)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, v = np.zeros(UNITS, np.int64), np.zeros(UNITS, np.int64)
        for b in small(batches):
            units = np.array([unit_of(w) for w in b.column(0).to_pylist()], np.int64)
            v += np.bincount(units, minlength=UNITS)
            np.add.at(n, units, b.column(1).to_numpy())
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(UNITS)), pa.array(n), pa.array(v)], ["k", "n", "v"])

    per = counts.select("token", "c").mapInArrow(run, "k long, n long, v long").groupBy("k").agg(F.sum("n").alias("n"), F.sum("v").alias("v")).collect()
    n, v = np.zeros(UNITS, np.int64), np.zeros(UNITS, np.int64)
    for r in per:
        n[r["k"]], v[r["k"]] = r["n"], r["v"]
    return Lexicon({w: k for k, w in enumerate(words)}, np.array([counted[w] for w in words], np.int64), np.array([unit_of(w) for w in words], np.int64),
                   classes, int(n.sum()), int(v.sum()), n, v), least


def trigram_keys(cls: np.ndarray) -> np.ndarray:
    """Class of the token and of the two before it (0 before the text), as one number."""
    before = np.r_[0, 0, cls[:-1]] if len(cls) > 1 else np.zeros(2, np.int64)
    return (before[:len(cls)] * CLASSES + np.r_[0, cls[:-1]]) * CLASSES + cls


def pair_keys(unit: np.ndarray) -> np.ndarray:
    """Unit before the token (the end's before the text) and of the token, as one number."""
    return np.r_[0, unit[:-1]] * UNITS + unit


def gathered(training: DataFrame, words: Lexicon) -> tuple[np.ndarray, np.ndarray]:
    """Counts over all training texts of class trigrams (older class first) and of unit pairs."""
    shared = training.sparkSession.sparkContext.broadcast(words)
    cells = CLASSES**3

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(cells + UNITS**2, np.int64)
        for b in small(batches):
            held = [np.empty(0, np.int64)]
            for t in as_bytes(b.column(0)):
                unit = shared.value.codes(tokens(t))[1]
                held += [trigram_keys(shared.value.classes[unit]), cells + pair_keys(unit)]
            np.add.at(total, np.concatenate(held), 1)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(total[at])], ["k", "n"])

    got = training.select("text").mapInArrow(run, "k int, n long").groupBy("k").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(cells + UNITS**2, np.int64)
    out[got["k"].to_numpy()] = got["n"].to_numpy()
    return out[:cells].reshape(CLASSES, CLASSES, CLASSES), out[cells:].reshape(UNITS, UNITS)


def train_units(pairs: np.ndarray, classes: np.ndarray, steps: int = 2500, batch: int = 1024, rate: float = 0.1, noise_units: int = 64, seed: int = 8) -> np.ndarray:
    """log10 probabilities [unit before, unit]: normalised over the units of each class. A step's noise units are drawn
    from the unigrams and shared by its batch, so a step is a few matrix products."""
    unigram = pairs.sum(0) + SMOOTHING
    noise = unigram / unigram.sum()
    rng = np.random.default_rng(seed)
    emb, out = rng.normal(0, 0.1, (UNITS, DIM)), rng.normal(0, 0.1, (UNITS, DIM))
    to_out, bias = np.eye(DIM), np.log(noise)
    log_noise = np.log(noise_units * noise)
    params = [emb, out, to_out, bias]
    squares = [np.full(p.shape, 1e-6) for p in params]
    cumulative, noise_cumulative, total = np.cumsum(pairs.ravel()), np.cumsum(noise), pairs.sum()
    for _ in range(steps if total else 0):
        key = np.searchsorted(cumulative, rng.random(batch) * total, side="right").clip(max=UNITS**2 - 1)
        before, word = key // UNITS, key % UNITS
        false = np.searchsorted(noise_cumulative, rng.random(noise_units)).clip(max=UNITS - 1)
        e = emb[before]
        h = e @ to_out
        right = 1 / (1 + np.exp(-((h * out[word]).sum(1) + bias[word] - log_noise[word]))) - 1
        wrong = 1 / (1 + np.exp(-(h @ out[false].T + bias[false] - log_noise[false])))
        g_h = right[:, None] * out[word] + wrong @ out[false]
        g_emb, g_out, g_bias = np.zeros_like(emb), np.zeros_like(out), np.zeros_like(bias)
        np.add.at(g_emb, before, g_h @ to_out.T)
        np.add.at(g_out, np.r_[word, false], np.concatenate([right[:, None] * h, wrong.T @ h]))
        np.add.at(g_bias, np.r_[word, false], np.r_[right, wrong.sum(0)])
        for p, g, s in zip(params, (g_emb, g_out, e.T @ g_h, g_bias), squares):
            g /= batch
            s += g * g
            p -= rate * g / np.sqrt(s)
    logits = emb @ to_out @ out.T + bias
    for c in range(CLASSES):
        some = np.flatnonzero(classes == c)
        if len(some):
            part = logits[:, some] - logits[:, some].max(1, keepdims=True)
            logits[:, some] = part - np.log(np.exp(part).sum(1, keepdims=True))
    return logits / math.log(10)


def train(trigrams: np.ndarray, steps: int = 2500, batch: int = 512, rate: float = 0.1, seed: int = 7) -> np.ndarray:
    """log10 probabilities, [older class, class before, class]: normalised over the last axis."""
    total = trigrams.sum()
    if not total:
        return np.full((CLASSES,) * 3, -math.log10(CLASSES))
    rng = np.random.default_rng(seed)
    unigram = trigrams.sum((0, 1)) + SMOOTHING
    noise = unigram / unigram.sum()
    log_noise = np.log(NOISE * noise)
    emb = rng.normal(0, 0.1, (CLASSES, DIM))
    out = rng.normal(0, 0.1, (CLASSES, DIM))
    maps = [np.eye(DIM) * s for s in (0.3, 0.7)]  # for the older and the nearer class
    bias = np.log(noise)
    cumulative = np.cumsum(trigrams.ravel())
    noise_cumulative = np.cumsum(noise)
    params = [emb, out, bias, *maps]
    squares = [np.full(p.shape, 1e-6) for p in params]
    for _ in range(steps):
        key = np.searchsorted(cumulative, rng.random(batch) * total, side="right")
        key = np.minimum(key, CLASSES**3 - 1)
        older, near, word = key // CLASSES**2, key // CLASSES % CLASSES, key % CLASSES
        false = np.minimum(np.searchsorted(noise_cumulative, rng.random((batch, NOISE))), CLASSES - 1)
        w = np.concatenate([word[:, None], false], 1)
        h = emb[older] @ maps[0] + emb[near] @ maps[1]
        score = np.einsum("bd,bkd->bk", h, out[w]) + bias[w]
        truth = np.zeros_like(score)
        truth[:, 0] = 1
        delta = (1 / (1 + np.exp(-(score - log_noise[w]))) - truth) / batch
        spread = np.zeros((batch, CLASSES))
        np.add.at(spread, (np.arange(batch)[:, None], w), delta)
        g_h = spread @ out
        g_emb = np.zeros_like(emb)
        np.add.at(g_emb, older, g_h @ maps[0].T)
        np.add.at(g_emb, near, g_h @ maps[1].T)
        grads = [g_emb, spread.T @ h, spread.sum(0), emb[older].T @ g_h, emb[near].T @ g_h]
        for p, g, s in zip(params, grads, squares):
            s += g * g
            p -= rate * g / np.sqrt(s)
    contexts = (emb @ maps[0])[:, None] + (emb @ maps[1])[None]
    logits = contexts.reshape(-1, DIM) @ out.T + bias
    logits -= logits.max(1, keepdims=True)
    logits -= np.log(np.exp(logits).sum(1, keepdims=True))
    return (logits / math.log(10)).reshape((CLASSES,) * 3)


def scored(docs: DataFrame, modulus: int = 10, hot: int = HOT) -> DataFrame:
    """docs (doc_id, text) -> doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score."""
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", (crc_mod(F.col("doc_id"), modulus) == 0).alias("out"))
    training = docs.filter(~F.col("out"))
    counts = written(count_tokens(training), "token-counts")
    words, least = lexicon(counts, hot)
    trigrams, pairs = gathered(training, words)
    inside = np.log10(words.unit_total + SMOOTHING * (words.unit_distinct + 1))
    shared = spark.sparkContext.broadcast((words, train(trigrams).ravel(), train_units(pairs, words.classes).astype(np.float32).ravel(), inside))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lex, of_class, of_unit, log_inside = shared.value
        log_count = np.log10(lex.counts + SMOOTHING)
        place = TaskContext.get().partitionId() << 40
        for b in small(batches):
            rows, rare_words, rare_times, ends = [], [], [], [0]
            for doc, text, out in zip(b.column(0).to_pylist(), as_bytes(b.column(1)), b.column(2).to_pylist()):
                ws = tokens(text)
                number, unit = lex.codes(ws)
                is_hot = number >= 0
                logs = np.where(is_hot, log_count[number], 0.0)
                many = unit >= TAIL
                fixed = (of_class[trigram_keys(lex.classes[unit])].sum() + of_unit[pair_keys(unit)].sum(dtype=np.float64)
                         + logs[many].sum() - log_inside[unit[many]].sum())
                rare = Counter(ws[i] for i in np.flatnonzero(~is_hot).tolist())
                rare_words += rare
                rare_times += rare.values()
                ends.append(len(rare_words))
                rows.append((place, doc, bool(out), len(ws), int((is_hot & (lex.counts[number] > 0)).sum()), float(logs.sum()), float(fixed)))
                place += 1
            cols = list(zip(*rows)) or [()] * 7
            kinds = [pa.int64(), pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.float64(), pa.float64()]
            offsets = pa.array(ends, pa.int32())
            yield pa.RecordBatch.from_arrays(
                [*(pa.array(c, k) for c, k in zip(cols, kinds)), pa.ListArray.from_arrays(offsets, pa.array(rare_words, pa.binary())),
                 pa.ListArray.from_arrays(offsets, pa.array(rare_times, pa.int32()))],
                ["key", "doc_id", "held_out", "n_tokens", "known", "hot_logs", "fixed", "rare", "times"])

    per_doc = written(docs.mapInArrow(run, "key long, doc_id long, held_out boolean, n_tokens long, known long, hot_logs double, fixed double, rare array<binary>, times array<int>"), "texts")
    rare = per_doc.select("key", F.explode(F.arrays_zip("rare", "times")).alias("x")).select("key", F.col("x.rare").alias("w"), F.col("x.times").alias("times"))
    tail = counts.filter(F.col("c") < least)  # words with a unit of their own are never rare, so their rows meet nothing
    c = F.coalesce(F.col("c"), F.lit(0))
    joined = rare.join(tail, rare["w"] == tail["token"], "left").groupBy("key").agg(
        F.sum(F.col("times") * F.log10(c + SMOOTHING)).alias("rare_logs"), F.sum(F.when(c > 0, F.col("times")).otherwise(0)).alias("rare_known"))
    joined = joined.withColumnRenamed("key", "k")
    unit = math.log10(words.total + SMOOTHING * (words.distinct + 1))
    logs = F.coalesce("rare_logs", F.lit(0.0))
    return per_doc.drop("rare", "times").join(joined, F.col("key") == F.col("k"), "left").select(
        "doc_id", "held_out", "n_tokens", (F.col("known") + F.coalesce("rare_known", F.lit(0))).cast("long").alias("n_known"),
        F.lit(words.total).cast("long").alias("train_tokens"), (F.col("hot_logs") + logs - F.col("n_tokens") * F.lit(unit)).alias("base_score"),
        (F.col("fixed") + logs).alias("score"))
