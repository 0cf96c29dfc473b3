"""Quality rules: base counts and a hashed n-gram log-likelihood ratio.

Two multinomials over hashed unigrams and bigrams of lower-cased words: one of trusted documents, one of the raw corpus
(all documents). A document's score is the mean, over its n-grams, of the log ratio of the two smoothed probabilities; it
is kept if no base rule fails and the score reaches the threshold. Every document is judged by the same fixed rule.

The raw counts cover all documents: each task adds up one array of BUCKETS counts, which meet in a grouped sum, so what is
shuffled is at most BUCKETS rows a task. The trusted multinomial is fitted on at most about MAX_TRUSTED labelled documents
(a bounded classifier sample, chosen by a hash of the id). The model is one float a bucket and is broadcast.

Defined edge results: a null or empty text has no words, fails the base rule and is not kept; repeated rows are judged
alike; without trusted documents only the base rules decide; `judged` keeps all columns, and its own take a prefix
(common.free_prefix gives one that clashes with none).
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_bytes, small, with_fields

BUCKETS = 1 << 16
MAX_TRUSTED = 20_000
#: Mean log ratio (nats an n-gram) below which a document goes: its n-grams are, on average, over a tenth less likely
#: under the trusted model than under the raw one.
THRESHOLD = -0.12
SMOOTHING = 2.0
SYMBOLS = b"#*$%&|<>"
BLANKS = b" \t\n\x0b\x0c\r"


def ngram_buckets(words: list[bytes]) -> np.ndarray:
    """Bucket numbers of the words and of the pairs of neighbouring words."""
    h = np.fromiter(map(zlib.crc32, words), np.uint32, len(words))
    pairs = (h[:-1] * np.uint32(0x9E3779B1)) ^ (h[1:] * np.uint32(0x85EBCA6B) + np.uint32(0x165667B1))
    both = np.concatenate([h, pairs])
    both = (both ^ (both >> np.uint32(15))) * np.uint32(0x2C1B3C6D)
    return both >> np.uint32(16)


def repeated_words(words: list[bytes]) -> int:
    """Words that stand in a 3-word window found twice or more in the text (first occurrence included)."""
    n = len(words)
    if n < 4:
        return 0
    codes: dict[bytes, int] = {}
    w = np.fromiter((codes.setdefault(x, len(codes)) for x in words), np.int64, n)
    size = len(codes)
    pair = w[:-1] * size + w[1:]
    if size > 2_000_000:  # three factors would not fit 63 bits
        pair = np.unique(pair, return_inverse=True)[1]
    window = pair[:-1] * size + w[2:]
    order = np.argsort(window, kind="stable")
    same = window[order][1:] == window[order][:-1]
    if not same.any():
        return 0
    again = np.zeros(n - 2, bool)
    again[order[1:][same]] = True
    again[order[:-1][same]] = True
    hit = np.zeros(n, bool)
    for k in range(3):
        hit[k:n - 2 + k] |= again
    return int(hit.sum())


def base_counts(text: bytes) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words."""
    words = text.split()
    solid = text.translate(None, BLANKS)
    lines = [x for x in text.split(b"\n") if x.strip()]
    return (len(words), len(solid.decode("utf-8", "replace")), len(text) - len(text.translate(None, SYMBOLS)),
            len(lines) - len(set(lines)), repeated_words(words))


def fit(docs: DataFrame, labels: DataFrame, max_trusted: int = MAX_TRUSTED) -> np.ndarray | None:
    """Log ratio for each bucket, or None without trusted documents."""
    spark = docs.sparkSession
    good = labels.filter("quality = 1 and doc_id is not null").select("doc_id").distinct()
    n = good.count()
    key = F.pmod(F.xxhash64(F.col("doc_id").cast("string")), F.lit(1 << 30))
    ids = {r[0] for r in good.filter(key < int(min(1.0, max_trusted / max(n, 1)) * (1 << 30))).collect()}
    shared = spark.sparkContext.broadcast(ids)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trusted = shared.value
        total, some = np.zeros(BUCKETS, np.int64), np.zeros(BUCKETS, np.int64)
        for b in small(batches):
            for doc, text in zip(b.column(0).to_pylist(), as_bytes(b.column(1))):
                words = text.lower().split() if text else []
                if words:
                    h = ngram_buckets(words)
                    np.add.at(total, h, 1) if len(h) < 2000 else np.add(total, np.bincount(h, minlength=BUCKETS), out=total)
                    if doc in trusted:
                        np.add.at(some, h, 1)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at]), pa.array(some[at])], ["bucket", "raw", "good"])

    got = (docs.select("doc_id", "text").mapInArrow(run, "bucket long, raw long, good long")
           .groupBy("bucket").agg(F.sum("raw").alias("raw"), F.sum("good").alias("good")).toPandas())
    raw, good_n = np.zeros(BUCKETS), np.zeros(BUCKETS)
    raw[got["bucket"]], good_n[got["bucket"]] = got["raw"], got["good"]
    if not good_n.sum():
        return None
    # the trusted sample backs off to the raw corpus, so a bucket unseen in it counts as rare, not as impossible
    p_raw = (raw + SMOOTHING) / (raw.sum() + SMOOTHING * BUCKETS)
    p_good = (good_n + SMOOTHING * BUCKETS * p_raw) / (good_n.sum() + SMOOTHING * BUCKETS)
    return np.log(p_good / p_raw).astype(np.float32)


def judged(docs: DataFrame, ratio: np.ndarray | None, threshold: float = THRESHOLD, prefix: str = "") -> DataFrame:
    """docs (text, ...) and n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, score, kept."""
    shared = docs.sparkSession.sparkContext.broadcast(ratio)
    place = docs.columns.index("text")
    names = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "score", "kept"]
    kinds = ["long"] * 5 + ["boolean", "double", "boolean"]
    schema = with_fields(docs.schema, **{prefix + n: k for n, k in zip(names, kinds)})
    arrow = [pa.int64()] * 5 + [pa.bool_(), pa.float64(), pa.bool_()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = shared.value
        for b in small(batches):
            rows = []
            for text in as_bytes(b.column(place)):
                counts = base_counts(text) if text else (0, 0, 0, 0, 0)
                failed = counts[0] < 50 or 100 * counts[4] > 50 * counts[0]
                score = float(table[ngram_buckets(text.lower().split())].mean(dtype=np.float64)) if table is not None and counts[0] else 0.0
                rows.append((*counts, failed, score, not failed and score >= threshold))
            cols = list(zip(*rows)) or [()] * 8
            yield pa.RecordBatch.from_arrays([*b.columns, *(pa.array(c, t) for c, t in zip(cols, arrow))], schema.names)

    return docs.mapInArrow(run, schema)
