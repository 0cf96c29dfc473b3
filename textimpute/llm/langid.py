"""Language identification: averaged hashed subword embeddings with a linear softmax.

A text (lower-cased, everything but letters read as one blank) is the average of the embeddings of its hashed 2-, 3- and
4-grams; a linear layer and a softmax give the language. Training is stochastic gradient descent in numpy over a bounded
sample of labelled rows (`max_train`, chosen by a hash of the id; each row as its whole text and as a few short windows of
it, so that short texts are learned too). A third of the sample sets the softmax temperature and the rejection threshold.
Because average and layer are linear, prediction needs one table (buckets x languages: 128 KB a language), which is
broadcast, and no shuffle. Every language of the learning rows is learned; the sample is at most about
max(max_train, least_each * languages) rows.

Defined edge results: a null text or one without a letter is `und` with score 0; with nothing to learn from every text
is `und`; null ids are predicted but not learned from; repeated rows are predicted alike; `predicted` keeps all columns,
and its own take a prefix (common.free_prefix gives one that clashes with none).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_bytes, crc_mod, small, with_fields

BUCKETS = 1 << 15
ORDERS = (2, 3, 4)
DIM = 12
#: Bound of the training sample, in rows (each has at most BUCKETS features for every view of its text), and the rows that
#: a language has in it at least, however many languages there are (as far as the language has so many).
MAX_TRAIN = 2000
LEAST_EACH = 20
BLOCK = 1 << 19
#: Greatest norm of one training step of the embeddings or of the layer. Batches are summed, so that many copies of one
#: passage in a batch, under different languages, would else make steps that overshoot and grow without bound.
MAX_STEP = 1.0

_letters: list[np.ndarray] = []


def letters() -> np.ndarray:
    if not _letters:
        _letters.append(np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000))
    return _letters[0]


def code_points(text: bytes) -> np.ndarray:
    """Code points of the lower-cased text, runs of anything but letters as one 0, framed by 0."""
    c = np.frombuffer(text.decode("utf-8", "replace").lower().encode("utf-32-le"), np.uint32)
    c = np.where(letters()[c], c, 0)
    return np.r_[np.uint32(0), c[(c != 0) | np.r_[True, c[:-1] != 0]], np.uint32(0)]


def buckets(c: np.ndarray) -> np.ndarray:
    """A row of bucket numbers for each order: the n-gram that begins at each position (framed so that none runs out)."""
    h = np.r_[c, np.zeros(max(ORDERS), np.uint32)]
    n = len(c)
    out, h0 = [], h[:n] * np.uint32(2654435761)
    for k in range(1, max(ORDERS)):
        h0 = (h0 ^ (h0 >> np.uint32(15))) * np.uint32(2246822519) + h[k:k + n] * np.uint32(3266489917)
        if k + 1 in ORDERS:
            out.append(((h0 ^ (h0 >> np.uint32(13))) * np.uint32(668265263)) >> np.uint32(32 - 15))
    return np.stack(out)


@dataclass
class Model:
    languages: list[str]
    table: np.ndarray  # buckets x languages
    bias: np.ndarray
    temperature: float
    threshold: float

    def predict(self, texts: list[bytes | None]) -> tuple[list[str], list[float]]:
        langs, scores = [], []
        for t in texts:
            c = code_points(t) if t and self.languages else np.zeros(0, np.uint32)
            if not c.any():
                langs.append("und"), scores.append(0.0)
                continue
            total = np.zeros(len(self.languages))
            for at in range(0, len(c), BLOCK):
                b = buckets(c[at:at + BLOCK + max(ORDERS)])[:, :BLOCK].ravel()
                total += np.bincount(b, minlength=BUCKETS).astype(np.float32) @ self.table if len(b) > BUCKETS else self.table[b].sum(0)
            logits = (total / (len(ORDERS) * len(c)) + self.bias) / self.temperature
            p = np.exp(logits - logits.max())
            p /= p.sum()
            langs.append(self.languages[int(p.argmax())]), scores.append(float(p.max()))
        return langs, scores


def bounded(step: np.ndarray) -> np.ndarray:
    """The step, shortened to a norm of MAX_STEP if it is longer."""
    return step * np.float32(min(1.0, MAX_STEP / max(float(np.linalg.norm(step)), 1e-12)))


def _views(text: bytes, key: int) -> list[np.ndarray]:
    """The whole text and three windows of it whose place follows from key."""
    c = code_points(text)
    rng = np.random.default_rng(key & 0xFFFFFFFF)
    out = [c]
    for n in (12, 40, 150):
        at = int(rng.integers(0, max(1, len(c) - n)))
        out.append(c[at:at + n])
    return [v for v in out if v.any()]


def _features(sample: DataFrame) -> list:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches):
            rows = []
            for key, lang, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), as_bytes(b.column(2))):
                for k, v in enumerate(_views(text, key)):
                    i, n = np.unique(buckets(v), return_counts=True)
                    rows.append((key, k, lang, i.astype(np.int32), (n / n.sum()).astype(np.float32)))
            cols = list(zip(*rows)) or [()] * 5
            kinds = [pa.int64(), pa.int32(), pa.string(), pa.list_(pa.int32()), pa.list_(pa.float32())]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], ["key", "view", "lang", "i", "w"])

    got = sample.mapInArrow(run, "key long, view int, lang string, i array<int>, w array<float>").toArrow()
    n = got.num_rows
    i, w = got["i"].combine_chunks(), got["w"].combine_chunks()
    cut = lambda a: np.split(a.flatten().to_numpy(), np.cumsum(pa.compute.list_value_length(a).to_numpy())[:-1]) if n else []
    rows = zip(got["key"].to_pylist(), got["view"].to_pylist(), got["lang"].to_pylist(), cut(i), cut(w))
    return sorted(rows, key=lambda r: (*r[:3], r[3].tobytes(), r[4].tobytes()))


def fit(labelled: DataFrame, max_train: int = MAX_TRAIN, epochs: int = 12, rate: float = 0.6, reject: float = 0.0005, seed: int = 1, least_each: int = LEAST_EACH) -> Model:
    """labelled (doc_id, text, lang): rows with a null in any of these are not used."""
    rows = labelled.select("doc_id", "text", "lang").filter("doc_id is not null and text is not null and lang is not null")
    counts = rows.groupBy("lang").agg(F.count("*").alias("n")).collect()  # one row a language
    languages = sorted(r["lang"] for r in counts)
    if not languages:
        return Model([], np.zeros((BUCKETS, 0), np.float32), np.zeros(0), 1.0, 0.0)
    # an even share for each language, as far as it has rows
    each = max(-(-max_train // len(languages)), least_each)
    share = rows.sparkSession.createDataFrame([(r["lang"], min(1.0, each / r["n"])) for r in counts], "of_lang string, share double")
    key = F.xxhash64(F.col("doc_id").cast("string"))
    chosen = (rows.join(F.broadcast(share), F.col("lang") == F.col("of_lang"))
              .filter(F.pmod(key, F.lit(1 << 30)) < F.col("share") * float(1 << 30)).select(key.alias("key"), "lang", "text"))
    views = _features(chosen)
    rng = np.random.default_rng(seed)
    at = {lang: k for k, lang in enumerate(languages)}
    held = [r for r in views if r[0] % 3 == 0] or views
    train = [r for r in views if r[0] % 3] or views
    emb = rng.normal(0, 0.1, (BUCKETS, DIM)).astype(np.float32)
    out = np.zeros((DIM, len(languages)), np.float32)
    bias = np.zeros(len(languages), np.float32)
    steps, batch = 0, 32
    for epoch in range(epochs):
        order = rng.permutation(len(train))
        lr = rate * (1 - epoch / epochs)
        for a in range(0, len(order), batch):
            some = [train[k] for k in order[a:a + batch]]
            i = np.concatenate([r[3] for r in some])
            w = np.concatenate([r[4] for r in some])[:, None]
            starts = np.cumsum([0, *(len(r[3]) for r in some[:-1])])
            hidden = np.add.reduceat(emb[i] * w, starts)
            logits = hidden @ out + bias
            p = np.exp(logits - logits.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            p[np.arange(len(some)), [at[r[2]] for r in some]] -= 1
            back = np.repeat(p @ out.T, [len(r[3]) for r in some], axis=0) * w
            out -= bounded(lr * hidden.T @ p)
            bias -= lr * 0.1 * p.mean(0)
            order_i = np.argsort(i, kind="stable")
            first = np.flatnonzero(np.r_[True, np.diff(i[order_i]) != 0])
            emb[i[order_i][first]] -= bounded(lr * 20 * np.add.reduceat(back[order_i], first))
            steps += 1
    table = (emb @ out).astype(np.float32)
    raw = np.array([(table[r[3]] * r[4][:, None]).sum(0) + bias for r in held])
    truth = np.array([at[r[2]] for r in held])

    def loss(t: float) -> float:
        z = raw / t
        z = z - z.max(1, keepdims=True)
        return float(-(z[np.arange(len(z)), truth] - np.log(np.exp(z).sum(1))).mean())

    temperature = min((0.05 * 1.25**k for k in range(24)), key=loss)
    z = np.exp((raw - raw.max(1, keepdims=True)) / temperature)
    top = (z / z.sum(1, keepdims=True)).max(1)
    right = raw.argmax(1) == truth
    threshold = float(np.quantile(top[right], reject)) if right.any() else 0.0
    return Model(languages, table, bias, temperature, min(threshold, 0.999))


def learning_rows(docs: DataFrame) -> DataFrame:
    """The rows that the contract lets a model see: crc32 of the id modulo 4 is not 2, and the language is known."""
    return docs.filter((crc_mod(F.col("doc_id"), 4) != 2) & F.col("lang").isNotNull())


def predicted(docs: DataFrame, model: Model, text: str = "text", prefix: str = "") -> DataFrame:
    """docs and lang_pred, score, rejected (score below the calibrated threshold, or `und`), named with the prefix."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    place = docs.columns.index(text)
    schema = with_fields(docs.schema, **{f"{prefix}lang_pred": "string", f"{prefix}score": "double", f"{prefix}rejected": "boolean"})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for b in small(batches):
            langs, scores = m.predict(as_bytes(b.column(place)))
            gone = [x == "und" or s < m.threshold for x, s in zip(langs, scores)]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(langs, pa.string()), pa.array(scores, pa.float64()), pa.array(gone, pa.bool_())], schema.names)

    return docs.mapInArrow(run, schema)
