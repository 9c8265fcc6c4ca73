"""Language identification: sparse multinomial logistic regression on TF-IDF of character n-grams.

Weights are trained with follow-the-regularised-leader (proximal, elastic net: L1 makes
them sparse), then one temperature is fitted on rows that training did not see, so that
scores are calibrated.

n-grams (1 to 3 characters of the lower-cased text, words padded by spaces; whatever is not
a to z, general punctuation or below U+00C0 counts as a space, all else as a letter) are hashed into ``DIM`` buckets with array arithmetic over whole
texts.  Document frequencies are counted over all rows that may be learned from: each task
sums its own, and one row a bucket is left.  The regression itself is fitted on a bounded
sample of them (``LangParams.sample`` distinct texts, those with the least hashes; a fifth
of them for the temperature).

Edge cases: a null text or one without letters is ``und`` with score 0; rows without a
language are not learned from; with one language only, that is predicted with score 1; with
none, all is ``und``; repeated rows are alike; an empty table gives an empty table.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BITS = 14
DIM = 1 << BITS
_PART = 1 << 16


@dataclass(frozen=True)
class LangParams:
    sample: int = 4_000
    epochs: int = 4
    alpha: float = 0.5
    beta: float = 1.0
    l1: float = 0.02
    l2: float = 0.02


def has_letters(text: str | None) -> bool:
    return bool(text) and any(map(str.isalpha, text))


def _letters(text: str) -> np.ndarray:
    """Code points of the lower-cased text; anything but letters is a space."""
    points = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    letter = ((points >= 97) & (points <= 122)) | ((points >= 0xC0) & (points != 0xD7) & (points != 0xF7) & ((points < 0x2000) | (points > 0x206F)))
    return np.where(letter, points, 32).astype(np.uint64)


def counts(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Buckets that occur, ascending, and how often, in a space, the letters with runs of
    spaces as one, and a space.  Works part by part, so memory is bounded: a part goes on
    from the last two characters of the one before, and an n-gram counts where it ends."""
    total = np.zeros(DIM, np.int64)
    a, b = np.uint64(0x9E3779B97F4A7C15), np.uint64(64 - BITS)
    before = np.zeros(0, np.uint64)
    parts = max(1, -(-len(text) // _PART))
    for i in range(parts):
        c = _letters(text[i * _PART : (i + 1) * _PART])
        keep = np.ones(len(c), bool)
        keep[1:] = (c[1:] != 32) | (c[:-1] != 32)
        if i and len(c) and c[0] == 32 and before[-1] == 32:
            keep[0] = False
        ends = ([np.uint64(32)] if i == 0 else [], [np.uint64(32)] if i == parts - 1 else [])
        c = np.concatenate((before, np.array(ends[0], np.uint64), c[keep], np.array(ends[1], np.uint64)))
        old = len(before)
        one = (c + np.uint64(1)) * a
        two = (one[:-1] ^ (c[1:] * np.uint64(0xC2B2AE3D27D4EB4F))) * a
        three = (two[:-1] ^ (c[2:] * np.uint64(0x165667B19E3779F9))) * a
        for size, h in enumerate((one, two, three), 1):
            total += np.bincount((h[max(0, old - size + 1) :] >> b).astype(np.int64), minlength=DIM)
        before = c[-2:]
    ids = np.flatnonzero(total)
    return ids, total[ids]


def _frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    df, n = np.zeros(DIM, np.int64), 0
    for batch in batches:
        for text in batch.column(0):
            if has_letters(text := text.as_py()):
                df[counts(text)[0]] += 1
                n += 1
    if n:
        ids = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(ids, -1)), pa.array(np.append(df[ids], n))], names=["bucket", "n"])


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        found = [counts(t.as_py()) for t in batch.column(1)]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([f[0] for f in found], pa.list_(pa.int32())), pa.array([f[1] for f in found], pa.list_(pa.int32()))], names=["lang", "ids", "n"])


class LangModel:
    """langs, idf (by bucket), weights (langs x buckets), bias, temperature."""

    def __init__(self, langs: list[str], idf: np.ndarray):
        self.langs, self.idf = langs, idf.astype(np.float32)
        self.weights, self.bias, self.temperature = np.zeros((len(langs), DIM), np.float32), np.zeros(len(langs), np.float32), 1.0

    def vector(self, ids: np.ndarray, n: np.ndarray) -> np.ndarray:
        x = (1 + np.log(n)) * self.idf[ids]
        return x / max(1e-9, float(np.sqrt(x @ x)))

    def logits(self, ids: np.ndarray, x: np.ndarray) -> np.ndarray:
        return self.weights[:, ids] @ x + self.bias

    def predict(self, text: str | None) -> tuple[str, float]:
        if not self.langs or not has_letters(text):
            return "und", 0.0
        ids, n = counts(text)
        p = _softmax(self.logits(ids, self.vector(ids, n)) / self.temperature)
        k = int(np.argmax(p))
        return self.langs[k], float(min(1.0, max(0.0, p[k])))


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def _ftrl(model: LangModel, rows: list, p: LangParams) -> None:
    """Per-coordinate FTRL-proximal; the last bucket of the arrays is the bias."""
    k = len(model.langs)
    z, n = np.zeros((k, DIM + 1)), np.zeros((k, DIM + 1))

    def weights(ids):
        zi, ni = z[:, ids], n[:, ids]
        w = -(zi - np.sign(zi) * p.l1) / ((p.beta + np.sqrt(ni)) / p.alpha + p.l2)
        return np.where(np.abs(zi) <= p.l1, 0.0, w)

    for _ in range(p.epochs):
        for y, ids, x in rows:
            ids, x = np.append(ids, DIM), np.append(x, 1.0)
            w = weights(ids)
            g = _softmax(w @ x)
            g[y] -= 1
            g = g[:, None] * x
            grown = n[:, ids] + g * g
            z[:, ids] += g - (np.sqrt(grown) - np.sqrt(n[:, ids])) / p.alpha * w
            n[:, ids] = grown
    w = weights(np.arange(DIM + 1))
    model.weights, model.bias = w[:, :DIM].astype(np.float32), w[:, DIM].astype(np.float32)


def _temperature(logits: np.ndarray, labels: np.ndarray) -> float:
    """The temperature with the least log loss, by golden-section search over its logarithm."""
    loss = lambda t: -np.log(np.maximum(_softmax(logits / np.exp(t))[np.arange(len(labels)), labels], 1e-12)).mean()
    a, b, r = -3.0, 3.0, (5**0.5 - 1) / 2
    for _ in range(40):
        c, d = b - r * (b - a), a + r * (b - a)
        a, b = (a, d) if loss(c) <= loss(d) else (c, b)
    return float(np.exp((a + b) / 2))


def train(docs: DataFrame, text: str = "text", lang: str = "lang", params: LangParams = LangParams()) -> LangModel:
    known = docs.select(F.col(lang).cast("string").alias("lang"), F.col(text).cast("string").alias("text")).where("lang is not null")
    df = {r["bucket"]: r["n"] for r in known.select("text").mapInArrow(_frequencies, "bucket bigint, n bigint").groupBy("bucket").agg(F.sum("n").alias("n")).collect()}
    total = df.pop(-1, 0)
    idf = np.full(DIM, np.log(1 + total) + 1, np.float32)
    for b, n in df.items():
        idf[b] = np.log((1 + total) / (1 + n)) + 1
    lettered = known.where(F.col("text").rlike(r"\p{L}")).withColumn("h", F.xxhash64("text").bitwiseAND(F.lit((1 << 63) - 1)))
    # hashes over a threshold stay in their task: little more than the sample is ordered
    texts = lettered.agg(F.approx_count_distinct("h", 0.05)).first()[0] or 1
    near = lettered.where(F.col("h") <= F.lit(int(min(1.0, 1.5 * params.sample / texts) * ((1 << 63) - 1024))))
    last = near.select("h").distinct().orderBy("h").limit(params.sample).agg(F.max("h")).first()[0]
    sample = near.where(F.col("h") <= F.lit(last)).groupBy("h").agg(F.min(F.struct("lang", "text")).alias("r")).select("r.*")
    rows = sorted(((r["lang"], np.array(r["ids"], np.int32), np.array(r["n"], np.float32)) for r in sample.mapInArrow(_rows, "lang string, ids array<int>, n array<int>").collect()), key=lambda r: (r[0], len(r[1]), r[1].tobytes()))
    langs = sorted({r[0] for r in rows})
    model = LangModel(langs, idf)
    order = np.random.default_rng(7).permutation(len(rows))
    data = [(langs.index(rows[i][0]), rows[i][1], model.vector(rows[i][1], rows[i][2])) for i in order]
    apart = len(data) // 5
    if len(langs) > 1:
        _ftrl(model, data[apart:], params)
        if apart:
            model.temperature = _temperature(np.array([model.logits(ids, x) for _, ids, x in data[:apart]]), np.array([y for y, _, _ in data[:apart]]))
    return model


def predict(docs: DataFrame, model: LangModel, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The kept columns, ``lang_pred`` and ``score``."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # langs x DIM numbers

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for batch in batches:
            found = [model.predict(t.as_py()) for t in batch.column(0)]
            yield pa.RecordBatch.from_arrays([*batch.columns[1:], pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64())], names=[*keep, "lang_pred", "score"])

    kinds = ", ".join(f"`{k}` {docs.schema[k].dataType.simpleString()}" for k in keep)
    return docs.select(F.col(text).cast("string").alias("_text"), *keep).mapInArrow(run, f"{kinds}, lang_pred string, score double")
