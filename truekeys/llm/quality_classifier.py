"""Quality classifier: logistic regression on hashed word n-grams, trained with follow-the-regularised-leader updates.

Tokens are runs of letters and digits or runs of other marks.  Features are hashed unigrams and bigrams of tokens and of
their shapes (lower, title, upper, digits, mixed, marks); a bigram of two equal tokens counts as one common feature, so
that stuttering shows whatever the word.  Counts are damped by a logarithm and scaled to length one.  A score is the
sparse dot product of a text's features with the weights, through the logistic function.

Training reads a bounded sample: of each class at most ``per_class`` labelled rows, the first by a hash of doc_id, and
of the documents that have them at most twice that many rows, in an order that depends on no partitioning; the
intercept is then moved to the class shares among all training labels.  Rows whose crc32(doc_id) mod 5 is 0 are held
out.  Labels, lang, source and doc_id are no features.  Defined results: null and empty texts are scored by the
intercept; without labels of both classes every score is the smoothed share of good labels; other columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from xxhash import xxh3_64_intdigest

from .text import mix

_TOKEN = re.compile(r"\w+|[^\w\s]+")
_K = np.uint64(0x9E3779B97F4A7C15)


@dataclass(frozen=True)
class Settings:
    bits: int = 18
    per_class: int = 2500
    epochs: int = 10
    alpha: float = 8.0
    beta: float = 1.0
    l1: float = 1e-4
    l2: float = 1e-4
    threshold: float = 0.3


class _Tokens(dict):
    """token -> (hash, shape): a bounded per-worker cache."""

    LIMIT = 1 << 18

    def __missing__(self, token: str) -> int:
        if len(self) >= self.LIMIT:
            self.clear()
        shape = 5 if not token[0].isalnum() else 3 if token.isdigit() else 0 if token.islower() else 2 if token.isupper() and len(token) > 1 else 1 if token.istitle() else 4
        value = self[token] = (xxh3_64_intdigest(token.encode("utf-8", "surrogatepass")) & ~7) | shape
        return value


_TOKENS = _Tokens()


def features(text: str | None, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """(index, value) of a text's features; the values have length one."""
    tokens = _TOKEN.findall(text or "")
    if not tokens:
        return np.empty(0, np.int32), np.empty(0, np.float32)
    h = np.fromiter(map(_TOKENS.__getitem__, tokens), np.uint64, len(tokens))
    shape = h & np.uint64(7)
    with np.errstate(over="ignore"):
        two = np.where(h[1:] == h[:-1], np.uint64(1), mix(h[:-1] * _K + h[1:]))
        every = np.concatenate([mix(h), two, shape + np.uint64(16), mix(shape[:-1] * np.uint64(8) + shape[1:] + np.uint64(64))])
    index, n = np.unique((mix(every) & np.uint64((1 << bits) - 1)).astype(np.int32), return_counts=True)
    value = np.log1p(n).astype(np.float32)
    return index, value / np.sqrt((value * value).sum())


@dataclass(frozen=True)
class Model:
    weights: np.ndarray
    intercept: float

    def score(self, index: np.ndarray, value: np.ndarray) -> float:
        return 1 / (1 + math.exp(-max(-40.0, min(40.0, self.intercept + float(self.weights[index] @ value)))))


def ftrl(rows: list[tuple[int, np.ndarray, np.ndarray]], s: Settings) -> Model:
    """Per-coordinate proximal updates over (label, index, value) rows; the intercept is a coordinate of its own."""
    size = (1 << s.bits) + 1
    z, n = np.zeros(size), np.zeros(size)

    def weights(at: np.ndarray) -> np.ndarray:
        w = -(z[at] - np.sign(z[at]) * s.l1) / ((s.beta + np.sqrt(n[at])) / s.alpha + s.l2)
        return np.where(np.abs(z[at]) <= s.l1, 0.0, w)

    rng = np.random.default_rng(7)
    for _ in range(s.epochs):
        for k in rng.permutation(len(rows)):
            label, index, value = rows[k]
            at, x = np.append(index, size - 1), np.append(value, 1.0)
            w = weights(at)
            g = (1 / (1 + math.exp(-max(-40.0, min(40.0, float(w @ x))))) - label) * x
            z[at] += g - (np.sqrt(n[at] + g * g) - np.sqrt(n[at])) / s.alpha * w
            n[at] += g * g
    w = weights(np.arange(size))
    return Model(w[:-1].astype(np.float32), float(w[-1]))


def remainder() -> Column:
    """crc32 of doc_id as text, modulo 5: 0 is held out."""
    return F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")), F.lit(5))


def train(docs: DataFrame, labels: DataFrame, s: Settings = Settings()) -> Model:
    known = labels.where(F.col("quality").isin(0, 1)).select("doc_id", F.col("quality").cast("int").alias("quality")).where(remainder() != 0)
    share = {r["quality"]: r["count"] for r in known.groupBy("quality").count().collect()}  # two rows
    prior = math.log((share.get(1, 0) + 1) / (share.get(0, 0) + 1))
    if len(share) < 2:
        return Model(np.zeros(1 << s.bits, np.float32), prior)
    picked = None
    for label in (0, 1):
        own = known.where(F.col("quality") == label).orderBy(F.xxhash64("doc_id"), "doc_id").limit(s.per_class)
        picked = own if picked is None else picked.unionByName(own)
    bits = s.bits

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            both = [features(t.as_py(), bits) for t in b.column(2)]
            yield pa.RecordBatch.from_pydict({"place": b.column(0), "quality": b.column(1), "i": pa.array([x.tobytes() for x, _ in both], pa.binary()), "v": pa.array([x.tobytes() for _, x in both], pa.binary())})

    place = F.struct(F.xxhash64("doc_id"), F.col("doc_id").cast("string"), F.xxhash64("text")).cast("string")
    sample = docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id").select(place.alias("place"), "quality", "text").mapInArrow(run, "place string, quality int, i binary, v binary")
    # ids that documents or labels repeat could make it longer; equal places have equal texts and labels, or differ in labels
    rows = sample.orderBy("place", "quality").limit(2 * s.per_class).collect()
    fit = ftrl([(r["quality"], np.frombuffer(r["i"], np.int32), np.frombuffer(r["v"], np.float32)) for r in rows], s)
    seen = [r["quality"] for r in rows]
    return Model(fit.weights, fit.intercept + prior - math.log((seen.count(1) + 1) / (seen.count(0) + 1)))


def classify(docs: DataFrame, model: Model, s: Settings = Settings()) -> DataFrame:
    """docs(doc_id, text) -> doc_id, held_out, score, predicted; one pass over whole texts."""
    shared = docs.sparkSession.sparkContext.broadcast((model.weights, model.intercept))  # 2**bits floats
    bits = s.bits

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = Model(*shared.value)
        for b in batches:
            yield pa.RecordBatch.from_pydict({"doc_id": b.column(0), "score": pa.array([own.score(*features(t.as_py(), bits)) for t in b.column(1)], pa.float64())})

    kind = docs.schema["doc_id"].dataType.simpleString()
    scored = docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, score double")
    return scored.select("doc_id", (remainder() == 0).alias("held_out"), "score", (F.col("score") >= s.threshold).cast("int").alias("predicted"))
