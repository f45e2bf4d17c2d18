"""Toxicity: FTRL-proximal logistic regression over hashed word n-grams and skip-grams.

Features of a text: its words, their first four and five letters (an unseen
ending then still meets a known stem), its pairs of adjacent words and its
pairs with one or two words between, each hashed to one of 2**BUCKET_BITS
coordinates and counted once.  Every coordinate has its own learning rate, and the L1 term
leaves most weights exactly zero, so the model that goes to the executors is a
short list.  Training takes a bounded sample of labelled rows, dealt to a fixed
number of shards whose FTRL states are averaged.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from arcfield.deploy import ship

BUCKET_BITS = 20
#: Most labelled rows that training takes; chosen by hash of the id.
MAX_LABELLED = 16_000
SHARDS, EPOCHS = 1, 4
STEMS = (4, 5)
_STRIP = b"\"'.,;:!?()[]{}<>*#$%&|-_"
_MIX = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9), np.uint64(0x27D4EB2F165667C5))


class _Words(dict):
    """Hashes of each word without the marks around it and of its two stems; bounded."""

    def __missing__(self, word: bytes) -> bytes:
        from xxhash import xxh64_digest

        if len(self) > 300_000:
            self.clear()
        bare = word.strip(_STRIP)
        letters = bare[:24].decode("utf-8", "replace")
        value = xxh64_digest(bare, 17) + b"".join(xxh64_digest(letters[:k].encode(), 17 + k) for k in STEMS)
        if len(word) <= 64:
            self[word] = value
        return value


_WORDS = _Words()


def features(text: bytes | None) -> np.ndarray:
    """Coordinates of a whole text, repeats included; coordinate 0 is the intercept."""
    words = (text or b"").lower().split()
    if not words:
        return np.zeros(1, np.int64)
    h = np.frombuffer(b"".join(map(_WORDS.__getitem__, words)), ">u8").astype(np.uint64).reshape(len(words), -1)
    parts = [(h * _MIX[0]).ravel()]
    h = h[:, 0]
    for gap in (1, 2, 3):
        if len(h) > gap:
            parts.append((h[:-gap] * _MIX[gap] + h[gap:]) * _MIX[0])
    x = np.concatenate(parts)
    x = (x ^ (x >> np.uint64(29))) * _MIX[1]
    return np.concatenate((np.zeros(1, np.int64), (x >> np.uint64(64 - BUCKET_BITS)).astype(np.int64)))


@dataclass(frozen=True)
class Model:
    index: np.ndarray
    weight: np.ndarray

    def dense(self) -> np.ndarray:
        w = np.zeros(1 << BUCKET_BITS, np.float32)
        w[self.index] = self.weight
        return w


class Ftrl:
    """FTRL-proximal state: per-coordinate gradient sums ``z`` and squared sums ``n``."""

    def __init__(self, alpha=1.0, beta=1.0, l1=3.0, l2=1.0):
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2
        self.z = np.zeros(1 << BUCKET_BITS)
        self.n = np.zeros(1 << BUCKET_BITS)

    def weights(self, at) -> np.ndarray:
        z = self.z[at]
        small = np.abs(z) <= self.l1
        return np.where(small, 0.0, -(z - np.sign(z) * self.l1) / ((self.beta + np.sqrt(self.n[at])) / self.alpha + self.l2))

    def learn(self, at: np.ndarray, label: float) -> None:
        w = self.weights(at)
        g = 1.0 / (1.0 + np.exp(-np.clip(w.sum(), -30, 30))) - label
        n = self.n[at]
        self.z[at] += g - (np.sqrt(n + g * g) - np.sqrt(n)) / self.alpha * w
        self.n[at] = n + g * g


def held_out(doc_id: str = "doc_id"):
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % 5 == 0


def train(docs: DataFrame, labels: DataFrame, *, limit: int = MAX_LABELLED, shards: int = SHARDS, epochs: int = EPOCHS) -> Model:
    """A model of ``labels.toxic`` from at most ``limit`` labelled rows outside the held-out fold."""
    ship(docs.sparkSession)
    chosen = labels.where("toxic is not null and doc_id is not null").where(~held_out()).groupBy(F.col("doc_id").alias("__id")).agg(F.max("toxic").alias("__toxic"))
    chosen = chosen.orderBy(F.xxhash64("__id"), "__id").limit(limit)
    rows = docs.join(F.broadcast(chosen), F.col("doc_id") == F.col("__id")).select("__id", "__toxic", F.col("text").cast("binary").alias("__text"))

    def sparse(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            x = [np.unique(features(t)).astype("<u4").tobytes() for t in pdf["__text"]]
            yield pd.DataFrame({"id": pdf["__id"], "toxic": pdf["__toxic"].astype("int32"), "x": x})

    def fit(pdf: pd.DataFrame) -> pd.DataFrame:
        model, rng = Ftrl(), np.random.default_rng(5)
        pdf = pdf.sort_values("id", kind="stable")
        x, y = [np.frombuffer(b, "<u4").astype(np.int64) for b in pdf["x"]], pdf["toxic"].to_numpy(float)
        for _ in range(epochs):
            for k in rng.permutation(len(y)):
                model.learn(x[k], y[k])
        at = np.flatnonzero(model.n)
        return pd.DataFrame({"at": [at.astype("<i4").tobytes()], "z": [model.z[at].tobytes()], "n": [model.n[at].tobytes()]})

    def merge(pdf: pd.DataFrame) -> pd.DataFrame:
        model, k = Ftrl(), len(pdf)
        for r in pdf.itertuples():
            at = np.frombuffer(r.at, "<i4")
            model.z[at] += np.frombuffer(r.z) / k
            model.n[at] += np.frombuffer(r.n) / k
        w = model.weights(slice(None))
        at = np.flatnonzero(w)
        return pd.DataFrame({"at": [at.astype("<i4").tobytes()], "w": [w[at].astype("<f4").tobytes()]})

    made = rows.mapInPandas(sparse, "id long, toxic int, x binary").withColumn("shard", F.pmod(F.xxhash64("id"), F.lit(shards)))
    states = made.groupBy("shard").applyInPandas(fit, "at binary, z binary, n binary")
    found = states.withColumn("one", F.lit(0)).groupBy("one").applyInPandas(merge, "at binary, w binary").first()
    if found is None:
        return Model(np.zeros(0, np.int64), np.zeros(0, np.float32))
    return Model(np.frombuffer(found["at"], "<i4").astype(np.int64), np.frombuffer(found["w"], "<f4"))


def score(docs: DataFrame, model: Model, text: str = "text", out: str = "score") -> DataFrame:
    """``docs`` with ``out``: the probability that a text is toxic.

    Null and empty texts score the intercept alone; repeated rows score alike;
    without labels every score is 0.5 and the column keeps its meaning.
    """
    ship(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast((model.index, model.weight))

    @F.pandas_udf("double")
    def probability(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        w = Model(*sent.value).dense()
        for part in texts:
            sums = np.zeros(len(part))
            for i, t in enumerate(part):
                at = features(t)
                at = at[w[at] != 0]
                sums[i] = w[np.unique(at)].sum(dtype=np.float64)
            yield pd.Series(1.0 / (1.0 + np.exp(-np.clip(sums, -30, 30))))

    return docs.withColumn(out, probability(F.col(text).cast("binary")))


def digest(docs: DataFrame, labels: DataFrame) -> DataFrame:
    model = train(docs.select("doc_id", "text"), labels)
    out = score(docs.select("doc_id", "text"), model)
    return out.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
