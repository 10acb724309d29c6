"""Quality classifier: logistic regression on hashed word n-grams, trained by
follow-the-regularised-leader updates, scored as a sparse dot product.

Four streams of a text are hashed into one table of weights: its words alone and
in pairs, its runs of punctuation, the case pattern of its words, and a mark for
each word that repeats the word before it. A feature's value is the square root
of its share of all features, so long and short texts have vectors of length one.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import add_columns, field, table
from .wordhash import ALNUM, mix, word_hashes

#: log2 of the number of weights; most labelled rows that training reads.
BITS, MAX_LABELLED = 18, 6000
THRESHOLD = 0.3

_LETTERS = bytes(b if (0x21 <= b <= 0x2F or 0x3A <= b <= 0x40 or 0x5B <= b <= 0x60 or 0x7B <= b <= 0x7E) else 0x20 for b in range(256))
_CASE = np.array([1 if 0x61 <= b <= 0x7A else 2 if 0x41 <= b <= 0x5A else 3 if 0x30 <= b <= 0x39 else 4 if b >= 0x80 else 0 for b in range(256)], np.uint64)
_SALT = {k: np.uint64(v) for v, k in enumerate(("pair", "punct", "case", "again"), 0x1F3D5B79)}


def features(raw: bytes, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """Positions in the table of weights, ascending, and values; the whole text counts."""
    words = word_hashes(raw, ALNUM)
    marks = word_hashes(raw, _LETTERS)
    parts = [words]
    with np.errstate(over="ignore"):
        if len(words) > 1:
            parts.append(mix(words[1:] * np.uint64(3) + words[:-1] + _SALT["pair"]))
            parts.append(np.repeat(mix(_SALT["again"][None]), int((words[1:] == words[:-1]).sum())))
        parts.append(mix(marks + _SALT["punct"]))
        data = np.frombuffer(raw, np.uint8)
        if len(data):
            kind = _CASE[data]
            before = np.empty_like(kind)
            before[0], before[1:] = 0, kind[:-1]
            first = np.flatnonzero((kind > 0) & (before == 0))
            second = kind[np.minimum(first + 1, len(kind) - 1)]
            parts.append(mix(kind[first] * np.uint64(8) + second + _SALT["case"]))
    found = np.concatenate(parts) >> np.uint64(64 - bits)
    at, n = np.unique(found, return_counts=True)
    return at.astype(np.int64), np.sqrt(n / max(1, len(found)))


class Ftrl:
    """Per-coordinate follow-the-regularised-leader for logistic loss; the last weight is the bias."""

    def __init__(self, bits: int = BITS, alpha: float = 1.0, beta: float = 1.0, l1: float = 0.002, l2: float = 0.01):
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2
        self.z, self.n = np.zeros((1 << bits) + 1), np.zeros((1 << bits) + 1)

    def weights(self, at: np.ndarray | slice = slice(None)) -> np.ndarray:
        z = self.z[at]
        return np.where(np.abs(z) <= self.l1, 0.0, (np.sign(z) * self.l1 - z) / ((self.beta + np.sqrt(self.n[at])) / self.alpha + self.l2))

    def learn(self, at: np.ndarray, x: np.ndarray, label: int) -> None:
        at, x = np.append(at, len(self.z) - 1), np.append(x, 1.0)
        w = self.weights(at)
        g = (sigmoid(w @ x) - label) * x
        n = self.n[at]
        self.z[at] += g - (np.sqrt(n + g * g) - np.sqrt(n)) / self.alpha * w
        self.n[at] = n + g * g


def sigmoid(x: float) -> float:
    return float(1 / (1 + np.exp(-np.clip(x, -35, 35))))


def train(labelled: DataFrame, text: str, label: str, order: Column, bits: int = BITS, epochs: int = 4, updates: int = 20_000) -> bytes:
    """Weights as float32 bytes, learnt in one task from a bounded labelled table, in a fixed order of its rows.

    The rows are gone through ``epochs`` times, and small tables until ``updates`` rows are seen, 40 times at most.
    """

    def run(batches):
        rows = []
        for batch in batches:
            for raw, y in zip(batch.column(0).cast(pa.binary()).to_pylist(), batch.column(1).to_pylist(), strict=True):
                rows.append((*features(raw or b"", bits), y))
        model = Ftrl(bits)
        for _ in range(max(epochs, min(40, updates // max(1, len(rows))))):
            for at, x, y in rows:
                model.learn(at, x, y)
        yield pa.RecordBatch.from_arrays([pa.array([model.weights().astype(np.float32).tobytes()], pa.binary())], names=["weights"])

    rows = labelled.select(F.col(text).cast("string").alias("text"), F.col(label).cast("int").alias("label"), order.alias("order"))
    found = rows.repartition(1).sortWithinPartitions("order", "text", "label").select("text", "label").mapInArrow(run, "weights binary").collect()
    return bytes(found[0].weights) if found else np.zeros((1 << bits) + 1, np.float32).tobytes()


def score(docs: DataFrame, weights: bytes, text: str = "text", out: str = "score", bits: int = BITS, keep: list[str] | None = None) -> DataFrame:
    """``docs`` with the probability of label 1; null counts as empty, whose score comes from the bias alone."""
    shared = docs.sparkSession.sparkContext.broadcast(weights)

    def make():
        w = np.frombuffer(shared.value, np.float32).astype(np.float64)

        def work(texts):
            for raw in texts:
                at, x = features(raw, bits)
                yield (sigmoid(w[at] @ x + w[-1]),)

        return work

    return add_columns(docs, text, [field(out, "double")], make, keep)


def held_out(key: Column, folds: int = 5) -> Column:
    return F.coalesce(F.crc32(key.cast("string").cast("binary")) % folds == 0, F.lit(False))


def fit_quality(docs: DataFrame, labels: DataFrame, text: str = "text", max_labelled: int = MAX_LABELLED) -> bytes:
    """Learn ``labels.quality`` from at most ``max_labelled`` rows outside the held-out fold.

    The labels of the smallest hashes of doc_id are taken; of several labels of
    a document the largest counts; rows without a label or an id are left out.
    """
    chosen = (
        labels.select("doc_id", F.col("quality").alias("__label"))
        .where("doc_id IS NOT NULL AND __label IN (0, 1)").where(~held_out(F.col("doc_id")))
        .groupBy("doc_id").agg(F.max("__label").alias("__label"))
        .orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_labelled)
    )
    rows = docs.select("doc_id", F.col(text).alias("__body")).join(F.broadcast(chosen), "doc_id")  # at most max_labelled rows of two numbers
    return train(rows, "__body", "__label", F.xxhash64("doc_id"))


def judge(docs: DataFrame, labels: DataFrame, text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """``docs`` with score and predicted (1 from a score of 0.3 on).

    Without any usable label all weights are zero and every score is one half.
    """
    return score(docs, fit_quality(docs, labels, text), text, keep=keep).withColumn("predicted", (F.col("score") >= THRESHOLD).cast("int"))


def op7_ftrl_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = judge(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "labels"), keep=["doc_id"])
    return found.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")
