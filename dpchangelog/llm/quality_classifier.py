"""Operator 5: document quality by attention-based multiple-instance learning.

A document is a bag of passages of PASSAGE words. Each passage is described by its shares of letters, signs and other
characters and by how much it repeats, and encoded by a learned layer. A gated attention unit (tanh times sigmoid) gives
each passage a weight within its document; the score is a logistic function of the weighted passage codes. Encoder,
attention and output are learned together from document labels alone.

Learning takes a bounded sample (sample_rows labelled documents, by a hash of their ids), of which only passage features
reach the driver. Scoring reads whole texts in one pass without a shuffle.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import prepare, quoted

PASSAGE = 64
_SIGNS = ".,;:!?'\"-()[]{}|#*$%&<>/\\=+_~@^`"
#: Byte -> class: 26 letters, upper case, digits, white space, each sign, bytes above ASCII, the rest.
CLASSES = 26 + 3 + len(_SIGNS) + 2
CLASS = np.full(256, CLASSES - 1, np.int64)
CLASS[128:] = CLASSES - 2
CLASS[ord("a") : ord("z") + 1] = np.arange(26)
CLASS[ord("A") : ord("Z") + 1] = 26
CLASS[ord("0") : ord("9") + 1] = 27
CLASS[[9, 10, 11, 12, 13, 32]] = 28
CLASS[[ord(c) for c in _SIGNS]] = np.arange(29, 29 + len(_SIGNS))
FEATURES = CLASSES + 6


def passages(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """(features of all passages, passages of each text); a text without words is one passage of zeros."""
    parts, sizes, more = [], np.zeros(len(texts), np.int64), []
    for i, t in enumerate(texts):
        words = (t or "").encode().split()
        seen: set = set()
        for k in range(0, len(words), PASSAGE):
            ws = words[k : k + PASSAGE]
            own = set(ws)
            # distinct words, words equal to the one before, words met earlier in the text, mean length, length, position
            more.append((len(own) / len(ws), sum(map(bytes.__eq__, ws, ws[1:])) / len(ws), len(own & seen) / len(own), sum(map(len, ws)) / len(ws) / 10, len(ws) / PASSAGE, k > 0))
            seen |= own
            parts.append(b" ".join(ws))
        sizes[i] = max(1, -(-len(words) // PASSAGE))
        if not words:
            parts.append(b"")
            more.append((0.0,) * 6)
    if not parts:
        return np.zeros((0, FEATURES), np.float32), sizes
    lengths = np.fromiter(map(len, parts), np.int64, len(parts))
    shares = np.bincount(np.repeat(np.arange(len(parts)) * CLASSES, lengths) + CLASS[np.frombuffer(b"".join(parts), np.uint8)], minlength=len(parts) * CLASSES)
    shares = np.sqrt(shares.reshape(-1, CLASSES) / np.maximum(lengths, 1)[:, None])
    return np.concatenate([shares, np.array(more)], axis=1).astype(np.float32), sizes


def _sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


@dataclass
class AttentionModel:
    """Parameters by name: W b encoder, V U w gated attention, c d output; shift and scale of the features."""

    p: dict
    shift: np.ndarray
    scale: np.ndarray

    @staticmethod
    def fresh(shift, scale, width: int = 24, gate: int = 12, seed: int = 7) -> "AttentionModel":
        r = np.random.default_rng(seed)
        f = len(shift)
        shapes = {"W": (f, width), "b": (width,), "V": (width, gate), "U": (width, gate), "w": (gate,), "c": (width,), "d": (1,)}
        return AttentionModel({k: r.normal(0, 1 / np.sqrt(s[0]), s) if len(s) > 1 or k in "wc" else np.zeros(s) for k, s in shapes.items()}, shift, scale)

    def forward(self, x, sizes):
        p, starts = self.p, np.r_[0, np.cumsum(sizes)[:-1]]
        x = np.clip((x - self.shift) / self.scale, -8, 8)
        h = np.tanh(x @ p["W"] + p["b"])
        t, g = np.tanh(h @ p["V"]), _sigmoid(h @ p["U"])
        e = (t * g) @ p["w"]
        e = np.exp(e - np.repeat(np.maximum.reduceat(e, starts), sizes))
        a = e / np.repeat(np.add.reduceat(e, starts), sizes)
        z = np.add.reduceat(a[:, None] * h, starts)
        return x, h, t, g, a, z, _sigmoid(z @ p["c"] + p["d"])

    def score(self, x, sizes) -> np.ndarray:
        return self.forward(x, sizes)[-1] if len(sizes) else np.zeros(0)

    def attention(self, x, sizes) -> np.ndarray:
        return self.forward(x, sizes)[4]

    def gradients(self, x, sizes, y, decay: float) -> dict:
        p, starts, n = self.p, np.r_[0, np.cumsum(sizes)[:-1]], len(y)
        x, h, t, g, a, z, s = self.forward(x, sizes)
        ds = (s - y) / n
        out = {"c": z.T @ ds, "d": np.array([ds.sum()])}
        dz = np.repeat(ds[:, None] * p["c"], sizes, axis=0)
        da = (dz * h).sum(1)
        de = a * (da - np.repeat(np.add.reduceat(a * da, starts), sizes))
        out["w"] = (t * g).T @ de
        dt, dg = de[:, None] * p["w"] * g * (1 - t * t), de[:, None] * p["w"] * t * g * (1 - g)
        out["V"], out["U"] = h.T @ dt, h.T @ dg
        dh = (a[:, None] * dz + dt @ p["V"].T + dg @ p["U"].T) * (1 - h * h)
        out["W"], out["b"] = x.T @ dh, dh.sum(0)
        return {k: v + decay * p[k] * (k in "WVUwc") for k, v in out.items()}

    def train(self, x, sizes, y, epochs: int = 30, batch: int = 128, rate: float = 0.01, decay: float = 1e-4, seed: int = 7) -> "AttentionModel":
        r, m, v, n = np.random.default_rng(seed), {}, {}, 0
        ends = np.cumsum(sizes)
        for epoch in range(epochs):
            for part in np.array_split(r.permutation(len(y)), max(1, len(y) // batch)):
                rows = np.concatenate([np.arange(ends[i] - sizes[i], ends[i]) for i in part])
                n += 1
                for k, grad in self.gradients(x[rows], sizes[part], y[part], decay).items():
                    m[k] = 0.9 * m.get(k, 0) + 0.1 * grad
                    v[k] = 0.99 * v.get(k, 0) + 0.01 * grad**2
                    self.p[k] = self.p[k] - rate * (1 - 0.9 * epoch / epochs) * (m[k] / (1 - 0.9**n)) / (np.sqrt(v[k] / (1 - 0.99**n)) + 1e-8)
        return self


@dataclass
class Constant:
    """Where labels of both kinds aren't there."""

    value: float

    def score(self, x, sizes) -> np.ndarray:
        return np.full(len(sizes), self.value)


def _remainder(c: str):
    return F.crc32(F.col(c).cast("string").cast("binary")) % 4


def train_classifier(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", sample_rows: int = 8000, sample_bytes: int = 64 << 20, label_id_col: str = "doc_id"):
    """Learn from at most sample_rows labelled documents whose crc32(id as text) mod 4 is not 2, and of them, in the order of a
    hash of their ids, from those whose passages take sample_bytes in all: that much reaches the driver, however long texts are.

    An id with several labels counts with the smallest, one with several texts with that of the smallest hash. Null ids and labels other than 0 and 1 are left out. Without labels
    every document scores 1; with one kind of label only, the share of label 1, smoothed.
    """
    prepare(docs.sparkSession)
    labels = labels.select(F.col(quoted(label_id_col)).alias("doc_id"), F.col(quoted(label_col)).alias("label"))
    rows = labels.where(F.col("label").isin(0, 1) & F.col("doc_id").isNotNull() & (_remainder("doc_id") != 2)).groupBy("doc_id").agg(F.min("label").alias("y"))
    chosen = rows.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_rows)  # bounded, so it may be broadcast
    found = docs.select(F.col(quoted(id_col)).alias("doc_id"), F.col(quoted(text_col)).alias("text")).join(F.broadcast(chosen), "doc_id").select("doc_id", "y", "text")

    def describe(batches):
        for b in batches:
            x, sizes = passages(b.column(2).to_pylist())
            ends = np.cumsum(sizes)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1).cast(pa.int64()), pa.array([x[e - n : e].tobytes() for e, n in zip(ends, sizes, strict=True)], pa.binary())], ["doc_id", "y", "x"])

    once = found.groupBy("doc_id", "y").agg(F.min_by("text", F.xxhash64("text")).alias("text"))
    upto = F.sum(F.octet_length("x")).over(Window.orderBy(F.xxhash64("doc_id"), "doc_id").rowsBetween(Window.unboundedPreceding, 0))  # over sample_rows rows
    bags = once.mapInArrow(describe, "doc_id long, y long, x binary").withColumn("upto", upto).where(F.col("upto") <= sample_bytes)
    got = sorted((r.doc_id, r.y, bytes(r.x)) for r in bags.collect())
    y = np.array([r[1] for r in got], float)
    if not len(y) or y.min() == y.max():
        return Constant(float((y.sum() + 1) / (len(y) + 1)) if len(y) else 1.0)
    bags = [np.frombuffer(r[2], np.float32).reshape(-1, FEATURES) for r in got]
    x, sizes = np.concatenate(bags).astype(float), np.array([len(b) for b in bags])
    return AttentionModel.fresh(x.mean(0), np.maximum(x.std(0), 0.02)).train(x, sizes, y)


def scored(docs: DataFrame, model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, score) of every whole text; null and empty texts are a passage of zeros."""
    spark = docs.sparkSession
    prepare(spark)
    shared = spark.sparkContext.broadcast(model)

    def run(batches):
        for b in batches:
            texts, scores = b.column(1).to_pylist(), []
            for k in range(0, len(texts), 500):
                scores.append(shared.value.score(*passages(texts[k : k + 500])))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(np.concatenate(scores) if scores else np.zeros(0), pa.float64())], ["doc_id", "score"])

    return docs.select(F.col(quoted(id_col)).cast("long").alias("doc_id"), F.col(quoted(text_col)).alias("text")).mapInArrow(run, "doc_id long, score double")


def documents_accepted(docs: DataFrame, labels: DataFrame, threshold: float = 0.7, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs with a score of at least threshold, with their columns and in one pass over the texts."""
    model = train_classifier(docs, labels, id_col, text_col)
    shared, at = docs.sparkSession.sparkContext.broadcast(model), docs.columns.index(text_col)

    def run(batches):
        for b in batches:
            texts, keep = b.column(at).to_pylist(), []
            for k in range(0, len(texts), 500):
                keep.append(shared.value.score(*passages(texts[k : k + 500])) >= threshold)
            yield b.filter(pa.array(np.concatenate(keep) if keep else np.zeros(0, bool)))

    return docs.mapInArrow(run, docs.schema)


def op5(spark: SparkSession, docs: DataFrame, labels: DataFrame, threshold: float = 0.7) -> DataFrame:
    """(doc_id, held_out, score, predicted). A null id is not held out."""
    out = scored(docs, train_classifier(docs, labels))
    return out.select("doc_id", F.coalesce(_remainder("doc_id") == 2, F.lit(False)).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
