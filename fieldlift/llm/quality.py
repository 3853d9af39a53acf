"""Quality classifier: nearest-neighbour voting in a latent-semantic space.

A text's features are hashed byte trigrams and hashed pairs of neighbouring words' outlines over the whole text, square-root damped and weighted by
inverse frequency. A bounded sample of labelled rows gives the frequency weights, the latent directions (truncated
singular vectors by subspace iteration) and the labelled latent vectors. Those are broadcast (SAMPLE rows of RANK numbers
for each label at most); every document gets exact cosines with all of them, in blocks, and the NEAR nearest vote
with their similarity as weight.

Defined cases: null and empty texts score 0 (no evidence of quality) and have predicted 0; without usable labels of both
kinds every non-empty text scores the share of label 1, or 1 where no label exists; repeated rows score alike; conflicting labels of one
doc_id count as 0; texts are read whole; extra columns pass through unchanged.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from .common import free_name, slices, trimmed, utf8

#: Parameters: labelled rows sampled per label (the fit's bound), hashed features, latent rank, neighbours, sharpness of the similarity weight.
SAMPLE, DIMS, RANK, NEAR, POWER = 2000, 4096, 48, 15, 8

_OUTLINE = np.zeros(256, np.int64)
for _a, _b, _code in ((65, 91, 1), (97, 123, 2), (48, 58, 3), (128, 256, 2)):
    _OUTLINE[_a:_b] = _code
for _i, _c in enumerate(b"!#$%&*|.,;:?"):
    _OUTLINE[_c] = 4 + _i


def features(raw: bytes, dims: int = DIMS) -> np.ndarray:
    """Damped counts of hashed trigrams (first three quarters) and word outlines with repetition (last quarter)."""
    out = np.zeros(dims, np.float32)
    if not raw:
        return out
    b = np.frombuffer(raw, np.uint8).astype(np.int64)
    low = dims * 3 // 4
    if len(b) >= 3:
        h = (b[:-2] * 7919 + b[1:-1] * 104729 + b[2:] * 1299709) % 1000003
        out[:low] = np.bincount(h % low, minlength=low)
    words = raw.split()
    if words:
        sizes = np.array([len(w) for w in words])
        first, last = np.array([w[0] for w in words]), np.array([w[-1] for w in words])
        same = np.r_[False, np.array([a == c for a, c in zip(words, words[1:])], bool)]
        outline = ((np.minimum(sizes, 7) * 20 + _OUTLINE[first]) * 20 + _OUTLINE[last]) * 2 + same
        h = outline * 31 + np.r_[0, outline[:-1]] * 17
        out[low:] = np.bincount((h * 2654435761 >> 7) % (dims - low), minlength=dims - low)
        out[low:] *= 2
    out = np.sqrt(out)
    return out / np.linalg.norm(out)


def learnable(labels: DataFrame) -> DataFrame:
    """(doc_id, quality) of labelled rows outside the held-out third; one row for each doc_id."""
    return labels.filter(F.col("doc_id").isNotNull() & F.col("quality").isin(0, 1)).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min("quality").alias("quality")).filter(~held_out(F.col("doc_id")))


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1, F.lit(False))


class Model:
    def __init__(self, weights: np.ndarray, directions: np.ndarray, points: np.ndarray, labels: np.ndarray, fallback: float):
        self.weights, self.directions, self.points, self.labels, self.fallback = weights, directions, points, labels, fallback

    def latent(self, x: np.ndarray) -> np.ndarray:
        z = (x * self.weights) @ self.directions
        return z / np.maximum(np.linalg.norm(z, axis=1, keepdims=True), 1e-9)

    def scores(self, raws: list[bytes], near: int = NEAR) -> np.ndarray:
        out = np.zeros(len(raws))
        filled = [i for i, r in enumerate(raws) if r]
        if not len(self.points):
            out[filled] = self.fallback
            return out
        for at in range(0, len(filled), 256):
            block = filled[at : at + 256]
            cosine = self.latent(np.stack([features(raws[i], len(self.weights)) for i in block])) @ self.points.T
            n = min(near, cosine.shape[1])
            top = np.argpartition(-cosine, n - 1, axis=1)[:, :n]
            w = np.maximum(np.take_along_axis(cosine, top, 1), 1e-6).astype(np.float64) ** POWER
            out[block] = (w * self.labels[top]).sum(axis=1) / w.sum(axis=1)
        return np.clip(out, 0.0, 1.0)


def learn(x: np.ndarray, y: np.ndarray, rank: int) -> Model:
    """Frequency weights, latent directions and labelled latent points from features x (overwritten) and labels y."""
    dims = x.shape[1]
    if len(set(y.tolist())) < 2:
        return Model(np.ones(dims, np.float32), np.empty((dims, 0), np.float32), np.empty((0, 0), np.float32), y, float(y.mean()) if len(y) else 1.0)
    weights = np.log((1 + len(x)) / (1 + np.count_nonzero(x, axis=0))).astype(np.float32) + np.float32(0.5)
    x *= weights
    basis = np.random.default_rng(3).standard_normal((dims, min(rank + 8, *x.shape))).astype(np.float32)
    for _ in range(5):
        basis, _ = np.linalg.qr(x.T @ (x @ basis))
    _, _, turn = np.linalg.svd(x @ basis, full_matrices=False)
    directions = np.ascontiguousarray((basis @ turn.T)[:, :rank])
    z = x @ directions
    points = z / np.maximum(np.linalg.norm(z, axis=1, keepdims=True), 1e-9)
    return Model(weights, directions, points.astype(np.float32), y, float(y.mean()))


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, dims: int = DIMS, rank: int = RANK) -> Model:
    """Learns from at most `sample` labelled rows of each label, picked by a hash of the id.

    Their features meet in one executor task, whose input is bounded by the sample; only the small model reaches the driver.
    """
    known = learnable(labels)
    order = [F.xxhash64("doc_id", F.lit(11)), F.col("doc_id")]
    picked = known.filter("quality = 0").orderBy(*order).limit(sample).unionByName(known.filter("quality = 1").orderBy(*order).limit(sample))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text", 4 << 20):
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array([features(r, dims).astype(np.float16).tobytes() for r in utf8(part.column(2))], pa.binary())], ["doc_id", "quality", "x"])

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x, y = np.zeros((2 * sample, dims), np.float32), []
        for batch in batches:
            for label, raw in zip(batch.column(1).to_pylist(), batch.column(2)):
                x[len(y)] = np.frombuffer(raw.as_buffer(), np.float16)
                y.append(label)
        model = learn(x[: len(y)], np.array(y, np.float64), rank)
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(model)], pa.binary())], ["model"])

    # the picked ids are bounded by 2 * sample, hence the broadcast
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(picked), "doc_id").filter(F.length("text") > 0).select("doc_id", F.col("quality").cast("int").alias("quality"), "text")
    sampled = rows.mapInArrow(trimmed(run), "doc_id long, quality int, x binary").groupBy("doc_id").agg(F.min("quality").alias("quality"), F.min("x").alias("x"))
    got = sampled.repartition(1).sortWithinPartitions("doc_id").mapInArrow(trimmed(solve), "model binary").first()
    return pickle.loads(got["model"]) if got else learn(np.zeros((0, dims), np.float32), np.empty(0), rank)


def score_documents(docs: DataFrame, model: Model, name: str = "quality_score") -> DataFrame:
    """docs with the score appended in a column of the given name (underscores follow it where it is taken); all others pass through."""
    name = free_name(docs, name)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    names = [*docs.columns, name]
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            for part in slices(batch, "text", 4 << 20):
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(m.scores(utf8(part.column(at))), pa.float64())], names)

    return docs.mapInArrow(trimmed(run), StructType([*docs.schema.fields, StructField(name, DoubleType())]))


def classify(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every document."""
    scored = score_documents(docs.select("doc_id", "text"), fit(docs, labels), "score")
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", F.when(F.col("score") >= 0.5, 1).otherwise(0).alias("predicted"))


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The documents that the classifier accepts, columns unchanged."""
    score = free_name(docs, "score")
    return score_documents(docs, fit(docs, labels), score).filter(F.col(score) >= 0.5).drop(score)
