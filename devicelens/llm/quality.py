"""Quality scores by nearest-neighbour voting in a latent-semantic space.

Features of a text are counts of its byte trigrams, hashed into a fixed number of bins, damped, weighted by inverse document frequency and normalised. A
truncated singular value decomposition of a bounded number of labelled texts (``sample_rows``, those first by a seeded hash of their id)
gives the latent space. Their vectors, rows of fixed length, are broadcast; every document's exact cosine to all of them is
computed in blocks, and the labels of its nearest neighbours vote by similarity.

The score is the weighted share of label 1 among the neighbours, shrunk to the share in all labels: 0 to 1, higher if label 1 is
likelier. Null and empty texts have no features and get that share. Labels that are null or whose document is unknown teach
nothing; of several labels of one document the least counts, and of several texts under one id the first in order of bytes teaches.
With no labels at all every score is 0.5. Of equally near neighbours those go first whose place among the labelled rows, in the order of label and
features, is smaller. Rows that repeat are scored each. Only texts are inputs of a score.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import portions, remainder

SAMPLE_ROWS, BINS, LATENT, NEIGHBOURS, POWER, PRIOR = 3_000, 4_096, 64, 15, 6, 0.3
SEED, THRESHOLD, BLOCK_ROWS = "quality-1", 0.7, 256
_AT_ONCE = 1 << 20


def trigram_counts(text: bytes, bins: int = BINS) -> np.ndarray:
    """Counts of hashed byte trigrams of a whole text."""
    data = np.frombuffer(text, np.uint8).astype(np.uint32)
    counts = np.zeros(bins, np.int64)
    for at in range(0, max(0, len(data) - 2), _AT_ONCE):
        part = data[at : at + _AT_ONCE + 2]
        code = (part[:-2] << 16 | part[1:-1] << 8 | part[2:]) * np.uint32(2654435761)
        counts += np.bincount(code >> np.uint32(32 - (bins.bit_length() - 1)), minlength=bins)
    return counts


def damped(counts: np.ndarray) -> np.ndarray:
    """Rows of counts as log-damped frequencies of unit length."""
    x = np.log1p(counts.astype(np.float32))
    return x / np.maximum(np.linalg.norm(x, axis=-1, keepdims=True), 1e-12)


def leading_axes(rows: np.ndarray, n: int, rounds: int = 6) -> np.ndarray:
    """The n leading right singular vectors, by subspace iteration from a fixed start."""
    axes = np.random.default_rng(1).standard_normal((rows.shape[1], n + 16)).astype(np.float32)
    for _ in range(rounds):
        axes = np.linalg.qr(rows.T @ (rows @ axes))[0]
    turn = np.linalg.svd(rows @ axes, full_matrices=False)[2]
    return np.ascontiguousarray((axes @ turn.T)[:, :n], np.float32)


def nearest_columns(cosine: np.ndarray, k: int) -> np.ndarray:
    """The k greatest columns of each row, of equal ones the first, in no order."""
    least = -np.partition(-cosine, k - 1, axis=1)[:, k - 1 : k]
    chosen = cosine > least
    ties = cosine == least
    room = k - chosen.sum(axis=1, keepdims=True)
    chosen |= ties & (np.cumsum(ties, axis=1) <= room)
    return np.nonzero(chosen)[1].reshape(len(cosine), k)


class VotingModel:
    """The latent space and the labelled vectors in it."""

    def __init__(self, counts: np.ndarray, labels: np.ndarray, latent: int = LATENT):
        self.share = float(labels.mean()) if len(labels) else 0.5
        self.labels = labels.astype(np.float64)
        found = (counts > 0).sum(axis=0)
        self.weight = np.log((1 + len(counts)) / (1 + found)).astype(np.float32) + 1
        rows = damped(counts) * self.weight
        self.centre = rows.mean(axis=0) if len(rows) else np.zeros(counts.shape[1], np.float32)
        rows -= self.centre
        self.axes = leading_axes(rows, min(latent, max(1, len(rows))))
        self.vectors = self.placed(counts) if len(counts) else np.zeros((0, self.axes.shape[1]), np.float32)

    def placed(self, counts: np.ndarray) -> np.ndarray:
        """Unit vectors in the latent space."""
        x = (damped(counts) * self.weight - self.centre) @ self.axes
        return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)

    def scores(self, counts: np.ndarray, neighbours: int = NEIGHBOURS) -> np.ndarray:
        if not len(self.labels):
            return np.full(len(counts), self.share)
        cosine = self.placed(counts) @ self.vectors.T
        k = min(neighbours, cosine.shape[1])
        near = nearest_columns(cosine, k)
        weight = np.maximum(np.take_along_axis(cosine, near, axis=1).astype(np.float64), 0) ** POWER
        score = (np.sum(weight * self.labels[near], axis=1) + PRIOR * self.share) / (weight.sum(axis=1) + PRIOR)
        return np.where(counts.sum(axis=1) > 0, score, self.share)


def labelled_sample(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """text and label of at most sample_rows labelled documents that may teach: crc32 of the id modulo 4 isn't 2; a row an id."""
    known = labels.filter(F.col("quality").isNotNull() & (remainder("doc_id", 4) != 2)).groupBy("doc_id").agg(F.min("quality").alias("label"))
    ids = known.orderBy(F.xxhash64(F.lit(SEED), F.col("doc_id")), "doc_id").limit(sample_rows)
    return docs.select("doc_id", "text").join(F.broadcast(ids), "doc_id").groupBy("doc_id").agg(F.min("text").alias("text"), F.min("label").alias("label")).select("text", "label")


def fitted(sample: pa.Table) -> pa.Table:
    """The model of the counts and labels of a sample, as bytes."""
    sample = sample.sort_by([("label", "ascending"), ("counts", "ascending")])
    counts = np.array([np.frombuffer(x.as_py(), np.uint16) for x in sample.column("counts")], np.uint16).reshape(-1, BINS)
    return pa.table({"model": pa.array([pickle.dumps(VotingModel(counts, np.array(sample.column("label").to_pylist(), np.float64)))], pa.binary())})


def fit(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS) -> VotingModel:
    """A model from a bounded sample, whose bins' counts meet in one task; only the model comes to the driver."""

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in portions(batches, 0):
            counts = [np.minimum(trigram_counts((t or "").encode()), 65_535).astype(np.uint16).tobytes() for t in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(counts, pa.binary()), batch.column(1)], ["counts", "label"])

    sample = labelled_sample(docs, labels, sample_rows).mapInArrow(features, "counts binary, label int")
    model = sample.withColumn("task", F.lit(0)).groupBy("task").applyInArrow(fitted, "model binary").first()
    return pickle.loads(model[0]) if model else VotingModel(np.zeros((0, BINS), np.uint16), np.zeros(0))


def quality_scores(docs: DataFrame, model: VotingModel, threshold: float = THRESHOLD, keep: list[str] | None = None) -> DataFrame:
    """doc_id or the columns named in keep, with score and predicted; map-only. A task places and compares block after block."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # sample_rows vectors of fixed length
    kept = docs.select(*(keep or ["doc_id"]))
    names = kept.columns
    place = names.index("text") if "text" in names else len(names)

    def scored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in portions(batches, place):
            texts = batch.column(place)
            found = [
                shared.value.scores(np.array([trigram_counts((t or "").encode()) for t in texts[a : a + BLOCK_ROWS].to_pylist()]).reshape(-1, BINS))
                for a in range(0, batch.num_rows, BLOCK_ROWS)
            ]
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(names)], pa.array(np.concatenate(found or [np.empty(0)]), pa.float64())], [*names, "score"])

    rows = kept if "text" in names else docs.select(*names, "text")  # a text goes to Python once
    return rows.mapInArrow(scored, T.StructType([*kept.schema.fields, T.StructField("score", T.DoubleType())])).withColumn("predicted", (F.col("score") >= threshold).cast("int"))
