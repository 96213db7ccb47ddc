"""Quality by nearest labelled neighbours in a latent-semantic space.

A document is the counts of its terms, hashed to ``TERMS`` buckets: the shapes of its
words, the shapes of neighbouring words, neighbours that are equal, and the distinct words
by how often they occur (in powers of two).  Counts are damped by a logarithm, weighted by
inverse document frequency and rotated into the leading singular directions of a bounded
labelled sample; no term has a weight set by hand.  The sample's vectors are broadcast
(their number is a parameter, so their size is bounded); every document is compared with
all of them by blocked cosine products, and the ``neighbours`` most similar vote with
their label, weighted by similarity.

Empty and null texts have no terms; they get the share of label 1 in the sample, as
does everything if no document is labelled 1 or 0 (then 0.5).  Repeated rows get equal
scores; every text is read to its end.
"""

from __future__ import annotations

import pickle
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_sample, byte_texts, id_bucket, mixed, with_columns

TERMS = 4096
#: Character classes of a shape: lower, upper, digit, other letter or byte; other ASCII stands for itself.
_CLASSES = bytes(97 if 97 <= b <= 122 or b >= 128 else 65 if 65 <= b <= 90 else 57 if 48 <= b <= 57 else b for b in range(256))


def _shape(word: bytes) -> bytes:
    """The classes of a word's characters, runs made one, and a coarse length: ``Hello,,`` is ``Aa,``."""
    raw = np.frombuffer(word.translate(_CLASSES), np.uint8)
    return raw[np.append(True, raw[1:] != raw[:-1])].tobytes() + bytes([min(len(word), 40) // 4])


class TermCounter(dict):
    """Numbers words (the memo holds ``limit`` of them); ``counts`` gives a document's bucket counts."""

    #: buckets: word shapes, pairs of shapes, frequency classes, equal neighbours
    SHAPES, PAIRS, CLASSES = TERMS // 2, TERMS // 2 - 32, 31

    def __init__(self, limit: int = 150_000):
        super().__init__()
        self.limit = limit
        self.shapes = np.empty(1024, np.uint64)

    def __missing__(self, word: bytes) -> int:
        at = self[word] = len(self)
        if at == len(self.shapes):
            self.shapes = np.concatenate([self.shapes, np.empty(at, np.uint64)])
        self.shapes[at] = xxhash.xxh3_64_intdigest(_shape(word))
        return at

    def counts(self, text: bytes | None) -> np.ndarray:
        words = (text or b"").split()
        if not words:
            return np.zeros(TERMS, np.float32)
        if len(self) >= self.limit:
            self.clear()
        at = np.fromiter(map(self.__getitem__, words), np.int64, len(words))
        shape = self.shapes[at]
        pairs = mixed(shape[:-1] * np.uint64(31) + shape[1:]) % np.uint64(self.PAIRS)
        often = np.log2(np.unique(at, return_counts=True)[1]).astype(np.int64)
        base = self.SHAPES + self.PAIRS
        terms = [(shape % np.uint64(self.SHAPES)).astype(np.int64), pairs.astype(np.int64) + self.SHAPES, base + np.minimum(often, self.CLASSES - 1)]
        got = np.bincount(np.concatenate(terms), minlength=TERMS).astype(np.float32)
        got[TERMS - 1] = (at[1:] == at[:-1]).sum()
        return got


@dataclass
class NeighbourVote:
    weights: np.ndarray  # inverse document frequencies, by bucket
    basis: np.ndarray  # buckets x dimensions
    vectors: np.ndarray  # labelled documents x dimensions, unit length
    labels: np.ndarray
    neighbours: int
    sharpness: float

    def embed(self, counts: np.ndarray) -> np.ndarray:
        tf = np.log1p(counts)
        tf *= self.weights
        tf /= np.maximum(np.linalg.norm(tf, axis=1, keepdims=True), 1e-12)
        return self.turned(tf)

    def turned(self, tf: np.ndarray) -> np.ndarray:
        got = tf @ self.basis
        return got / np.maximum(np.linalg.norm(got, axis=1, keepdims=True), 1e-12)

    def score(self, counts: np.ndarray) -> np.ndarray:
        """Similarity-weighted share of label 1 among the nearest labelled vectors."""
        base = float(self.labels.mean())
        near = self.embed(counts) @ self.vectors.T
        k = min(self.neighbours, len(self.labels))
        top = np.argpartition(-near, k - 1, axis=1)[:, :k]
        similar = np.maximum(np.take_along_axis(near, top, 1), 0.0) ** self.sharpness
        total = similar.sum(1)
        score = np.where(total > 1e-12, (similar * self.labels[top]).sum(1) / np.maximum(total, 1e-12), base)
        return np.clip(np.where(counts.any(1), score, base), 0.0, 1.0)


def fit(docs: DataFrame, labels: DataFrame, sample_docs: int = 2_000, dimensions: int = 96, neighbours: int = 15, sharpness: float = 4.0) -> NeighbourVote | None:
    """Fit on about ``sample_docs`` labelled documents (never over 5/4 of it); None without any."""
    marked = labels.where(F.col("quality").isin(0, 1) & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("quality").cast("int").alias("quality"))
    chosen = bounded_sample(marked, "doc_id", sample_docs)
    joined = docs.where(F.col("text").isNotNull()).select("doc_id", "text").join(F.broadcast(chosen), "doc_id")

    def make():
        counter = TermCounter()

        def work(batch: pa.RecordBatch) -> list[pa.Array]:
            got = [counter.counts(x) for x in byte_texts(batch.column("text"))]
            where = [np.flatnonzero(x) for x in got]
            return [pa.array([pickle.dumps((i.astype(np.uint16), x[i])) for i, x in zip(where, got)], pa.binary())]

        return work

    rows = with_columns(joined, "terms binary", make).select("doc_id", "quality", "terms").collect()
    rows = sorted(rows, key=lambda r: (r["doc_id"], bytes(r["terms"])))[: sample_docs * 5 // 4]
    if not rows:
        return None
    counts = np.zeros((len(rows), TERMS), np.float32)
    for i, row in enumerate(rows):
        at, values = pickle.loads(bytes(row["terms"]))
        counts[i, at] = values
    labels_ = np.array([r["quality"] for r in rows], np.float64)
    held = len(rows)
    del rows
    weights = (np.log((1 + held) / (1 + (counts > 0).sum(0))) + 0.1).astype(np.float32)
    # in place: the driver holds this one matrix
    tf = np.log1p(counts, out=counts)
    tf *= weights
    tf /= np.maximum(np.linalg.norm(tf, axis=1, keepdims=True), 1e-12)
    # leading right singular vectors by the smaller of the two Gram matrices
    if held <= TERMS:
        values, left = np.linalg.eigh(tf @ tf.T)
        keep = np.argsort(-values)[: min(dimensions, held)]
        keep = keep[values[keep] > 1e-6 * max(values[keep[0]], 1e-12)]
        basis = tf.T @ left[:, keep] / np.sqrt(values[keep])
    else:
        values, right = np.linalg.eigh(tf.T @ tf)
        basis = right[:, np.argsort(-values)[:dimensions]]
    model = NeighbourVote(weights, basis.astype(np.float32), np.empty((0, 0), np.float32), labels_, neighbours, sharpness)
    model.vectors = model.turned(tf).astype(np.float32)
    return model


def score(docs: DataFrame, model: NeighbourVote | None, block: int = 256) -> DataFrame:
    """``docs`` with score (0 to 1); the model goes to the executors as one broadcast."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        vote, counter = sent.value, TermCounter()

        def work(batch: pa.RecordBatch) -> list[pa.Array]:
            if vote is None:
                return [pa.array(np.full(batch.num_rows, 0.5))]
            return [pa.array(vote.score(np.stack([counter.counts(x) for x in byte_texts(batch.column("text"))])), pa.float64())]

        return work

    return with_columns(docs, "score double", make, rows=block)


def learn_and_score(docs: DataFrame, labels: DataFrame, folds: int = 4, held: int = 2, threshold: float = 0.7, **options) -> DataFrame:
    """``docs`` with score, predicted and held_out; rows of fold ``held`` teach nothing."""
    known = labels.where(id_bucket("doc_id", folds) != held)
    scored = score(docs, fit(docs, known, **options))
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int")).withColumn("held_out", id_bucket("doc_id", folds) == held)
