"""Quality by nearest-neighbour voting in a latent-semantic space.

A text's features are square-rooted shares of hashed lower-cased words, of hashed word shapes (letters, digits and
capitals as classes, other bytes as they are) and of immediate repeats, scaled by inverse document frequency. A
truncated singular value decomposition of the labelled sample gives the latent space. The sample's unit vectors and
labels are broadcast (at most ``REFERENCES`` x ``RANK`` floats); every document's cosines with all of them are taken
in blocks, and the ``NEIGHBOURS`` nearest vote with weight (cosine ** SHARP). Ties keep all tied neighbours.
Null, empty and blank texts have no features: their score is the sample's share of label 1.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_chunks, fold, labelled_sample, texts_of
from .textops import Words

WORD_ROWS, SHAPE_ROWS = 2048, 512
WIDTH = WORD_ROWS + SHAPE_ROWS + 1
REFERENCES, RANK, NEIGHBOURS, SHARP, THRESHOLD, BLOCK = 4096, 48, 25, 8.0, 0.7, 512

_CLASS = np.arange(256, dtype=np.uint8)
_CLASS[ord("a") : ord("z") + 1] = ord("a")
_CLASS[128:] = ord("a")
_CLASS[ord("A") : ord("Z") + 1] = ord("A")
_CLASS[ord("0") : ord("9") + 1] = ord("0")


def counts(texts: list[bytes]) -> np.ndarray:
    """Texts x WIDTH feature counts."""
    low = Words(texts, lower=True)
    shape = Words([_CLASS[np.frombuffer(t, dtype=np.uint8)].tobytes() for t in texts])
    n = len(texts)
    word = low.word_hashes()
    same = np.concatenate([[False], (word[1:] == word[:-1]) & (low.doc[1:] == low.doc[:-1])]) if len(word) else np.zeros(0, dtype=bool)
    tail = np.maximum(shape.start, shape.end - 4)
    kinds = shape.hashes(tail, shape.end)
    out = np.zeros((n, WIDTH), dtype=np.float32)
    for column, weight in (((word % WORD_ROWS).astype(np.int64), None), (WORD_ROWS + (kinds % SHAPE_ROWS).astype(np.int64), None), (np.full(len(word), WIDTH - 1), same.astype(float))):
        out += np.bincount(low.doc * WIDTH + column, weight, n * WIDTH).reshape(n, WIDTH)
    return out


def profile(texts: list[bytes]) -> np.ndarray:
    """Square-rooted shares: long and short texts compare."""
    c = counts(texts)
    return np.sqrt(c / np.maximum(c[:, :WORD_ROWS].sum(axis=1, keepdims=True), 1))


class Voter:
    """The latent map, the broadcast references and the vote."""

    def __init__(self, to_latent: np.ndarray, vectors: np.ndarray, labels: np.ndarray, prior: float):
        self.to_latent, self.vectors, self.labels, self.prior = to_latent, vectors, labels, prior

    def latent(self, texts: list[bytes]) -> np.ndarray:
        v = profile(texts) @ self.to_latent
        return v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-9)

    def scores(self, texts: list[bytes]) -> np.ndarray:
        out = np.full(len(texts), self.prior)
        if not len(self.labels):
            return out
        for i in range(0, len(texts), BLOCK):
            v = self.latent(texts[i : i + BLOCK])
            cosine = np.round(v @ self.vectors.T, 5)
            k = min(NEIGHBOURS, len(self.labels))
            least = -np.partition(-cosine, k - 1, axis=1)[:, k - 1 : k]
            weight = np.where(cosine >= least, np.maximum(cosine, 0) ** SHARP, 0)
            total = weight.sum(axis=1)
            live = (np.abs(v).sum(axis=1) > 0) & (total > 0)
            out[i : i + BLOCK][live] = (weight @ self.labels)[live] / total[live]
        return np.round(out, 4)


def train(rows: list[tuple[int, str, int]], rank: int = RANK, seed: int = 11) -> Voter:
    """Latent space and references from (id, text, label) rows; a block power iteration finds the leading directions."""
    labels = np.array([r[2] for r in rows], dtype=np.float32)
    if not len(rows):
        return Voter(np.zeros((WIDTH, rank), dtype=np.float32), np.zeros((0, rank), dtype=np.float32), labels, 0.5)
    x = np.concatenate([profile([r[1].encode() for r in rows[i : i + 256]]) for i in range(0, len(rows), 256)]).astype(np.float32)
    idf = np.log((len(rows) + 1) / ((x > 0).sum(axis=0) + 1)).astype(np.float32) + 0.2
    x *= idf
    q = np.linalg.qr(np.random.default_rng(seed).standard_normal((WIDTH, rank + 8)).astype(np.float32))[0]
    for _ in range(12):
        q = np.linalg.qr(x.T @ (x @ q))[0]
    _, _, vt = np.linalg.svd(x @ q, full_matrices=False)
    to = (idf[:, None] * (q @ vt[:rank].T)).astype(np.float32)
    voter = Voter(to, np.zeros((0, rank), dtype=np.float32), labels, float(np.round(labels.mean(), 4)))
    latent = x @ (to / idf[:, None])
    voter.vectors = latent / np.maximum(np.linalg.norm(latent, axis=1, keepdims=True), 1e-9)
    return voter


def score(docs: DataFrame, voter: Voter, held_fold: int = 2, folds: int = 4, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, held_out, score, predicted for every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in byte_chunks(batch):
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(voter.scores(texts_of(part)))], ["doc_id", "score"])

    scored = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, score double")
    return scored.select("doc_id", (fold(F.col("doc_id"), folds) == held_fold).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def quality(docs: DataFrame, marks: DataFrame, bound: int = REFERENCES) -> DataFrame:
    """Fit on the bounded sample outside the held-out fold and score every document."""
    return score(docs, train(labelled_sample(docs, marks, "quality", 2, 4, bound)))


def keep_good(docs: DataFrame, voter: Voter, threshold: float = THRESHOLD) -> DataFrame:
    """The rows scored at ``threshold`` or more, with all their columns, in one pass without a join."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in byte_chunks(batch):
                yield part.filter(pa.array(voter.scores(texts_of(part)) >= threshold))

    return docs.mapInArrow(run, docs.schema)
