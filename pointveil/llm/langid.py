"""Language identification: averaged hashed subword embeddings with a linear softmax, trained by SGD in numpy.

Subwords are byte n-grams (2 to 4) of bordered, lower-cased words; a text is the mean of its subwords' vectors.
A temperature is fitted on part of the training rows, and answers below the calibrated confidence are marked
``rejected`` (their prediction stays). Null texts and texts without a letter are ``und`` with score 0.
Training uses a bounded sample (``TRAIN_ROWS``); scoring covers whole texts.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_chunks, fold, texts_of
from .textops import Words

ROWS, DIM, GRAMS = 1 << 15, 10, (2, 3, 4)
TRAIN_ROWS, LEAST_STEPS, BATCH, RATE, REJECT = 2000, 450, 32, 2.0, 0.005
UNKNOWN = "und"


def bags(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(text, word number) of every word, then (owner word, subword row) of the distinct words, and their count."""
    words = Words(texts, lower=True)
    first, _, back = words.distinct()
    owner, grams = words.grams(first, GRAMS)
    return words.doc, back, owner, (grams % ROWS).astype(np.int64), np.array([len(first)])


class LangModel:
    """Subword vectors, softmax weights, temperature, rejection bound and the learned languages."""

    def __init__(self, langs: list[str], table: np.ndarray, weights: np.ndarray, bias: np.ndarray, temperature: float = 1.0, reject: float = 0.0):
        self.langs, self.table, self.weights, self.bias = langs, table, weights, bias
        self.temperature, self.reject = temperature, reject

    def logits(self, texts: list[bytes]) -> np.ndarray:
        """Mean subword vector times weights: the product is taken once for the table, then averaged."""
        doc, back, owner, row, (n,) = bags(texts)
        k = len(self.langs)
        flat = (self.table @ self.weights).astype(np.float64)
        per_word = np.stack([np.bincount(owner, flat[row, c], n) for c in range(k)], axis=1) if n else np.zeros((0, k))
        size = np.bincount(owner, minlength=n)
        total = np.bincount(doc, size[back], len(texts)) if n else np.zeros(len(texts))
        sums = np.stack([np.bincount(doc, per_word[back, c], len(texts)) for c in range(k)], axis=1)
        return sums / np.maximum(total, 1)[:, None] + self.bias

    def predict(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(language number, probability) by the tempered softmax."""
        z = self.logits(texts) / self.temperature
        p = np.exp(z - z.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        return p.argmax(axis=1), np.round(p.max(axis=1), 6)


def train(rows: list[tuple[str, str]], seed: int = 3) -> LangModel | None:
    """Fit on (text, lang) rows; a fifth of them sets the temperature and the rejection bound."""
    langs = sorted({lang for _, lang in rows})
    if not langs:
        return None
    rng = np.random.default_rng(seed)
    texts, y = [t.encode() for t, _ in rows], np.array([langs.index(lang) for _, lang in rows])
    order = rng.permutation(len(texts))
    hold = order[: len(order) // 5]
    fit = order[len(order) // 5 :]
    table = (rng.standard_normal((ROWS, DIM)) * 0.1).astype(np.float32)
    model = LangModel(langs, table, np.zeros((DIM, len(langs)), dtype=np.float32), np.zeros(len(langs)))
    bag = []
    for i in range(0, len(texts), 64):
        doc, back, owner, row, (n,) = bags(texts[i : i + 64])
        count = np.bincount(owner, minlength=n)
        at = count.cumsum() - count if n else count
        order_w = np.argsort(owner, kind="stable")
        row = row[order_w]
        for d in range(len(texts[i : i + 64])):
            used, times = np.unique(back[doc == d], return_counts=True)
            size = count[used]
            ids = row[np.arange(size.sum()) - np.repeat(size.cumsum() - size, size) + np.repeat(at[used], size)] if len(used) else row[:0]
            bag.append((ids, np.repeat(times, size) / max(1, (times * size).sum())))
    epochs = -(-LEAST_STEPS // max(1, -(-len(fit) // BATCH)))
    for epoch in range(epochs):
        rate = RATE * (1 - epoch / epochs)
        fit = rng.permutation(fit)
        for i in range(0, len(fit), BATCH):
            batch = [j for j in fit[i : i + BATCH] if len(bag[j][0])]
            if not batch:
                continue
            ids = np.concatenate([bag[j][0] for j in batch])
            share = np.concatenate([bag[j][1] for j in batch]).astype(np.float32)
            owner = np.repeat(np.arange(len(batch)), [len(bag[j][0]) for j in batch])
            cut = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]]))
            mean = np.add.reduceat(model.table[ids] * share[:, None], cut, axis=0)
            z = mean @ model.weights + model.bias
            p = np.exp(z - z.max(axis=1, keepdims=True))
            p /= p.sum(axis=1, keepdims=True)
            p[np.arange(len(batch)), y[batch]] -= 1
            p = (p / len(batch)).astype(np.float32)
            step = p @ model.weights.T
            model.weights -= rate * mean.T @ p
            model.bias -= rate * p.sum(axis=0)
            used, back = np.unique(ids, return_inverse=True)
            grad = np.stack([np.bincount(back, share * step[owner, c], len(used)) for c in range(DIM)], axis=1)
            model.table[used] -= (rate * 20 * grad).astype(np.float32)
    if len(hold):
        z = model.logits([texts[i] for i in hold])
        best = (np.inf, 1.0)
        for t in np.geomspace(0.05, 20, 61):
            q = z / t
            q = q - q.max(axis=1, keepdims=True)
            loss = (np.log(np.exp(q).sum(axis=1)) - q[np.arange(len(hold)), y[hold]]).mean()
            best = min(best, (loss, t))
        model.temperature = float(best[1])
        model.reject = float(np.quantile(model.predict([texts[i] for i in hold])[1], REJECT))
    return model


def sample(docs: DataFrame, bound: int, held_fold: int, folds: int) -> list[tuple[str, str]]:
    """At most ``bound`` rows with text and language outside the held-out fold, by smallest id hash."""
    usable = F.col("doc_id").isNotNull() & F.col("text").isNotNull() & F.col("lang").isNotNull() & (fold(F.col("doc_id"), folds) != held_fold)
    keep = docs.where(usable).select("doc_id").dropDuplicates().orderBy(F.xxhash64("doc_id"), "doc_id").limit(bound)
    rows = docs.where(usable).select("doc_id", "text", "lang").join(F.broadcast(keep), "doc_id").collect()
    return [(r.text, r.lang) for r in sorted(rows, key=lambda r: (r.doc_id, r.text, r.lang))]


def identify(docs: DataFrame, model: LangModel | None, held_fold: int = 2, folds: int = 4) -> DataFrame:
    """doc_id, held_out, lang_pred, score, rejected for every row; without any training row all are ``und``."""
    import regex

    letter = regex.compile(r"\p{L}")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in byte_chunks(batch):
                texts = part.column("text").to_pylist()
                known = [bool(t) and letter.search(t) is not None and model is not None for t in texts]
                number, sure = model.predict([(t or "").encode() for t in texts]) if model is not None else ([0] * len(texts), [0.0] * len(texts))
                yield pa.RecordBatch.from_arrays([
                    part.column("doc_id"),
                    pa.array([model.langs[n] if k else UNKNOWN for n, k in zip(number, known)], pa.string()),
                    pa.array([float(s) if k else 0.0 for s, k in zip(sure, known)]),
                    pa.array([not k or s < model.reject for s, k in zip(sure, known)]),
                ], ["doc_id", "lang_pred", "score", "rejected"])

    found = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, lang_pred string, score double, rejected boolean")
    return found.select("doc_id", (fold(F.col("doc_id"), folds) == held_fold).alias("held_out"), "lang_pred", "score", "rejected")


def language(docs: DataFrame, bound: int = TRAIN_ROWS) -> DataFrame:
    """Train on the bounded sample outside the held-out fold and identify every document."""
    return identify(docs, train(sample(docs, bound, 2, 4)))
