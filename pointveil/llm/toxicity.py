"""Toxicity by a bidirectional gated recurrent network with attention pooling over character and word inputs.

A word's input joins its hashed word vector and the sum of its hashed character n-gram vectors over the root of their number. Windows of
``WINDOW`` words start every ``STRIDE`` words, so every word but those at the ends lies in two windows; all windows
of a text are scored, and a logistic layer maps their largest and mean logits to the text's score. Training
uses a bounded sample of labelled rows (``TRAIN_ROWS``); scoring covers whole texts. Null, empty and blank texts
have one empty window. Equal texts get equal scores whatever batch they come in.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_chunks, fold, labelled_sample, texts_of
from .gru import F32, Adam, Gru
from .textops import Words

WINDOW, STRIDE, HIDDEN, DIM = 32, 16, 8, 12
WORD_ROWS, GRAM_ROWS, GRAMS = 1 << 13, 1 << 15, (4, 6)
TRAIN_ROWS, STEPS, BATCH, RATE, THRESHOLD = 4000, 450, 192, 0.01, 0.3
#: Chance that a training word keeps a part of its input; shrinking of the tables at each step.
KEEP, DECAY = 0.8, 0.0005


class ToxicNet:
    """Weights and scoring; a plain dict of arrays travels to the executors."""

    def __init__(self, weights: dict[str, np.ndarray]):
        self.w = weights

    @staticmethod
    def fresh(seed: int = 5) -> "ToxicNet":
        rng = np.random.default_rng(seed)
        n = HIDDEN
        def draw(*shape, scale):
            return (rng.standard_normal(shape) * scale).astype(F32)

        return ToxicNet({
            "word": draw(WORD_ROWS, DIM, scale=0.1), "gram": draw(GRAM_ROWS, DIM, scale=0.3),
            "wf": draw(2 * DIM, 3 * n, scale=0.3), "wb": draw(2 * DIM, 3 * n, scale=0.3), "bias": np.zeros(6 * n, dtype=F32),
            "uf": Gru(n, rng).u, "ub": Gru(n, rng).u,
            "att": draw(2 * n, scale=0.3), "out": draw(2 * n, scale=0.3), "b": np.zeros(1, dtype=F32),
            "calib": np.array([1.0, 0.0, 0.0]),
        })

    def inputs(self, words: Words) -> tuple[np.ndarray, ...]:
        """(word row, n-gram owners, n-gram rows, number of each word) of the distinct words."""
        first, values, back = words.distinct()
        owner, grams = words.grams(first, GRAMS)
        order = np.argsort(owner, kind="stable")
        owner, grams = owner[order], grams[order]
        return (values % WORD_ROWS).astype(np.int64), owner, (grams % GRAM_ROWS).astype(np.int64), back

    def vectors(self, word_row: np.ndarray, owner: np.ndarray, gram_row: np.ndarray) -> np.ndarray:
        out = np.zeros((len(word_row), 2 * DIM), dtype=F32)
        out[:, :DIM] = self.w["word"][word_row]
        if len(owner):
            has, at, count = np.unique(owner, return_index=True, return_counts=True)
            out[has, DIM:] = np.add.reduceat(self.w["gram"][gram_row], at, axis=0) / np.sqrt(count[:, None].astype(F32))
        return out

    def window_logits(self, xf: np.ndarray, xb: np.ndarray, index: np.ndarray) -> np.ndarray:
        """Logits of windows; ``index`` (windows x WINDOW) numbers the distinct words, their count meaning padding."""
        w, n = self.w, HIDDEN
        rows, steps = index.shape
        out = np.zeros((rows, steps, 2 * n), dtype=F32)
        for gru, x, part, order in ((Gru(n, u=w["uf"]), xf, slice(0, n), range(steps)), (Gru(n, u=w["ub"]), xb, slice(n, 2 * n), range(steps - 1, -1, -1))):
            h = np.zeros((rows, n), dtype=F32)
            for t in order:
                word = index[:, t]
                new = gru.step(x[word], h)
                h = np.where((word < len(x) - 1)[:, None], new, h)
                out[:, t, part] = h
        score = out @ w["att"]
        score[index >= len(xf) - 1] = -30
        score = np.exp(score - score.max(axis=1, keepdims=True))
        score /= score.sum(axis=1, keepdims=True)
        return np.einsum("rt,rtk->rk", score, out) @ w["out"] + w["b"][0]

    def text_features(self, texts: list[bytes], most: int = 4096) -> np.ndarray:
        """(largest logit, mean logit) over all windows of each text."""
        words = Words(texts, lower=True)
        word_row, owner, gram_row, back = self.inputs(words)
        vec = self.vectors(word_row, owner, gram_row)
        n = 3 * HIDDEN
        pad = np.zeros((1, n), dtype=F32)
        xf = np.concatenate([vec @ self.w["wf"] + self.w["bias"][:n], pad])
        xb = np.concatenate([vec @ self.w["wb"] + self.w["bias"][n:], pad])
        doc, start = windows_of(words.sizes)
        begin = np.concatenate([[0], words.sizes.cumsum()[:-1]])
        back = np.append(back, len(vec))
        logits = np.empty(len(doc), dtype=np.float64)
        for i in range(0, len(doc), most):
            d, s = doc[i : i + most], start[i : i + most]
            at = s[:, None] + np.arange(WINDOW)
            index = back[np.where(at < words.sizes[d][:, None], begin[d][:, None] + at, len(back) - 1)]
            logits[i : i + most] = self.window_logits(xf, xb, index)
        cut = np.flatnonzero(np.concatenate([[True], doc[1:] != doc[:-1]]))
        return np.stack([np.maximum.reduceat(logits, cut), np.add.reduceat(logits, cut) / np.diff(np.append(cut, len(doc)))], axis=1)

    def scores(self, texts: list[bytes]) -> np.ndarray:
        f = self.text_features(texts)
        a, b, c = self.w["calib"]
        return np.round(1 / (1 + np.exp(-np.clip(a * f[:, 0] + b * f[:, 1] + c, -30, 30))), 5)


def windows_of(sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(text, first word) of all overlapping windows; a text without words has one empty window."""
    count = np.maximum(1, -(-(sizes - WINDOW) // STRIDE) + 1)
    doc = np.repeat(np.arange(len(sizes)), count)
    return doc, (np.arange(len(doc)) - np.repeat(count.cumsum() - count, count)) * STRIDE


def train(rows: list[tuple[int, str, int]], steps: int = STEPS, seed: int = 5) -> ToxicNet:
    """Fit on (id, text, label) rows by minibatches of windows that carry their text's label."""
    net = ToxicNet.fresh(seed)
    if not rows or len({r[2] for r in rows}) < 2:
        net.w["calib"] = np.array([0.0, 0.0, 4.0 if rows and rows[0][2] else -4.0])
        return net
    rng = np.random.default_rng(seed)
    texts, y = [r[1].encode() for r in rows], np.array([r[2] for r in rows])
    runs = list(_runs(texts))
    word_row, gram_row, gram_count, back, sizes = _gathered(net, runs)
    gram_at = np.concatenate([[0], gram_count.cumsum()])
    doc, start = windows_of(sizes)
    begin = np.concatenate([[0], sizes.cumsum()[:-1]])
    full = sizes[doc] > 0
    sides = [np.flatnonzero(full & (y[doc] == k)) for k in (0, 1)]
    if min(map(len, sides)) == 0:
        return net
    chance = _even(doc[sides[1]])
    w, n = net.w, HIDDEN
    learned = {k: v for k, v in w.items() if k != "calib"}
    adam = Adam(learned, RATE)
    gf, gb = Gru(n, u=w["uf"]), Gru(n, u=w["ub"])
    for step in range(steps):
        adam.rate = RATE * (1 - 0.9 * step / steps)
        pick = np.concatenate([rng.choice(sides[0], BATCH // 2), rng.choice(sides[1], BATCH // 2, p=chance)])
        target = np.repeat([0.0, 1.0], BATCH // 2).astype(F32)
        at = start[pick][:, None] + np.arange(WINDOW)
        live = at < sizes[doc[pick]][:, None]
        flat = back[np.where(live, begin[doc[pick]][:, None] + at, 0)]
        used, index = np.unique(flat, return_inverse=True)
        index = index.reshape(flat.shape)
        count = gram_at[used + 1] - gram_at[used]
        own = np.repeat(np.arange(len(used)), count)
        rows_g = gram_row[np.arange(len(own)) - np.repeat(count.cumsum() - count, count) + np.repeat(gram_at[used], count)]
        vec = net.vectors(word_row[used], own, rows_g)
        shown = np.repeat((rng.random((len(used), 2)) < KEEP).astype(F32) / F32(KEEP), DIM, axis=1)
        vec *= shown  # a word's vector or its characters are hidden now and then, so that neither is learnt by heart
        x = vec[index]  # rows x steps x 2 DIM
        xt = np.swapaxes(x, 0, 1)
        pf = xt @ w["wf"] + w["bias"][: 3 * n]
        pb = (xt @ w["wb"] + w["bias"][3 * n :])[::-1]
        zero = np.zeros((BATCH, n), dtype=F32)
        of, tf = gf.forward(pf, zero)
        ob, tb = gb.forward(pb, zero)
        both = np.concatenate([of, ob[::-1]], axis=2)
        lt = live.T
        sc = np.where(lt, both @ w["att"], -30)
        sc = np.exp(sc - sc.max(axis=0))
        al = (sc / sc.sum(axis=0)).astype(F32)
        pooled = np.einsum("tr,trk->rk", al, both)
        p = 1 / (1 + np.exp(-(pooled @ w["out"] + w["b"][0])))
        dl = ((p - target) / BATCH).astype(F32)
        dpool = dl[:, None] * w["out"]
        dal = np.einsum("trk,rk->tr", both, dpool)
        ds = (al * (dal - (al * dal).sum(axis=0))).astype(F32)
        dboth = al[:, :, None] * dpool[None] + ds[:, :, None] * w["att"]
        dxf, duf = gf.backward(tf, np.ascontiguousarray(dboth[:, :, :n]))
        dxb, dub = gb.backward(tb, np.ascontiguousarray(dboth[::-1, :, n:]))
        dxb = dxb[::-1]
        dxf, dxb = dxf * lt[:, :, None], dxb * lt[:, :, None]
        flat_x, ff, fb = xt.reshape(-1, 2 * DIM), dxf.reshape(-1, 3 * n), dxb.reshape(-1, 3 * n)
        dvec_t = ff @ w["wf"].T + fb @ w["wb"].T
        dvec = np.zeros_like(vec)
        np.add.at(dvec, index.T.ravel(), dvec_t)
        dvec *= shown
        gword, ggram = np.zeros_like(w["word"]), np.zeros_like(w["gram"])
        np.add.at(gword, word_row[used], dvec[:, :DIM])
        np.add.at(ggram, rows_g, (dvec[:, DIM:] / np.sqrt(np.maximum(count, 1))[:, None].astype(F32))[own])
        adam.apply({
            "word": gword, "gram": ggram, "wf": flat_x.T @ ff, "wb": flat_x.T @ fb, "bias": np.concatenate([ff.sum(axis=0), fb.sum(axis=0)]),
            "uf": duf, "ub": dub, "att": np.einsum("tr,trk->k", ds, both), "out": pooled.T @ dl, "b": np.array([dl.sum()], dtype=F32),
        })
        for table in ("word", "gram"):
            w[table] *= F32(1 - DECAY)
    w["calib"] = calibrate(np.concatenate([net.text_features(run) for run in runs]), y)
    return net


def _even(doc: np.ndarray) -> np.ndarray:
    """Chances of windows that give every text the same sum."""
    _, back, size = np.unique(doc, return_inverse=True, return_counts=True)
    p = 1 / size[back]
    return p / p.sum()


def _runs(texts: list[bytes], limit: int = 1 << 20) -> Iterator[list[bytes]]:
    """Consecutive texts of about ``limit`` bytes; bounds the driver's memory."""
    held, size = [], 0
    for t in texts:
        if held and size + len(t) > limit:
            yield held
            held, size = [], 0
        held.append(t)
        size += len(t)
    if held:
        yield held


def _gathered(net: ToxicNet, runs: list[list[bytes]]) -> tuple[np.ndarray, ...]:
    """Word rows, n-gram rows and their counts of each run's distinct words; each word's number; words of each text."""
    found, offset = [], 0
    for run in runs:
        words = Words(run, lower=True)
        word_row, owner, gram_row, back = net.inputs(words)
        found.append((word_row.astype(np.int32), gram_row.astype(np.int32), np.bincount(owner, minlength=len(word_row)), (back + offset).astype(np.int32), words.sizes))
        offset += len(word_row)
    return tuple(np.concatenate(c) for c in zip(*found))


def calibrate(features: np.ndarray, y: np.ndarray, rounds: int = 60, ridge: float = 1e-3) -> np.ndarray:
    """Logistic weights (per feature, then the constant) by Newton steps."""
    x = np.column_stack([np.clip(features, -30, 30), np.ones(len(y))])
    w = np.zeros(x.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        h = (x * (p * (1 - p))[:, None]).T @ x + ridge * len(y) / 100 * np.eye(len(w))
        w = w + np.linalg.solve(h, x.T @ (y - p) - ridge * len(y) / 100 * w)
    return w


def score(docs: DataFrame, net: ToxicNet, held_fold: int = 2, folds: int = 4, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, held_out, score, predicted for every row."""
    weights = net.w

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = ToxicNet(weights)
        for batch in batches:
            for part in byte_chunks(batch):
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(model.scores(texts_of(part)))], ["doc_id", "score"])

    scored = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, score double")
    return scored.select("doc_id", (fold(F.col("doc_id"), folds) == held_fold).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def toxicity(docs: DataFrame, marks: DataFrame, bound: int = TRAIN_ROWS) -> DataFrame:
    """Train on the bounded sample outside the held-out fold and score every document."""
    return score(docs, train(labelled_sample(docs, marks, "toxic", 2, 4, bound)))
