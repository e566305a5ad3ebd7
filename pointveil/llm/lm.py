"""Gated recurrent language model with a class-factored softmax, and the smoothed unigram base beside it.

Corpus pass 1 counts every token of all training texts. The ``SYMBOLS`` commonest tokens are the network's
vocabulary; other words are one of a few symbols by their form, times the word's smoothed share among the other
words of that form, so every text has a proper probability. Symbols fall into classes by frequency: a token's
probability is its class's times its own inside the class. Weights are trained in numpy by truncated
backpropagation with the state carried over windows: a bounded sample of training texts (``TRAIN_ROWS``) gives the
start, then corpus pass 2 goes on from it over all training texts, each task over its own, and the tasks' weights are
averaged by their tokens. Output biases start at the corpus counts. Corpus pass 3 scores whole texts, the state carried across windows from the first
word to the end. Words outside the broadcast list (``HOT_WORDS``, bounded) get their counts by a join.

Null and empty texts are one end token. Equal rows are scored as separate rows.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fold, staged, texts_of
from .gru import F32, Adam, Gru

CLASSES, PER_CLASS = 32, 32
SYMBOLS = CLASSES * PER_CLASS
HOT_WORDS, MOST_COUNTED, RUN_TOKENS, WINDOW = 1 << 18, 300_000, 4_000_000, 64
HIDDEN, DIM, TRAIN_ROWS, EPOCHS, STREAMS, STEP_WINDOW, RATE = 16, 16, 1500, 2, 64, 24, 0.01
#: The pass over all training texts: tokens a task trains on at a time, streams, and the steps that small runs get too.
SWEEP_TOKENS, SWEEP_STREAMS, SWEEP_STEPS, SWEEP_RATE = 1_000_000, 256, 64, 0.02
#: The end of a text; no word is empty.
END = b""
FORMS = 6


def form(word: bytes) -> int:
    """The form of a word outside the vocabulary: its last sign and whether it is plain ASCII."""
    return (1 if word.endswith(b".") else 2 if word.endswith(b",") else 0) + (0 if word.isascii() else 3)


def token_counts(docs: DataFrame) -> DataFrame:
    """(word binary, n long) over all texts, the end token included; combined in each task before the shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter = Counter()

        def out() -> pa.RecordBatch:
            batch = pa.RecordBatch.from_arrays([pa.array(list(seen.keys()), pa.binary()), pa.array(list(seen.values()), pa.int64())], ["word", "n"])
            seen.clear()
            return batch

        for batch in batches:
            seen[END] += batch.num_rows
            for text in texts_of(batch):
                seen.update(text.lower().split())
                if len(seen) > MOST_COUNTED:
                    yield out()
        if seen:
            yield out()

    return docs.select("text").mapInArrow(run, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n"))


class Lexicon:
    """What the corpus counts give: totals, the broadcast words with their counts and symbols, and form totals."""

    def __init__(self, hot: list[tuple[bytes, int]], total: int, distinct: int, by_form: dict[int, tuple[int, int]]):
        self.total, self.distinct = total, distinct
        hot = sorted(hot, key=lambda r: (-r[1], r[0]))
        room = SYMBOLS - FORMS - 1
        own = [w for w, _ in hot if w != END][:room]
        masses = {END: dict(hot).get(END, 0)}
        mine = set(own)
        masses.update((w, n) for w, n in hot if w in mine)
        # words that are symbols themselves leave their form's totals
        self.form_n, self.form_v = np.zeros(FORMS), np.zeros(FORMS)
        for f, (n, v) in by_form.items():
            self.form_n[f], self.form_v[f] = n, v
        for w, n in masses.items():
            if w != END:
                self.form_n[form(w)] -= n
                self.form_v[form(w)] -= 1
        entries = [(n, 0, w) for w, n in masses.items()] + [(int(self.form_n[f]), 1, f) for f in range(FORMS)]
        entries += [(0, 2, i) for i in range(SYMBOLS - len(entries))]
        entries.sort(key=lambda e: (-e[0], e[1], str(e[2])))
        self.mass = np.array([e[0] + 0.5 for e in entries])
        number = {(k, x): i for i, (_, k, x) in enumerate(entries)}
        self.end = number[0, END]
        self.form_symbol = np.array([number[1, f] for f in range(FORMS)])
        self.index = {w: i for i, (w, _) in enumerate(hot)}
        self.count = np.array([n for _, n in hot] + [0], dtype=np.float64)
        self.symbol = np.array([number.get((0, w), -1) if w in masses else self.form_symbol[form(w)] for w, _ in hot] + [0], dtype=np.int32)
        self.other = np.array([w not in masses for w, _ in hot] + [True])
        self.form_bits = np.log10(self.form_n + self.form_v + 1)

    def symbols(self, text: bytes) -> tuple[np.ndarray, np.ndarray, list[bytes]]:
        """(symbol of every token, number among the hot words or -1, the tail words) of a text with its end."""
        words = text.lower().split()
        get = self.index.get
        at = np.fromiter(map(get, words, repeat(-1)), dtype=np.int32, count=len(words))
        symbol = self.symbol[at]
        lost = np.flatnonzero(at < 0)
        tail = [words[i] for i in lost.tolist()]
        if tail:
            symbol[lost] = self.form_symbol[[form(w) for w in tail]]
        return np.append(symbol, self.end), np.append(at, self.index.get(END, -1)), tail


class Symbols:
    """The symbol rows alone: a small table of the words that are symbols, and the form of every other word."""

    def __init__(self, words: Lexicon):
        self.own = {w: s for w, s in zip(words.index, words.symbol.tolist()) if not words.other[words.index[w]]}
        self.form_symbol, self.end = words.form_symbol.astype(np.int32), words.end
        self.blank = np.zeros(256, dtype=bool)
        self.blank[[0x20, *range(0x09, 0x0E)]] = True

    def row(self, text: bytes) -> np.ndarray:
        """The symbol of every token of a text with its end."""
        words = text.lower().split()
        symbol = np.fromiter(map(self.own.get, words, repeat(-1)), dtype=np.int32, count=len(words))
        lost = (symbol < 0).nonzero()[0]
        if len(lost):
            raw = np.frombuffer(text, dtype=np.uint8)
            blank = np.concatenate([[True], self.blank[raw], [True]])
            first, last = (blank[:-1] & ~blank[1:]).nonzero()[0], (~blank[:-1] & blank[1:]).nonzero()[0] - 1
            last, first = last[lost], first[lost]
            wide = np.concatenate([[0], (raw > 127).cumsum()])
            sign = raw[last]
            kind = np.where(sign == 0x2E, 1, np.where(sign == 0x2C, 2, 0)) + np.where(wide[last + 1] > wide[first], 3, 0)
            symbol[lost] = self.form_symbol[kind]
        return np.append(symbol, np.int32(self.end))


class Network:
    """Weights of the recurrent model; symbol s is member s % PER_CLASS of class s // PER_CLASS."""

    def __init__(self, weights: dict[str, np.ndarray]):
        self.w = weights

    @staticmethod
    def fresh(mass: np.ndarray, seed: int = 9) -> "Network":
        rng = np.random.default_rng(seed)
        by_class = mass.reshape(CLASSES, PER_CLASS)

        def draw(*shape, scale):
            return (rng.standard_normal(shape) * scale).astype(F32)

        return Network({
            "emb": draw(SYMBOLS, DIM, scale=0.3), "wx": draw(DIM, 3 * HIDDEN, scale=0.3), "bx": np.zeros(3 * HIDDEN, dtype=F32), "u": Gru(HIDDEN, rng).u,
            "wc": draw(HIDDEN, CLASSES, scale=0.1), "bc": np.log(by_class.sum(axis=1) / mass.sum()).astype(F32),
            "ww": draw(CLASSES, HIDDEN, PER_CLASS, scale=0.1), "bw": np.log(by_class / by_class.sum(axis=1, keepdims=True)).astype(F32),
        })

    def inputs(self) -> np.ndarray:
        """Projected input of every symbol."""
        return self.w["emb"] @ self.w["wx"] + self.w["bx"]

    def log_probs(self, states: np.ndarray, target: np.ndarray) -> np.ndarray:
        """Natural log probability of the target symbol after each state (states are below 1, so logits stay small)."""
        w = self.w
        order = np.argsort((target // PER_CLASS).astype(np.uint8), kind="stable")
        target, h = target[order], states[order]
        kind, member, one = target // PER_CLASS, target % PER_CLASS, np.ones(max(CLASSES, PER_CLASS), dtype=F32)
        z = h @ w["wc"]
        z += w["bc"]
        found = z[np.arange(len(z)), kind]
        np.exp(z, out=z)
        mass = z @ one[:CLASSES]
        cuts = np.searchsorted(kind, np.arange(CLASSES + 1)).tolist()
        for c, (a, b) in enumerate(zip(cuts, cuts[1:])):
            if a < b:
                z = h[a:b] @ w["ww"][c]
                z += w["bw"][c]
                found[a:b] += z[np.arange(b - a), member[a:b]]
                np.exp(z, out=z)
                found[a:b] -= np.log(z @ one[:PER_CLASS])
        found -= np.log(mass)
        out = np.empty_like(found)
        out[order] = found
        return out

    def text_scores(self, ids: list[np.ndarray], end: int) -> np.ndarray:
        """Natural log probability of every symbol row; all rows go together, the longest first, in windows."""
        size = np.array([len(r) for r in ids])
        order = np.argsort(-size, kind="stable")
        size = size[order]
        flat = np.concatenate([ids[i] for i in order])
        begin = size.cumsum() - size
        x, gru = self.inputs(), Gru(HIDDEN, u=self.w["u"])
        total = np.zeros(len(ids))
        h = np.zeros((len(ids), HIDDEN), dtype=F32)
        live_at = np.searchsorted(-size, -np.arange(size[0] if len(size) else 0), side="left")  # rows longer than t
        previous, start = np.full(len(ids), end), 0
        while start < len(live_at):
            states, targets, owners = [], [], []
            stop = min(len(live_at), start + max(8, min(WINDOW, 131_072 // int(live_at[start]))))
            for t in range(start, stop):
                n = live_at[t]
                h = gru.step(x[previous[:n]], h[:n])
                now = flat[begin[:n] + t]
                states.append(h)
                targets.append(now)
                owners.append(n)
                previous = now
            p = self.log_probs(np.concatenate(states), np.concatenate(targets))
            at = 0
            for n in owners:
                total[:n] += p[at : at + n]
                at += n
            start = stop
        out = np.empty(len(ids))
        out[order] = total
        return out


def _softmax_step(w: dict[str, np.ndarray], states: np.ndarray, target: np.ndarray) -> tuple[float, np.ndarray, dict[str, np.ndarray]]:
    """(summed loss, its mean's gradient at the states, gradients of the output weights) of class and member softmax.

    States are below 1 and weights clipped, so the exponentials stay in range. Rows go in order of their class.
    """
    m = len(target)
    order = np.argsort((target // PER_CLASS).astype(np.uint8), kind="stable")
    target, h = target[order], states[order]
    kind, member, row = target // PER_CLASS, target % PER_CLASS, np.arange(m)
    cuts = np.searchsorted(kind, np.arange(CLASSES + 1)).tolist()
    parts = [(c, a, b) for c, (a, b) in enumerate(zip(cuts, cuts[1:])) if a < b]
    p = h @ w["wc"]
    p += w["bc"]
    np.exp(p, out=p)
    q = np.empty((m, PER_CLASS), dtype=F32)
    for c, a, b in parts:
        np.matmul(h[a:b], w["ww"][c], out=q[a:b])
        q[a:b] += w["bw"][c]
    np.exp(q, out=q)
    loss = 0.0
    for prob, own in ((p, kind), (q, member)):
        total = prob @ np.ones(prob.shape[1], dtype=F32)
        loss -= float(np.log(prob[row, own] / total + 1e-12).sum())
        total *= m
        prob /= total[:, None]
        prob[row, own] -= F32(1 / m)
    grads = {"wc": h.T @ p, "bc": p.sum(axis=0), "ww": np.zeros_like(w["ww"]), "bw": np.zeros_like(w["bw"])}
    sorted_d = p @ w["wc"].T
    one = np.ones(m, dtype=F32)
    for c, a, b in parts:
        sorted_d[a:b] += q[a:b] @ w["ww"][c].T
        np.matmul(h[a:b].T, q[a:b], out=grads["ww"][c])
        np.matmul(one[a:b], q[a:b], out=grads["bw"][c])
    d_h = np.empty_like(sorted_d)
    d_h[order] = sorted_d
    return loss, d_h, grads


def train(net: Network, rows: list[np.ndarray], end: int, epochs: int = EPOCHS, seed: int = 9, most_streams: int = STREAMS, rate: float = RATE) -> list[float]:
    """Truncated backpropagation over ``most_streams`` parallel streams of symbol rows; returns the loss of each step."""
    if not rows:
        return []
    rng = np.random.default_rng(seed)
    w, gru = net.w, Gru(HIDDEN, u=net.w["u"])
    adam, losses = Adam(w, rate), []
    for epoch in range(epochs):
        flat = np.concatenate([rows[i] for i in rng.permutation(len(rows))])
        streams = max(1, min(most_streams, len(flat) // STEP_WINDOW))
        target = flat[: len(flat) // streams * streams].reshape(streams, -1).T
        before = np.concatenate([np.full((1, streams), end), target[:-1]])
        h = np.zeros((streams, HIDDEN), dtype=F32)
        starts = range(0, len(target), STEP_WINDOW)
        for k, s in enumerate(starts):
            adam.rate = rate * (1 - 0.9 * (epoch + k / len(starts)) / epochs)
            x_id, y = before[s : s + STEP_WINDOW], target[s : s + STEP_WINDOW]
            keep = (x_id != end).astype(F32)[:, :, None]
            inputs = w["emb"] @ w["wx"] + w["bx"]
            states, tape = gru.forward(inputs[x_id], h, keep)
            h = states[-1]
            flat_h, flat_y = states.reshape(-1, HIDDEN), y.ravel()
            loss, d_h, grads = _softmax_step(w, flat_h, flat_y)
            m = len(flat_y)
            dx, grads["u"] = gru.backward(tape, d_h.reshape(states.shape), keep)
            # what each symbol's projected input gets, summed over its places
            order = np.argsort(x_id.ravel().astype(np.uint16), kind="stable")
            sorted_id = x_id.ravel()[order]
            run = np.concatenate([[True], sorted_id[1:] != sorted_id[:-1]]).nonzero()[0]
            d_in = np.add.reduceat(dx.reshape(-1, 3 * HIDDEN)[order], run, axis=0)
            here = sorted_id[run]
            grads["wx"], grads["bx"] = w["emb"][here].T @ d_in, d_in.sum(axis=0)
            grads["emb"] = np.zeros_like(w["emb"])
            grads["emb"][here] = d_in @ w["wx"].T
            adam.apply({k: grads[k].astype(F32) for k in w})
            for k in ("wc", "ww", "bc", "bw"):
                np.clip(w[k], -20 if k[0] == "b" else -3, 20 if k[0] == "b" else 3, out=w[k])
            losses.append(float(loss / m))
    return losses


def _hot(counts: DataFrame, most: int) -> list[tuple[bytes, int]]:
    """All words above the least count level that keeps the list within ``most`` words."""
    level = F.floor(F.log2(F.col("n").cast("double")) * 16).cast("int")
    sizes = sorted(counts.groupBy(level.alias("level")).agg(F.count(F.lit(1)).alias("size")).collect(), key=lambda r: -r.level)
    taken, least = 0, None
    for r in sizes:
        if taken + r.size > most:
            break
        taken, least = taken + r.size, r.level
    if least is None:
        return []
    return [(bytes(r.word), r.n) for r in counts.where(level >= least).collect()]


def _form_column(word):
    ascii_ = ~F.col("text_").rlike("[^\\x00-\\x7F]")
    last = F.when(F.col("text_").endswith("."), 1).when(F.col("text_").endswith(","), 2).otherwise(0)
    return (last + F.when(ascii_, 0).otherwise(3)).cast("int")


def lexicon(counts: DataFrame, hot_words: int = HOT_WORDS) -> Lexicon:
    """The corpus totals and the bounded list of the commonest words."""
    words = counts.where(F.octet_length("word") > 0).withColumn("text_", F.col("word").cast("string"))
    forms = {r.form: (r.n, r.v) for r in words.groupBy(_form_column("text_").alias("form")).agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("v")).collect()}
    whole = counts.agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("v")).first()
    hot = _hot(counts, hot_words)
    if END not in dict(hot):
        hot += [(END, r.n) for r in counts.where(F.octet_length("word") == 0).collect()]
    return Lexicon(hot, whole.n or 0, whole.v, forms)


def _sample(docs: DataFrame, bound: int) -> list[bytes]:
    keep = docs.where("doc_id IS NOT NULL").select("doc_id").dropDuplicates().orderBy(F.xxhash64("doc_id", F.lit(5)), "doc_id").limit(bound)
    rows = docs.select("doc_id", "text").join(F.broadcast(keep), "doc_id").collect()
    return [(r.text or "").encode() for r in sorted(rows, key=lambda r: (r.doc_id, r.text or ""))]


def sweep(docs: DataFrame, net: Network, words: Lexicon, run_tokens: int = SWEEP_TOKENS) -> Network:
    """Train over all rows of ``docs``: each task goes on from ``net`` over its texts, ``run_tokens`` at a time.

    The result is the mean of the tasks' weights by their tokens. The driver gets one row per weight.
    """
    start = net.w
    names = sorted(start)
    symbols = Symbols(words)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mine = Network({k: v.copy() for k, v in start.items()})
        held: list[np.ndarray] = []
        size, done = 0, 0

        def learn() -> None:
            nonlocal size, done
            streams = max(8, min(SWEEP_STREAMS, size // (STEP_WINDOW * SWEEP_STEPS)))
            train(mine, held, symbols.end, epochs=1, most_streams=streams, rate=SWEEP_RATE)
            done += size
            size = 0
            held.clear()

        for batch in batches:
            for text in texts_of(batch):
                held.append(symbols.row(text))
                size += len(held[-1])
                if size >= run_tokens:
                    learn()
        if size:
            learn()
        if done:
            flat = np.concatenate([mine.w[k].ravel() for k in names] + [np.ones(1)]).astype(np.float64)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(flat)), pa.int32()), pa.array(flat * done)], ["at", "total"])

    rows = docs.select("text").mapInArrow(run, "at int, total double").groupBy("at").agg(F.sum("total").alias("total")).collect()
    if not rows:
        return net
    flat = np.empty(len(rows))
    flat[[r.at for r in rows]] = [r.total for r in rows]
    flat, cut, out = (flat[:-1] / flat[-1]).astype(F32), 0, {}
    for k in names:
        out[k] = flat[cut : cut + start[k].size].reshape(start[k].shape)
        cut += start[k].size
    return Network(out)


def score(docs: DataFrame, held_fold: int = 2, folds: int = 7, bound: int = TRAIN_ROWS, hot_words: int = HOT_WORDS) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score for every row (log10 probabilities)."""
    learn = docs.where(fold(F.col("doc_id"), folds) != held_fold)
    counts = staged(token_counts(learn))
    words = lexicon(counts, hot_words)
    net = Network.fresh(words.mass)
    train(net, [words.symbols(t)[0] for t in _sample(learn, bound)], words.end)
    net = sweep(learn, net, words)
    norm, weights = float(np.log10(words.total + words.distinct + 1)), net.w

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, bits = Network(weights), np.log10(words.count + 1)
        rows, ids, size = [], [], 0

        def out() -> pa.RecordBatch:
            marks = model.text_scores(ids, words.end) / np.log(10)
            done = [(*r[:5], r[5] + m, r[6], r[7]) for r, m in zip(rows, marks)]
            cols = list(zip(*done))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.list_(pa.binary()), pa.list_(pa.int32()))
            names = ("row_no", "doc_id", "n_tokens", "n_known", "base_sum", "score", "tail", "times")
            batch = pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], list(names))
            rows.clear()
            ids.clear()
            return batch

        for batch in batches:
            for row_no, doc_id, text in zip(batch.column("row_no").to_pylist(), batch.column("doc_id").to_pylist(), texts_of(batch)):
                symbol, at, tail = words.symbols(text)
                known = words.count[at] > 0
                other = words.other[at]
                gain = float(bits[at][other].sum())
                odd = np.bincount(symbol[other], minlength=SYMBOLS)[words.form_symbol]
                tally = Counter(tail)
                rows.append((row_no, doc_id, len(symbol), int(known.sum()), float(bits[at].sum()), gain - float((odd * words.form_bits).sum()), list(tally.keys()), list(tally.values())))
                ids.append(symbol)
                size += len(symbol)
                if size >= RUN_TOKENS:
                    yield out()
                    size = 0
        if rows:
            yield out()

    numbered = docs.select(F.monotonically_increasing_id().alias("row_no"), F.col("doc_id").cast("long").alias("doc_id"), "text")
    fields = "row_no long, doc_id long, n_tokens long, n_known long, base_sum double, score double, tail array<binary>, times array<int>"
    scored = staged(numbered.mapInArrow(run, fields))
    tail = scored.select("row_no", F.explode(F.arrays_zip("tail", "times")).alias("e")).select("row_no", F.col("e.tail").alias("word"), F.col("e.times").alias("times"))
    more = (
        tail.join(counts, "word")
        .groupBy("row_no")
        .agg(F.sum("times").alias("more_known"), F.sum(F.col("times") * F.log10(F.col("n") + 1)).alias("more"))
    )
    whole = scored.drop("tail", "times").join(more, "row_no", "left")
    gain = F.coalesce("more", F.lit(0.0))
    return whole.select(
        "doc_id", (fold(F.col("doc_id"), folds) == held_fold).alias("held_out"), "n_tokens",
        (F.col("n_known") + F.coalesce("more_known", F.lit(0))).alias("n_known"), F.lit(int(words.total)).cast("long").alias("train_tokens"),
        (F.col("base_sum") + gain - F.col("n_tokens") * F.lit(norm)).alias("base_score"), (F.col("score") + gain).alias("score"),
    )
