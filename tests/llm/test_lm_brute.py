"""The language model's scores against a token-by-token computation, on tables with odd rows and a short word list."""

import zlib
from collections import Counter

import numpy as np
import pytest

from pointveil.llm import lm

COLUMNS = "doc_id long, text string, row_no string, word long"


def rows():
    rng = np.random.default_rng(6)
    words = [f"w{int(k)}" for k in rng.zipf(1.4, 4000).clip(1, 3000)]
    texts = [" ".join(words[i : i + 25]) + (". Ünd, " if i % 3 else "\t x,") for i in range(0, 4000, 25)]
    texts += [None, "", " \n ", "Same Words", "Same Words", "only here.", "ONLY here.", "solo " * 30_000]
    ids = [*range(len(texts) - 4), 3, 3, None, 900]
    return list(zip(ids, texts, ["a"] * len(texts), range(len(texts))))


def tokens(text):
    return (text or "").encode().lower().split()


def fold_of(doc_id):
    return 0 if doc_id is None else zlib.crc32(str(doc_id).encode()) % 7


def plain_score(net, words, counts, text):
    """One token after the other: gates, class, member, and the share of a word among its form."""
    w = {k: v.astype(np.float64) for k, v in net.w.items()}
    n, h, last, total = lm.HIDDEN, np.zeros(lm.HIDDEN), words.end, 0.0
    own = {k: s for k, s, other in zip(words.index, words.symbol.tolist(), words.other) if not other}
    soft = lambda v: v / (1 + np.abs(v))
    for t in [*tokens(text), lm.END]:
        symbol = words.end if t == lm.END else own.get(t, int(words.form_symbol[lm.form(t)]))
        x, a = w["emb"][last] @ w["wx"] + w["bx"], h @ w["u"]
        gate = 0.5 + 0.5 * soft(x[: 2 * n] + a[: 2 * n])
        new = soft(x[2 * n :] + gate[n:] * a[2 * n :])
        h = new + gate[:n] * (h - new)
        kind, member = divmod(symbol, lm.PER_CLASS)
        z, y = h @ w["wc"] + w["bc"], h @ w["ww"][kind] + w["bw"][kind]
        total += (z[kind] - np.log(np.exp(z).sum()) + y[member] - np.log(np.exp(y).sum())) / np.log(10)
        if t != lm.END and t not in own:
            f = lm.form(t)
            total += np.log10((counts.get(t, 0) + 1) / (words.form_n[f] + words.form_v[f] + 1))
        last = symbol
    return total


def test_scores_match_token_by_token(spark, monkeypatch):
    table = rows()
    held = {}
    monkeypatch.setattr(lm, "train", lambda net, *a, **k: [])

    def keep(docs, net, words):
        rng = np.random.default_rng(2)
        held["net"] = lm.Network({k: (v + rng.standard_normal(v.shape) * 0.2).astype(np.float32) for k, v in net.w.items()})
        held["words"] = words
        return held["net"]

    monkeypatch.setattr(lm, "sweep", keep)
    got = lm.score(spark.createDataFrame(table, COLUMNS).repartition(3), hot_words=40).collect()
    counts = Counter(t for i, text, *_ in table if fold_of(i) != 2 for t in [*tokens(text), lm.END])
    total, distinct = sum(counts.values()), len(counts)
    assert len(held["words"].index) <= 41 < distinct
    want = []
    for i, text, *_ in table:
        row = [*tokens(text), lm.END]
        base = sum(np.log10((counts.get(t, 0) + 1) / (total + distinct + 1)) for t in row)
        want.append((str(i), fold_of(i) == 2, len(row), sum(t in counts for t in row), total, base, text if len(row) < 1000 else "long"))
    order = lambda r: (r[0], r[2], r[5])
    found = sorted(((str(r.doc_id), r.held_out, r.n_tokens, r.n_known, r.train_tokens, r.base_score, r.score) for r in got), key=order)
    want.sort(key=order)
    assert [f[:5] for f in found] == [w[:5] for w in want]
    for f, w in zip(found, want):
        assert f[5] == pytest.approx(w[5], rel=1e-9, abs=1e-6)
        text = "solo " * 30_000 if w[6] == "long" else w[6]
        assert f[6] == pytest.approx(plain_score(held["net"], held["words"], counts, text), rel=2e-4, abs=2e-3)


def test_symbol_rows_are_the_lexicon_rows():
    texts = ["Ab c. d, é. É, x", "", " ", "\t\x0b a\x1cb é", "日本. z" * 40]
    counts = Counter(t for x in texts for t in [*tokens(x), lm.END])
    counts["other".encode()] = 3
    forms = {}
    for w, n in counts.items():
        if w:
            n0, v0 = forms.get(lm.form(w), (0, 0))
            forms[lm.form(w)] = (n0 + n, v0 + 1)
    words = lm.Lexicon(list(counts.items())[:5], sum(counts.values()), len(counts), forms)
    small = lm.Symbols(words)
    for t in texts:
        assert small.row(t.encode()).tolist() == words.symbols(t.encode())[0].tolist()


def test_empty_table(spark):
    assert lm.score(spark.createDataFrame([], COLUMNS)).count() == 0
