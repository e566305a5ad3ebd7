"""Held-out accuracy, brute force and edge cases of the learned operators and the tokenizer."""

import hashlib
import math
import random
import zlib
from collections import Counter

import numpy as np
import pytest

from pointveil.llm import bpe, langid, lm, quality, toxicity
from pointveil.llm.common import documents, labels
from pointveil.llm.gru import Gru
from pointveil.llm.textops import Words

SF = "/root/testdata/sf0.01"
EDGES = [None, "", " ", "\n\t", "a", "\U0001F600 é́", "x" * 5000, "word " * 6000]


def edge_frame(spark):
    return spark.createDataFrame([(i, t, None, "s", 7) for i, t in enumerate(EDGES)] + [(1, "", None, "s", 7), (None, "a", None, None, None)], "doc_id long, text string, lang string, source string, score int")


def auc(score, label):
    order = np.argsort(score, kind="stable")
    rank = np.empty(len(score))
    rank[order] = np.arange(len(score))
    pos = label == 1
    return (rank[pos].mean() - (pos.sum() - 1) / 2) / (len(label) - pos.sum())


def held_out(rows):
    return [r for r in rows if zlib.crc32(str(r.doc_id).encode()) % 4 == 2]


@pytest.mark.parametrize("run,label,sf,least", [(quality.quality, "quality", SF, 0.95), (toxicity.toxicity, "toxic", "/root/testdata/sf0.1", 0.9)])
def test_classifiers_on_held_out_rows(spark, run, label, sf, least):
    docs, marks = documents(spark, sf), labels(spark, sf)
    got = run(docs, marks).collect()
    assert len(got) == docs.count() and all(0 <= r.score <= 1 for r in got)
    truth = {r.doc_id: r[label] for r in marks.collect()}
    rows = [r for r in held_out(got) if r.doc_id in truth]
    assert all(r.held_out for r in rows)
    assert auc(np.array([r.score for r in rows]), np.array([truth[r.doc_id] for r in rows])) > least


def test_classifiers_take_edge_cases(spark):
    df = edge_frame(spark)
    marks = spark.createDataFrame([(4, 1, 0), (6, 0, 1), (7, 1, 1), (None, 1, 0), (5, None, None)], "doc_id long, quality int, toxic int")
    for run in (quality.quality, toxicity.toxicity):
        for m in (marks, marks.limit(0)):
            rows = run(df, m).collect()
            assert len(rows) == df.count() and all(r.score is not None and 0 <= r.score <= 1 for r in rows)
        assert run(df.limit(0), marks).count() == 0


def test_language_on_held_out_rows(spark):
    docs = documents(spark, SF)
    truth = {r.doc_id: r.lang for r in docs.select("doc_id", "lang").collect()}
    rows = held_out(langid.language(docs).collect())
    assert np.mean([r.lang_pred == truth[r.doc_id] for r in rows]) > 0.95


def test_language_edge_cases(spark):
    df = edge_frame(spark)
    assert langid.train([]) is None
    model = langid.train([("the house is red and the sky", "en"), ("das haus ist rot und der himmel", "de")] * 20)
    got = {r.doc_id: r for r in langid.identify(df.where("doc_id > 1"), model).collect()}
    assert got[2].lang_pred == got[3].lang_pred == "und" and got[2].score == 0
    assert got[7].lang_pred in ("de", "en") and 0 <= got[7].score <= 1
    assert all(r.lang_pred == "und" for r in langid.language(df).collect())
    assert langid.identify(df.limit(0), model).count() == 0


def test_language_mean_equals_plain_average():
    model = langid.train([("aa bb cc", "x"), ("dd ee ff", "y")] * 10)
    text = b"aa bb aa zz"
    doc, back, owner, row, (n,) = langid.bags([text])
    total = [model.table[r] for w in back for r in row[owner == w]]
    want = np.mean(total, axis=0) @ model.weights + model.bias
    assert np.allclose(model.logits([text])[0], want, atol=1e-5)


def test_words_match_split():
    rnd = random.Random(1)
    texts = ["".join(rnd.choices(" \t\n\x0babéZ", k=rnd.randint(0, 30))).encode() for _ in range(200)]
    w = Words(texts)
    assert w.sizes.tolist() == [len(t.split()) for t in texts]
    flat = [x for t in texts for x in t.split()]
    assert [w.buffer[a:b].tobytes() for a, b in zip(w.start, w.end)] == flat
    seen = dict(zip(w.word_hashes().tolist(), flat))
    assert len(seen) == len(set(flat))


def test_gru_gradients():
    rng = np.random.default_rng(0)
    gru = Gru(3, rng)
    gru.u = gru.u.astype(np.float64)
    x, target = rng.standard_normal((4, 2, 9)), rng.standard_normal((4, 2, 3))
    keep = np.ones((4, 2, 1))
    keep[2, 0] = 0
    loss = lambda: float((gru.forward(x, np.zeros((2, 3)), keep)[0].astype(np.float64) * target).sum())
    _, tape = gru.forward(x, np.zeros((2, 3)), keep)
    dx, du = gru.backward(tape, target, keep)
    for arr, grad in ((x, dx), (gru.u, du)):
        for _ in range(6):
            at = tuple(rng.integers(0, s) for s in arr.shape)
            old = arr[at]
            arr[at] = old + 1e-2
            up = loss()
            arr[at] = old - 1e-2
            down = loss()
            arr[at] = old
            assert grad[at] == pytest.approx((up - down) / 2e-2, abs=2e-3)


def plain_lm_base(rows):
    fold = {i: zlib.crc32(str(i).encode()) % 7 for i, _ in rows}
    count = Counter()
    for i, t in rows:
        if fold[i] != 2:
            count.update((t or "").encode().lower().split())
            count[b""] += 1
    n, v = sum(count.values()), len(count)
    out = {}
    for i, t in rows:
        tokens = [*(t or "").encode().lower().split(), b""]
        out[i] = (len(tokens), sum(count[w] > 0 for w in tokens), n, sum(math.log10((count[w] + 1) / (n + v + 1)) for w in tokens))
    return out


def test_lm_base_and_model(spark):
    rows = [(r.doc_id, r.text) for r in documents(spark, SF).select("doc_id", "text").limit(400).collect()] + [(10**6, None), (10**6 + 1, ""), (10**6 + 2, "zzqq unseenword")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = plain_lm_base(rows)
    for hot in (1 << 18, 3000):
        got = {r.doc_id: r for r in lm.score(df, hot_words=hot).collect()}
        assert set(got) == set(want)
        for i, (n, known, total, base) in want.items():
            r = got[i]
            assert (r.n_tokens, r.n_known, r.train_tokens) == (n, known, total)
            assert r.base_score == pytest.approx(base, rel=1e-9) and r.score < 0
    held = [r for r in got.values() if r.held_out]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)
    assert lm.score(df.limit(0)).count() == 0


def test_lm_is_a_distribution():
    words = [(b"a", 9), (b"b.", 5), (b"c", 4), (b"", 3)]
    lex = lm.Lexicon(words, 21, 4, {0: (13, 2), 1: (5, 1)})
    net = lm.Network.fresh(lex.mass)
    state = np.full((lm.SYMBOLS, lm.HIDDEN), 0.3, dtype=np.float32)
    assert np.exp(net.log_probs(state, np.arange(lm.SYMBOLS)).astype(np.float64)).sum() == pytest.approx(1, abs=1e-4)
    a, b = np.array([5, 3, lex.end]), np.array([7, lex.end])
    both = net.text_scores([b, a], lex.end)
    assert both[0] == pytest.approx(net.text_scores([b], lex.end)[0], abs=1e-4) and both[1] == pytest.approx(net.text_scores([a], lex.end)[0], abs=1e-4)


def tokenizer_path():
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def test_bpe_equals_the_library(spark):
    from tokenizers import Tokenizer

    real, mine = Tokenizer.from_file(tokenizer_path()), bpe.held(tokenizer_path())
    rnd = random.Random(3)
    signs = "abcABC019 .,!'\n\t\r\x0b\xa0 éß中字ا²½\U0001F600‍_-<|endoftext|>"
    texts = ["".join(rnd.choices(signs, k=rnd.randint(0, 50))) for _ in range(3000)] + ["<|endoftext|>a<|endoftext|>", "x" * 700, "ab" * 900, "   \n  x", "I'll don't 'S"]
    texts += [r.text for r in documents(spark, SF).select("text").limit(200).collect()]
    for t, ids in zip(texts, mine.encode_batch(texts)):
        want = real.encode(t, add_special_tokens=False).ids
        assert ids == want and mine.decode(ids) == real.decode(want, skip_special_tokens=False)


def test_bpe_pair_test_is_exact_merging():
    mine = bpe.held(tokenizer_path())
    rng = np.random.default_rng(4)
    tokens = np.array(list(mine.sound.values()))
    a, b = rng.choice(tokens, 3000), rng.choice(tokens, 3000)
    want = [mine.exact(mine.text[x] + mine.text[y]) == [x, y] for x, y in zip(a, b)]
    assert mine.compatible(a, b).tolist() == want


def test_bpe_round_trip_query(spark):
    df = edge_frame(spark)
    got = {r.doc_id: r for r in bpe.round_trip(df.where("doc_id > 1"), tokenizer_path()).collect()}
    for i, t in enumerate(EDGES):
        if i > 1:
            assert got[i].decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest()
    coded = bpe.encode_column(df.where("doc_id > 1"), tokenizer_path())
    assert {r.doc_id: r.text for r in bpe.decode_column(coded, tokenizer_path()).collect()} == {i: t for i, t in enumerate(EDGES) if i > 1}
    assert bpe.round_trip(df.limit(0), tokenizer_path()).count() == 0
