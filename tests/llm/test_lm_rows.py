"""The language model's weights come from all training rows, not from the starting sample alone."""

import random

import numpy as np

from pointveil.llm import lm


def test_rows_outside_the_sample_shape_the_weights(spark):
    rnd = random.Random(3)
    cycle = ["red", "blue", "green", "white", "black", "grey"]
    rows = []
    for i in range(3000):
        at = rnd.randrange(6)
        rows.append((i, " ".join(cycle[(at + k) % 6] for k in range(60))))
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(2, "doc_id")
    got = [r for r in lm.score(docs, bound=0).collect() if r.held_out]
    # one of six words follows: the unigram share is 1/6, a model of the order comes near 1
    base, own = (sum(x) / sum(r.n_tokens for r in got) for x in ([r.base_score for r in got], [r.score for r in got]))
    assert own > base + 0.3


def test_sweep_averages_tasks_by_tokens(spark):
    words = lm.Lexicon([(b"a", 9), (b"b.", 5), (b"", 3)], 17, 3, {0: (9, 1), 1: (5, 1)})
    net = lm.Network.fresh(words.mass)
    docs = spark.createDataFrame([(None,), ("a b. " * 40,), ("a " * 300,)], "text string")
    got = lm.sweep(docs.coalesce(1), net, words, run_tokens=50)
    mine = lm.Network({k: v.copy() for k, v in net.w.items()})
    ids = [words.symbols(t.encode())[0] for t in ("", "a b. " * 40, "a " * 300)]
    for held in (ids[:2], ids[2:]):
        lm.train(mine, held, words.end, epochs=1, most_streams=8, rate=lm.SWEEP_RATE)
    assert all(np.allclose(got.w[k], mine.w[k], atol=1e-5) for k in net.w)
    assert lm.sweep(docs.limit(0), net, words) is net
