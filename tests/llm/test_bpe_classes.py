"""Byte-level BPE against the tokenizers library: every sign beside suffixes, blanks, digits and letters; odd tables."""

import hashlib
import unicodedata

import numpy as np
import public_tokenizers
from tokenizers import Tokenizer

from pointveil.llm import bpe

PATH = public_tokenizers.path("byte_bpe_50k.json")


def library(texts):
    return [e.ids for e in Tokenizer.from_file(PATH).encode_batch(texts, add_special_tokens=False)]


def test_every_sign_falls_into_the_library_class():
    ranges = bpe.LETTERS_16 + bpe.NUMBERS_16 + bpe.LATER
    odd = {c for a, b in ranges for c in {a - 1, a, (a + b) // 2, b, b + 1}}
    known = {c for c in range(0x2F800) if unicodedata.category(chr(c)) not in ("Cn", "Cs", "Co", "Lo")} | set(range(0x3000))
    signs = [chr(c) for c in sorted(odd | known) if not 0xD800 <= c < 0xE000]
    texts = [f"{c}'s{c}'re {c}1{c} a{c}!{c}\n{c}" for c in signs]
    got = bpe.Bpe(PATH).encode_batch(texts)
    assert [c for c, a, b in zip(signs, library(texts), got) if a != b] == []


def test_odd_tables(spark):
    rows = [(1, None, 7), (1, "", 7), (None, "a\u0558's", 7), (2, "same", 7), (2, "same", 7), (3, "long " * 60_000 + "x" * 5_000, 7)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, ids_sha256 int")
    got = sorted((str(r.doc_id), r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in bpe.round_trip(docs, PATH).collect())
    want = []
    for (n, t, _), ids in zip(rows, library([t or "" for _, t, _ in rows])):
        back = Tokenizer.from_file(PATH).decode(ids, skip_special_tokens=False)
        want.append((str(n), len(ids), hashlib.sha256(np.array(ids, dtype="<u4").tobytes()).hexdigest(), hashlib.sha256(back.encode()).hexdigest()))
    assert got == sorted(want)
    assert bpe.round_trip(docs.limit(0), PATH).count() == 0
