"""Many images stored and read together against one by one."""

import numpy as np
import pytest

from pointveil.llm import webp, webp_many
from pointveil.llm.webp_read import decode
from pointveil.llm.webp_write import chosen, encode


def texts():
    rng = np.random.default_rng(5)
    words = ["".join(chr(97 + c) for c in rng.integers(0, 26, n)) for n in rng.integers(1, 11, 400)]
    prose = [" ".join(rng.choice(words, int(n))).encode() for n in rng.integers(1, 900, 90)]
    odd = [b"", b"a", b"ab" * 700, bytes(range(256)) * 9, b"\0" * 640, b"x" * 64, b"x" * 65, rng.bytes(3000), rng.bytes(webp.MANY_BYTES + 1), b"long passage " * 4000]
    runs = [b"one passage of some length " * int(n) + rng.bytes(5) for n in rng.integers(1, 60, 40)]
    return prose + odd + runs


def test_rows_are_those_of_single_texts():
    every = texts()
    want = [webp.media_row(t) for t in every]
    assert webp.media_rows(every) == want
    # whatever else is in a batch
    assert webp.media_rows(every[::-1]) == want[::-1]
    assert [webp.media_rows([t])[0] for t in every[85:105]] == want[85:105]
    assert webp.media_rows([]) == []


def pictures(n):
    rng = np.random.default_rng(n)
    out = []
    for i in range(n):
        p = rng.integers(0, 256, (int(rng.integers(1, 30)), 16, 4), dtype=np.uint8)
        if i % 5 == 0:
            p = rng.integers(0, 256, (30, 4), dtype=np.uint8)[rng.integers(0, 30 if i % 2 else 9, (29, 16))]  # few colours
        elif i % 5 == 1:
            p = np.cumsum(p % 3, axis=1, dtype=np.uint8)  # steps to the right
        elif i % 5 == 2:
            p[:, :, 1] = p[:, :, 3] = p[:, :, 2]  # red and blue follow green
        elif i % 5 == 3:
            p[:, :, 1] = (p[:, :, 2].view(np.int8) // 2).view(np.uint8)
        out.append(np.ascontiguousarray(p))
    return out


def test_files_have_the_transforms_of_single_images():
    images = pictures(120)
    tally: dict[str, int] = {}
    files = webp_many.stored(images, 8)
    assert files == [encode(p, **chosen(p, 8)) for p in images]
    for p, f in zip(images, files):
        assert (decode(f, tally) == p).all()
    assert {"predictor", "cross_colour", "green", "palette", "literals", "references", "cached"} <= set(tally)


def test_all_kinds_of_files_are_read_together():
    images = pictures(150)
    options = [{}, {"cache": 8, "refs": True}, {"cache": 3, "groups": 3}, {"cache": 8}, {"cache": 8, "refs": True, "riff": False}, {"palette": False, "green": True, "cache": 8}]
    files = [encode(p, **options[i % len(options)]) for i, p in enumerate(images)]
    files.append(encode(np.full((9, 16, 4), 7, dtype=np.uint8)))  # a symbol without bits
    images.append(np.full((9, 16, 4), 7, dtype=np.uint8))
    for p, back in zip(images, webp_many.read_many(files)):
        assert back.shape == p.shape and (back == p).all()


def test_a_cut_file_is_refused():
    files = [encode(p, cache=8, refs=True) for p in pictures(80)]
    files[40] = encode(pictures(1)[0].repeat(9, axis=0), cache=8, riff=False)[:-9]
    with pytest.raises((ValueError, IndexError)):
        webp_many.read_many(files)


def test_the_query_stores_short_texts_together(monkeypatch):
    seen, stored = [], webp.stored
    monkeypatch.setattr(webp, "stored", lambda images, cache: seen.append(len(images)) or stored(images, cache))
    webp.media_rows([b"text %d" % i for i in range(300)])
    assert len(seen) == 2 and sum(seen) == 300
