"""The lossless WebP store: round trips through every feature of the decoder, and the digest columns."""

import hashlib
import itertools
import zlib

import numpy as np
import pytest

from pointveil.llm import webp


def picture(kind, h, w):
    rng = np.random.default_rng(h * 100 + w)
    if kind == "noise":
        return rng.integers(0, 256, (h, w, 4), dtype=np.uint8)
    colours = rng.integers(0, 256, ({"two": 2, "four": 4, "few": 11, "many": 200}[kind], 4), dtype=np.uint8)
    return colours[rng.integers(0, len(colours), (h, w))]


@pytest.mark.parametrize("h,w", [(1, 1), (3, 5), (9, 17), (16, 16)])
def test_plain_round_trip(h, w):
    p = picture("noise", h, w)
    assert (webp.decode(webp.encode(p)) == p).all()
    assert (webp.decode(webp.encode(p, riff=False)) == p).all()


@pytest.mark.parametrize("mode", range(14))
def test_predictors(mode):
    p = picture("noise", 7, 9)
    assert (webp.decode(webp.encode(p, predictor=mode)) == p).all()


def test_all_feature_mixes():
    for kind, palette, predictor, cross, green, cache, refs in itertools.product(
        ("few", "noise"), (False, True), (None, 2, 11), (None, (100, -3, 77)), (False, True), (0, 4), (False, True)
    ):
        if palette and kind == "noise":
            continue
        p = picture(kind, 6, 11)
        assert (webp.decode(webp.encode(p, palette, predictor, cross, green, cache, refs)) == p).all()


@pytest.mark.parametrize("kind", ["two", "four", "few", "many"])
def test_palette_packing(kind):
    p = picture(kind, 5, 13)
    assert (webp.decode(webp.encode(p, palette=True)) == p).all()
    assert (webp.decode(webp.encode(p, palette=True, refs=True, cache=3)) == p).all()


def test_back_references_reach_and_overlap():
    p = np.zeros((10, 30, 4), dtype=np.uint8)
    p[4:, 7:] = picture("few", 6, 23)
    data = webp.encode(p, refs=True)
    assert len(data) < len(webp.encode(p)) and (webp.decode(data) == p).all()


def test_broken_files_raise():
    good = webp.encode(picture("noise", 4, 4))
    for bad in (b"", b"RIFF", good[:40], b"RIFF\0\0\0\0WEBPVP8 \0\0\0\0", b"\x2f" + b"\xff" * 30):
        with pytest.raises((ValueError, IndexError, KeyError)):
            webp.decode(bad)


def test_media_columns(spark):
    texts = [None, "", "a", "é" * 40, "x" * 64, "y" * 65, "z\0" * 300_000, "a"]
    df = spark.createDataFrame([(i, t, 1) for i, t in enumerate(texts)], "doc_id long, text string, feature int")
    got = {r.doc_id: r for r in webp.media_columns(df).collect()}
    for i, t in enumerate(texts):
        raw = (t or "").encode()
        pay = raw + b"\0" * (max(64, -(-len(raw) // 64) * 64) - len(raw))
        r = got[i]
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(pay), hashlib.sha256(pay).hexdigest(), zlib.crc32(pay[-64:]))
    assert got[2].media_sha256 == got[7].media_sha256 and got[2].feature == got[7].feature
    assert webp.media_columns(df.limit(0)).count() == 0


def test_decode_images_writes_pixels(spark):
    p = picture("few", 5, 6)
    rows = [(1, webp.encode(p, palette=True)), (2, b"junk"), (3, None)]
    got = {r.media_id: r for r in webp.decode_images(spark.createDataFrame(rows, "media_id long, media binary")).collect()}
    assert (got[1].width, got[1].height, bytes(got[1].pixels)) == (6, 5, p.tobytes())
    assert got[2].error and got[2].pixels is None and got[3].error
