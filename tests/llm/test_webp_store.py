"""Stored payloads are read through prefix codes, back-references, the colour cache and transforms; foreign bytes decode."""

import base64
import random

import numpy as np
import pyarrow.parquet as pq
import pytest

from pointveil.llm import webp, webp_read, webp_write
from pointveil.llm.webp_write import chosen, code_lengths


def words(n, seed=4):
    rnd = random.Random(seed)
    return " ".join(rnd.choices(["alpha", "beta", "gamma", "delta", "seven", "of", "twelve"], k=n)).encode()


def padded(text):
    return text + b"\0" * (-len(text) % 64)


def test_stored_payloads_are_compressed():
    payload = padded(words(600))
    media, tally = webp.store(payload), {}
    assert len(media) < len(payload) / 2
    assert webp.decode(media, tally).tobytes()[: len(payload)] == payload
    assert tally["literals"] and tally["references"] and tally["cached"]


def test_documents_meet_every_kind_of_symbol():
    texts = pq.read_table("/root/testdata/sf0.01/documents.parquet").column("text").to_pylist()
    tally, size, stored = {}, 0, 0
    for t in texts:
        payload = padded((t or "").encode()) or b"\0" * 64
        media = webp.store(payload)
        assert webp.decode(media, tally).tobytes()[: len(payload)] == payload
        size, stored = size + len(payload), stored + len(media)
    assert all(tally[k] > 0 for k in ("literals", "references", "cached", "palette"))
    assert stored < 0.6 * size


@pytest.mark.parametrize("option", ["predictor", "cross_colour", "green", "palette"])
def test_the_transform_that_suits_an_image_is_chosen(option):
    rng = np.random.default_rng(3)
    y, x = np.mgrid[:64, :64]
    noise = rng.integers(0, 256, (64, 64), dtype=np.uint8)
    flat = np.full_like(noise, 255)
    image = {
        "predictor": np.stack([flat, *[(((3 + k) * y + 5 * x + (7 - 2 * k) * x * y // 64) & 255).astype(np.uint8) for k in range(3)]], axis=2),
        "green": np.stack([flat, noise + rng.integers(0, 4, noise.shape, dtype=np.uint8), noise, noise + 9], axis=2),
        "cross_colour": np.stack([flat, (noise.view(np.int8).astype(int) * 20 >> 5).astype(np.uint8) + rng.integers(0, 4, noise.shape, dtype=np.uint8), noise, (noise.view(np.int8).astype(int) * -25 >> 5).astype(np.uint8)], axis=2),
        "palette": rng.integers(0, 256, (9, 4), dtype=np.uint8)[noise % 9],
    }[option]
    options, tally = chosen(image, 8), {}
    assert option in options
    assert (webp.decode(webp.encode(image, **options), tally) == image).all() and tally[option] == 1


def test_several_code_groups():
    rng = np.random.default_rng(8)
    p = rng.integers(0, 256, (20, 40, 4), dtype=np.uint8)
    p[8:] &= 15
    for options in ({}, {"cache": 5, "refs": True}, {"green": True, "predictor": 11}):
        data = webp.encode(p, groups=3, **options)
        assert (webp.decode(data) == p).all()


def test_both_readers_agree(monkeypatch):
    payload = padded(words(900) + bytes(300) + words(40) * 9)
    media = webp.store(payload)
    whole = webp.decode(media)
    for stretch in (64, 1000):
        monkeypatch.setattr(webp_read, "STRETCH", stretch)
        assert (webp.decode(media) == whole).all()
    slow = lambda bits, group, *rest: np.array(webp_read._read_symbols(bits, [webp_read._tables(group)], *rest[:3], 0, None, rest[3]))
    monkeypatch.setattr(webp_read, "_read_stretches", slow)
    assert (webp.decode(media) == whole).all()


def test_code_lengths_are_optimal_and_bounded():
    rng = np.random.default_rng(1)
    for n in (2, 3, 7, 60, 256):
        counts = rng.integers(0, 50, n) ** 3
        counts[:2] += 1
        lengths = code_lengths(counts, 60)
        pool = sorted(counts[counts > 0].tolist())
        best = 0
        while len(pool) > 1:
            pair = pool.pop(0) + pool.pop(0)
            best += pair
            pool = sorted([*pool, pair])
        assert int((counts * lengths).sum()) == best
        assert (0.5 ** lengths[lengths > 0]).sum() == 1
    steep = np.array([1 << k for k in range(30)])
    assert code_lengths(steep, 11).max() == 11 and (0.5 ** code_lengths(steep, 11)).sum() == 1


def test_a_file_of_another_encoder():
    # a widely published one-pixel lossless file that browsers are probed with
    known = base64.b64decode("UklGRhoAAABXRUJQVlA4TA0AAAAvAAAAEAcQERGIiP4HAA==")
    assert webp.decode(known).shape == (1, 1, 4)


def bits_to_bytes(text):
    """Bytes of bits written in stream order, blanks aside."""
    flat = [int(b) for b in text.replace(" ", "")]
    return np.packbits(np.array(flat, dtype=np.uint8), bitorder="little").tobytes()


def number(value, width):
    return "".join(str(value >> i & 1) for i in range(width))


def test_hand_written_streams():
    head = number(0x2F, 8) + number(1, 14) + number(0, 14) + "1" + "000"  # 2 x 1 pixels
    one = lambda s: "10" + "1" + number(s, 8)  # noqa: E731  one symbol of eight bits
    plain = head + "0" + "0" + "0" + one(7) + one(9) + one(11) + one(255) + one(0)
    assert webp.decode(bits_to_bytes(plain)).tolist() == [[[255, 9, 7, 11]] * 2]
    # two greens (3 and 200); the second pixel takes the longer symbol
    two = "11" + "1" + number(3, 8) + number(200, 8)
    assert webp.decode(bits_to_bytes(head + "000" + two + one(1) + one(2) + one(255) + one(0) + "0" + "1")).tolist() == [[[255, 1, 3, 2], [255, 1, 200, 2]]]
    # subtracted green is added back to red and blue
    green = head + "1" + number(2, 2) + "0" + "00" + one(250) + one(10) + one(3) + one(255) + one(0)
    assert webp.decode(bits_to_bytes(green)).tolist() == [[[255, 4, 250, 253]] * 2]
    # a palette of two colours, eight to a byte: indices 1, 0 in the green byte 1
    palette = head + "1" + number(3, 2) + number(1, 8) + "0" + "11" + "1" + number(10, 8) + number(15, 8) + one(1) + one(2) + one(255) + one(0) + "0" + "1"
    palette += "0" + "00" + one(1) + one(0) + one(0) + one(255) + one(0)
    assert webp.decode(bits_to_bytes(palette)).tolist() == [[[254, 2, 25, 4], [255, 1, 10, 2]]]


def test_hand_written_reference_and_cache():
    head = number(0x2F, 8) + number(3, 14) + number(0, 14) + "1" + "000"  # 4 x 1 pixels
    one = lambda s: "10" + "1" + number(s, 8)
    colour = 255 << 24 | 1 << 16 | 5 << 8 | 2
    slot = (colour * 0x1E35A7BD & 0xFFFFFFFF) >> 31
    # green alphabet of 256 + 24 + 2 with three symbols: literal 5 (1 bit), run of 2 (2 bits), the colour's slot (2 bits);
    # lengths are told by a code over 0 (unused here), 1, 2, 17, 18
    told = "0" + number(11 - 4 + 4, 4)
    order = (17, 18, 0, 1, 2, 3, 4, 5, 16, 6, 7, 8, 9, 10, 11)
    size = {0: 2, 1: 2, 2: 2, 18: 2}
    told += "".join(number(size.get(s, 0), 3) for s in order)
    code = {0: "00", 1: "01", 2: "10", 18: "11"}
    told += "0"  # all 282 lengths follow
    lengths = code[0] * 5 + code[1]
    lengths += code[18] + number(138 - 11, 7) + code[18] + number(112 - 11, 7)  # up to symbol 256
    lengths += code[0] + code[2]  # 256: run of 1; 257: run of 2
    lengths += code[18] + number(22 - 11, 7) + "".join(code[2] if s == slot else code[0] for s in range(2))
    group = told + lengths + one(1) + one(2) + one(255) + one(1)
    body = "0" + "1" + number(1, 4) + "0" + group
    # literal; run of 2 at plane code 2 (one pixel left); cached colour
    stream = bits_to_bytes(head + body + "0" + "10" + "11")
    tally = {}
    assert webp.decode(stream, tally).tolist() == [[[255, 1, 5, 2]] * 4]
    assert tally == {"literals": 1, "references": 1, "cached": 1}


def test_odd_tables(spark):
    rows = [(None, "a", 1), (2, "b", 1), (2, "b", 1), (2, "other", 1), (3, None, 1), (3, "", 1), (4, "ab é " * 120_000, 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, media_bytes int")
    got = webp.media_columns(docs).collect()
    assert sorted(str(r.doc_id) for r in got) == sorted(str(r[0]) for r in rows)
    assert len({(r.payload_sha256, r.media_sha256, r.feature) for r in got}) == 5
    assert max(r.n_bytes for r in got) == len(("ab é " * 120_000).encode())
