"""Lossless WebP: stored text payloads, their digest columns, and images to pixel arrays.

``webp_write`` fits prefix codes, back-references, a colour cache and one transform to each image; ``webp_read``
undoes all of the format, symbol by symbol through lookup tables.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_chunks, texts_of
from .webp_many import read_many, stored
from .webp_planes import MOST_SIDE
from .webp_read import decode
from .webp_write import chosen, encode

def shape_of(n_bytes: int) -> tuple[int, int]:
    """(height, width) in pixels of a payload: 16 pixels wide, doubled while the image would be too high."""
    width = 16
    while n_bytes > 4 * width * MOST_SIDE:
        width *= 2
    if width > MOST_SIDE:
        raise ValueError("a payload over 1 GiB needs more than one image")
    return -(-n_bytes // (4 * width)), width


#: Colour-cache bits of a stored payload.
STORE_CACHE = 8


#: Payloads of up to so many bytes are stored and read many together: so many images, of so many bytes in all.
MANY_BYTES, MANY_IMAGES, MANY_TOTAL = 1 << 15, 256, 1 << 20


def _pixels(payload: bytes) -> np.ndarray:
    height, width = shape_of(len(payload))
    full = payload + b"\0" * (4 * height * width - len(payload))
    return np.frombuffer(full, dtype=np.uint8).reshape(height, width, 4)


def store(payload: bytes) -> bytes:
    """Lossless WebP of a payload, with the transform that suits it, back-references and a colour cache.

    The payload's length is a positive multiple of 64; a wider last row ends in zeros.
    """
    pixels = _pixels(payload)
    return encode(pixels, **chosen(pixels, STORE_CACHE))


def features(pixels: np.ndarray) -> str:
    """Size, channel means and a 64-cell brightness hash over equal runs of the samples, as text."""
    flat = pixels.reshape(-1)
    if len(flat) < 64:
        flat = np.pad(flat, (0, 64 - len(flat)))
    if len(flat) % 64 == 0:  # whole cells, and rows that are wide enough to be summed fast
        total = flat.reshape(-1, 64).sum(axis=0, dtype=np.int64).reshape(-1, 4).sum(axis=0)
        cells = flat.reshape(64, -1).sum(axis=1, dtype=np.int64) / (len(flat) // 64)
    else:
        total = pixels.reshape(-1, 4).sum(axis=0, dtype=np.int64)
        cut = len(flat) * np.arange(65) // 64
        cells = np.add.reduceat(flat, cut[:-1], dtype=np.int64) / np.diff(cut)
    means = total / (pixels.size // 4)
    bits = np.packbits(cells > total.sum() / len(flat)).tobytes().hex()
    return f"{pixels.shape[1]}x{pixels.shape[0]};" + ",".join(f"{m:.3f}" for m in means) + f";{bits}"


FIELDS = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def _padded(text: bytes) -> bytes:
    return text + b"\0" * (max(64, -(-len(text) // 64) * 64) - len(text))


def _told(text: bytes, media: bytes, pixels: np.ndarray) -> tuple:
    payload_bytes = max(64, -(-len(text) // 64) * 64)
    back = pixels.tobytes()[:payload_bytes]
    return len(text), payload_bytes, hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(media), hashlib.sha256(media).hexdigest(), features(pixels)


def media_row(text: bytes) -> tuple:
    """The digest columns of one text, all taken from the stored bytes read back."""
    media = store(_padded(text))
    return _told(text, media, decode(media))


def media_rows(texts: list[bytes]) -> list[tuple]:
    """``media_row`` of every text; short ones are stored and read together, like lengths first."""
    rows: list[tuple | None] = [None] * len(texts)
    part, total = [], 0
    for i in sorted(range(len(texts)), key=lambda i: len(texts[i])):
        if len(texts[i]) > MANY_BYTES:
            rows[i] = media_row(texts[i])
            continue
        if part and (len(part) == MANY_IMAGES or total + len(texts[i]) > MANY_TOTAL):
            _tell_part(texts, part, rows)
            part, total = [], 0
        part.append(i)
        total += len(texts[i])
    if part:
        _tell_part(texts, part, rows)
    return rows


def _tell_part(texts: list[bytes], part: list[int], rows: list) -> None:
    media = stored([_pixels(_padded(texts[i])) for i in part], STORE_CACHE)
    for i, one, pixels in zip(part, media, read_many(media)):
        rows[i] = _told(texts[i], one, pixels)


def media_columns(docs: DataFrame) -> DataFrame:
    """Store every whole text (null: empty) as a lossless WebP image and describe what is read back.

    One row per input row: repeated and null ids and equal rows stay separate, other columns are not read. An empty
    table gives an empty result.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [f.split()[0] for f in FIELDS.split(", ")]
        for batch in batches:
            for part in byte_chunks(batch):
                texts = texts_of(part)
                each = list(dict.fromkeys(texts))  # equal texts have equal values
                done = dict(zip(each, media_rows(each)))
                rows = list(zip(*map(done.__getitem__, texts)))
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), *[pa.array(c) for c in rows]], names)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, FIELDS)


def decode_images(images: DataFrame) -> DataFrame:
    """(media_id, width, height, pixels, error) of (media_id, media) rows: A, R, G, B bytes; a broken file gives its error."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for media in batch.column("media").to_pylist():
                try:
                    p = decode(media or b"")
                    rows.append((p.shape[1], p.shape[0], p.tobytes(), None))
                except (ValueError, IndexError, KeyError) as e:
                    rows.append((None, None, None, str(e) or type(e).__name__))
            w, h, p, e = zip(*rows) if rows else ((), (), (), ())
            yield pa.RecordBatch.from_arrays([batch.column("media_id"), pa.array(w, pa.int32()), pa.array(h, pa.int32()), pa.array(p, pa.binary()), pa.array(e, pa.string())], ["media_id", "width", "height", "pixels", "error"])

    return images.select(F.col("media_id").cast("long").alias("media_id"), "media").mapInArrow(run, "media_id long, width int, height int, pixels binary, error string")
