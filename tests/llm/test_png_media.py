from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from vtask.llm.png_media import SIGNATURE, _chunk, cosine_hash, op6_png_media, png_decode, png_encode, read_media, store_texts


def _paeth(a, b, c):
    p = a + b - c
    return min((abs(p - a), 0, a), (abs(p - b), 1, b), (abs(p - c), 2, c))[2]


def filtered(img, kinds, bpp):
    """Rows of img under the given filters, pixel by pixel."""
    out = b""
    for r, kind in enumerate(kinds):
        line = []
        for x in range(img.shape[1]):
            a = int(img[r, x - bpp]) if x >= bpp else 0
            b = int(img[r - 1, x]) if r else 0
            c = int(img[r - 1, x - bpp]) if r and x >= bpp else 0
            line.append((int(img[r, x]) - (0, a, b, (a + b) // 2, _paeth(a, b, c))[kind]) & 255)
        out += bytes([kind, *line])
    return out


@pytest.mark.parametrize(("color", "bpp"), [(0, 1), (4, 2), (2, 3), (6, 4)])
def test_every_filter(color, bpp):
    rng = np.random.default_rng(color)
    img = rng.integers(0, 256, (23, 7 * bpp), dtype=np.uint8)
    raw = filtered(img, rng.integers(0, 5, 23), bpp)
    data = SIGNATURE + _chunk(b"IHDR", struct.pack(">IIBBBBB", 7, 23, 8, color, 0, 0, 0)) + _chunk(b"tEXt", b"a\0b") + _chunk(b"IDAT", zlib.compress(raw)[:40]) + _chunk(b"IDAT", zlib.compress(raw)[40:]) + _chunk(b"IEND", b"")
    assert (png_decode(data) == img).all()


def test_round_trip_and_damage():
    rng = np.random.default_rng(1)
    for n in (64, 640, 64 * 3000):
        for p in (rng.integers(0, 256, n, dtype=np.uint8).tobytes(), bytes(range(64)) * (n // 64), b"abc " * (n // 4)):
            assert png_decode(png_encode(p)).tobytes() == p
    good = png_encode(b"abcd" * 64)
    for i in range(8, len(good), 7):
        with pytest.raises(ValueError):
            png_decode(good[:i] + bytes([good[i] ^ 1]) + good[i + 1 :])
    with pytest.raises(ValueError):
        png_decode(good[:-4])


def test_hash_is_the_cosine_transform():
    img = np.random.default_rng(2).integers(0, 256, (64, 64), dtype=np.uint8)
    small = img.astype(float).reshape(32, 2, 32, 2).mean(axis=(1, 3))
    k = np.arange(32)
    dct = np.cos(np.pi * k[:, None] * (2 * k + 1) / 64)
    c = np.round((dct @ small @ dct.T)[:8, :8], 6).ravel()
    assert cosine_hash(img) == np.packbits(c > np.median(c[1:])).tobytes()


def test_columns(spark, awkward, tmp_path):
    awkward.withColumn("media", F.lit(1)).write.parquet(str(tmp_path / "documents.parquet"))
    rows = op6_png_media(spark, str(tmp_path)).collect()
    texts = {r.doc_id: (r.text or "").encode() for r in awkward.collect()}
    assert len(rows) == 12
    for r in rows:
        t = texts[r.doc_id]
        p = t + b"\0" * (-len(t) % 64 or (0 if t else 64))
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(t), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:])) and len(r.feature) == 16
    bad = spark.createDataFrame([(1, None), (2, bytearray(b"nothing"))], "k int, media binary")
    assert [(r.k, r.payload, r.error) for r in read_media(bad).orderBy("k").collect()] == [(1, None, None), (2, None, "no PNG signature")]
    assert read_media(store_texts(awkward.limit(0))).count() == 0


def _image(head, raw, level=9):
    return SIGNATURE + _chunk(b"IHDR", head) + _chunk(b"IDAT", zlib.compress(raw, level)) + _chunk(b"IEND", b"")


def test_broken_headers_and_bombs_are_faults_of_their_row(spark):
    head = struct.pack(">IIBBBBB", 64, 1, 8, 0, 0, 0, 0)
    good = _image(head, b"\0" + b"x" * 64)
    bad = [_image(head[:-1], b"\0" * 65), _image(head + b"\0", b"\0" * 65), _image(b"", b""), _image(head, b"\0" * 200_000_000, 1), _image(struct.pack(">IIBBBBB", 2**31, 2**31, 8, 0, 0, 0, 0), b"\0")]
    bad += [_image(struct.pack(">IIBBBBB", 0, 5, 8, 0, 0, 0, 0), b"\0" * 5), _image(head, b"\5" + b"x" * 64), _image(head, b"\0" + b"x" * 63)]
    df = spark.createDataFrame([(i, bytearray(x)) for i, x in enumerate([good, *bad])], "k int, media binary")
    got = sorted(read_media(df).select("k", "payload", "error").collect())
    assert bytes(got[0].payload) == b"x" * 64 and got[0].error is None
    assert all(r.payload is None and r.error for r in got[1:]), got


def test_tall_images_of_late_filters():
    rng = np.random.default_rng(4)
    img = rng.integers(0, 256, (300, 33), dtype=np.uint8)
    kinds = np.repeat(rng.integers(0, 5, 60), 5)
    assert (png_decode(_image(struct.pack(">IIBBBBB", 33, 300, 8, 0, 0, 0, 0), filtered(img, kinds, 1))) == img).all()
