"""Texts as PNG media columns, and a PNG reader with checksum tests and numpy unfiltering.

The writer stores a payload as 8-bit grey samples, `width` to a row, and takes
whichever of the filters none, sub and up leaves the smallest differences. The
reader walks the chunks, tests each checksum, inflates the image data, undoes
all five row filters (rows of one kind together, those that need their left and
upper samples along diagonals), inflates no more than the header promises and
computes a 64-bit hash: the signs, about their median, of the 8 x 8 lowest
frequencies of the cosine transform of the image shrunk to 32 x 32.

Both steps are map-only. Defined cases: null text is the empty text; an empty
payload is one row of zeros; a null, damaged or unsupported image gives a null
payload and feature and its fault in `error`; other columns are ignored.
"""

from __future__ import annotations

import struct
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vtask.llm.common import need, sliced, text_values, tidy

# fixed values of the format
SIGNATURE = b"\x89PNG\r\n\x1a\n"
CHANNELS = {0: 1, 2: 3, 4: 2, 6: 4}
_IDAT = 1 << 16


def _chunk(kind: bytes, data: bytes) -> bytes:
    return struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(kind + data))


def png_encode(payload: bytes, width: int = 64, level: int = 6) -> bytes:
    """An 8-bit grey image, `width` samples to a row; the payload's length must be a positive multiple of width."""
    if not payload or len(payload) % width:
        raise ValueError("the payload must fill whole rows")
    img = np.frombuffer(payload, np.uint8).reshape(-1, width)
    rows = np.empty((img.shape[0], width + 1), np.uint8)
    left = np.zeros_like(img)
    left[:, 1:] = img[:, :-1]
    above = np.zeros_like(img)
    above[1:] = img[:-1]
    kinds = (img, img - left, img - above)
    cost = [int(np.minimum(k, 256 - k.astype(np.int16)).sum()) for k in kinds]
    kind = int(np.argmin(cost))
    rows[:, 0] = kind
    rows[:, 1:] = kinds[kind]
    data = zlib.compress(rows.tobytes(), level)
    head = struct.pack(">IIBBBBB", width, img.shape[0], 8, 0, 0, 0, 0)
    return SIGNATURE + _chunk(b"IHDR", head) + b"".join(_chunk(b"IDAT", data[i : i + _IDAT]) for i in range(0, len(data), _IDAT)) + _chunk(b"IEND", b"")


def _along_diagonals(block: np.ndarray, kinds: np.ndarray, above: np.ndarray, bpp: int) -> None:
    """Undo filters 3 and 4 in place: a sample needs its left, upper and upper left ones, so all of one diagonal are done at once."""
    high, wide = block.shape[0], block.shape[1] // bpp
    done = np.zeros((high + 1, wide + 1, bpp), np.int16)
    done[0, 1:] = above.reshape(wide, bpp)
    raw = block.reshape(high, wide, bpp)
    for t in range(high + wide - 1):
        r = np.arange(max(0, t - wide + 1), min(high, t + 1))
        x = t - r
        a, b, c = done[r + 1, x], done[r, x + 1], done[r, x]
        pa_, pb, pc = np.abs(b - c), np.abs(a - c), np.abs(a + b - 2 * c)
        paeth = np.where((pa_ <= pb) & (pa_ <= pc), a, np.where(pb <= pc, b, c))
        done[r + 1, x + 1] = (raw[r, x] + np.where(kinds[r, None] == 3, (a + b) >> 1, paeth)) & 255
    block[:] = done[1:, 1:].reshape(block.shape)


def _unfilter(raw: np.ndarray, height: int, stride: int, bpp: int) -> np.ndarray:
    rows = raw.reshape(height, stride + 1)
    kinds, out = rows[:, 0], rows[:, 1:].copy()
    if (kinds > 4).any():
        raise ValueError(f"unknown row filter {int(kinds.max())}")
    sort = np.minimum(kinds, 3)  # runs of rows that are undone together
    first = np.flatnonzero(np.concatenate(([True], sort[1:] != sort[:-1])))
    for i, j in zip(first.tolist(), [*first[1:].tolist(), height], strict=True):
        block = out[i:j]
        if sort[i] == 1:  # running sums along each row, for each byte of a sample
            for c in range(bpp):
                block[:, c::bpp] = np.cumsum(block[:, c::bpp], axis=1, dtype=np.uint8)
        elif sort[i] == 2:  # running sums down the columns
            if i:
                block[0] += out[i - 1]
            block[:] = np.cumsum(block, axis=0, dtype=np.uint8)
        elif sort[i] == 3:
            _along_diagonals(block, kinds[i:j], out[i - 1] if i else np.zeros(stride, np.uint8), bpp)
    return out


def png_decode(data: bytes, most: int = 1 << 30) -> np.ndarray:
    """Samples of an 8-bit image, (height, width * channels); ValueError on damage, an unsupported kind or more than `most` bytes of samples."""
    if data[:8] != SIGNATURE:
        raise ValueError("no PNG signature")
    at, head, idat, ended = 8, None, [], False
    while at < len(data):
        if at + 12 > len(data):
            raise ValueError("cut off within a chunk")
        size, kind = struct.unpack_from(">I4s", data, at)
        if at + 12 + size > len(data):
            raise ValueError("cut off within a chunk")
        body = data[at + 8 : at + 8 + size]
        if zlib.crc32(kind + body) != struct.unpack_from(">I", data, at + 8 + size)[0]:
            raise ValueError(f"checksum of {kind.decode('latin-1')} is wrong")
        if kind == b"IHDR":
            if size != 13:
                raise ValueError("the header has the wrong length")
            head = struct.unpack(">IIBBBBB", body)
        elif kind == b"IDAT":
            idat.append(body)
        elif kind == b"IEND":
            ended = True
            break
        elif not kind[0] & 32 and kind != b"PLTE":
            raise ValueError(f"unknown critical chunk {kind.decode('latin-1')}")
        at += 12 + size
    if head is None or not idat or not ended:
        raise ValueError("a chunk is missing")
    width, height, depth, color, packing, filtering, interlace = head
    if depth != 8 or color not in CHANNELS or packing or filtering or interlace:
        raise ValueError(f"unsupported: depth {depth}, colour type {color}, interlace {interlace}")
    bpp = CHANNELS[color]
    want = height * (width * bpp + 1)
    if not width or not height or want > most:
        raise ValueError(f"unsupported: {width} x {height} samples")
    inflate = zlib.decompressobj()
    try:  # never more than the header promises
        raw = inflate.decompress(b"".join(idat), want + 1)
    except zlib.error as e:
        raise ValueError(f"image data: {e}") from None
    if len(raw) != want or not inflate.eof:
        raise ValueError("image data have the wrong length")
    return _unfilter(np.frombuffer(raw, np.uint8), height, width * bpp, bpp)


_COS = np.cos(np.pi * np.arange(8)[:, None] * (2 * np.arange(32) + 1) / 64)


@lru_cache(maxsize=512)
def _low(n: int) -> np.ndarray:
    """The 8 lowest cosine frequencies of n samples after area-averaging to 32."""
    edge = np.arange(33) * n / 32
    pos = np.arange(n)
    cover = np.clip(np.minimum(edge[1:, None], pos + 1) - np.maximum(edge[:-1, None], pos), 0, None)
    return _COS @ (cover / cover.sum(axis=1, keepdims=True))


def cosine_hash(img: np.ndarray) -> bytes:
    """Eight bytes: which of the 64 lowest frequencies lie above their median."""
    c = np.round(_low(img.shape[0]) @ img.astype(np.float64) @ _low(img.shape[1]).T, 6).ravel()
    return np.packbits(c > np.median(c[1:])).tobytes()


_STORE = "doc_id long, n_bytes long, media binary"


def store_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 64, level: int = 6) -> DataFrame:
    """doc_id, n_bytes, media: each text's UTF-8, padded with zeros to whole rows, as an image."""
    need(docs, id_col, text_col)

    def run(batches):
        for b in sliced(batches, "text", 4 << 20):
            texts = text_values(b.column("text"))
            media = [png_encode(t + b"\0" * (-len(t) % width or (0 if t else width)), width, level) for t in texts]
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(map(len, texts), pa.int64()), pa.array(media, pa.binary())], ["doc_id", "n_bytes", "media"])

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(tidy(run), _STORE)


def read_media(df: DataFrame, media_col: str = "media") -> DataFrame:
    """The other columns of df with media, and payload, feature (eight bytes) and error read from it."""
    need(df, media_col)
    added = ["payload", "feature", "error"]
    keep = [c for c in df.columns if c not in added]
    schema = df.select(*keep).schema.add("payload", "binary").add("feature", "binary").add("error", "string")

    def run(batches):
        for b in sliced(batches, media_col, 2 << 20):
            payload, feature, error = [], [], []
            for x in b.column(media_col).to_pylist():
                p = f = e = None
                try:
                    if x is not None:
                        img = png_decode(x)
                        p, f = img.tobytes(), cosine_hash(img)
                except ValueError as err:
                    e = str(err)
                payload.append(p)
                feature.append(f)
                error.append(e)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(payload, pa.binary()), pa.array(feature, pa.binary()), pa.array(error, pa.string())], [*b.schema.names, *added])

    return df.select(*keep).mapInArrow(tidy(run), schema)


def op6_png_media(spark, sf_dir: str) -> DataFrame:
    read = read_media(store_texts(spark.read.parquet(f"{sf_dir}/documents.parquet")))
    return read.select(
        "doc_id", "n_bytes", F.octet_length("payload").cast("long").alias("payload_bytes"), F.sha2("payload", 256).alias("payload_sha256"), F.crc32(F.expr("substring(payload, -64, 64)")).alias("tail_crc32"),
        F.octet_length("media").cast("long").alias("media_bytes"), F.sha2("media", 256).alias("media_sha256"), F.lower(F.hex("feature")).alias("feature"),
    )
