"""Shared pieces of the corpus operators: shared storage, sizes, word hashing and components.

All hashing is vectorised over the UTF-8 bytes of many documents at once; a
word is a maximal run of bytes outside ``[\\x20\\x09-\\x0D]``.
"""

from __future__ import annotations

import ctypes
import gc
import hashlib
import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Java pattern of a word; the same bytes that Python's bytes.split() splits on.
WORD = r"[^\x20\x09-\x0D]+"
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def need(df: DataFrame, *cols: str) -> None:
    """Raise a clear error if a column is missing."""
    lost = [c for c in cols if c not in df.columns]
    if lost:
        raise ValueError(f"missing columns {lost}; there are {df.columns}")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share; one of our own only in a local session that names none."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="vtask-checkpoint-"))
    return sc.getCheckpointDir()


def drop_folder(spark: SparkSession, path: str) -> None:
    """Delete a folder of shared storage, on whatever file system it lies."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def settle(df: DataFrame) -> DataFrame:
    """Write df to the cluster's shared checkpoint folder and cut its lineage.

    Survives lost executors, as every executor can read that folder. Shuffle
    files that only led to this table are released at once.
    """
    spark = df.sparkSession
    shared_dir(spark)
    before = spark.conf.get(_CLEANUP, "false")
    spark.conf.set(_CLEANUP, "true")
    try:
        return df.select("*").checkpoint(eager=True)
    finally:
        spark.conf.set(_CLEANUP, before)


def tidy(run):
    """run, a function for mapInArrow, with the worker's freed memory given back to the system, as workers live on between stages."""

    def tidied(batches):
        libc = ctypes.CDLL(None)
        if hasattr(libc, "mallopt"):
            libc.mallopt(-3, 1 << 20)  # M_MMAP_THRESHOLD: large arrays are mapped, and unmapped once freed
        try:
            yield from run(batches)
        finally:
            gc.collect()
            pa.default_memory_pool().release_unused()
            if hasattr(libc, "malloc_trim"):
                libc.malloc_trim(0)

    return tidied


def text_bytes(df: DataFrame, col: str) -> int:
    """Bytes of all texts, by one aggregation."""
    return df.agg(F.sum(F.octet_length(F.col(col)))).first()[0] or 0


def parts_for(spark: SparkSession, amount: float, per_part: float) -> int:
    """Partitions so that each holds about per_part; never fewer than the session's own number."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), int(amount // per_part) + 1)


# --------------------------------------------------------------------------- words of many documents

_SPACE = np.zeros(256, bool)
_SPACE[[0x20, 9, 10, 11, 12, 13]] = True
_LONG = 1024  # longer words are hashed one by one


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every bit of x over all 64."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Docs:
    """Texts laid end to end, each followed by one space, with the spans of their words."""

    def __init__(self, texts: list[bytes]):
        self.n = len(texts)
        self.buf = np.frombuffer(b" ".join([*texts, b""]), np.uint8) if texts else np.zeros(0, np.uint8)
        lens = np.fromiter((len(t) + 1 for t in texts), np.int64, self.n)
        self.doc_at = np.concatenate(([0], np.cumsum(lens)))
        gap = _SPACE[self.buf]
        edge = np.flatnonzero(gap[1:] != gap[:-1]) + 1
        first = 0 if self.buf.size and not gap[0] else 1
        if first == 0:
            edge = np.concatenate(([0], edge))
        self.start, self.end = edge[0::2], edge[1::2]  # the last byte is a space, so each word ends
        self.word_at = np.searchsorted(self.start, self.doc_at)  # first word of each document, and the number of words
        self.doc = np.repeat(np.arange(self.n), np.diff(self.word_at))

    def hashes(self) -> np.ndarray:
        """64-bit hash of each word: its bytes, eight at a time, through a mixing step; one to one on words of one length up to eight."""
        size = self.end - self.start
        out = mix64(size.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
        lanes = np.concatenate((self.buf, np.zeros(16 + -self.buf.size % 8, np.uint8))).view("<u8")
        big = np.flatnonzero(size > _LONG)
        at, left = np.flatnonzero(size <= _LONG), size[size <= _LONG]
        pos = self.start[at]
        while at.size:
            q, r = pos >> 3, ((pos & 7) << 3).astype(np.uint64)
            x = (lanes[q] >> r) | ((lanes[q + 1] << (np.uint64(56) - r)) << np.uint64(8))
            x &= np.uint64(2**64 - 1) >> (64 - 8 * np.minimum(left, 8)).astype(np.uint64)
            out[at] = mix64((out[at] ^ x) * np.uint64(0xD6E8FEB86659FD93))
            more = left > 8
            at, pos, left = at[more], pos[more] + 8, left[more] - 8
        for i in big.tolist():
            out[i] ^= np.uint64(xxhash.xxh3_64_intdigest(self.buf[self.start[i] : self.end[i]].tobytes()))
        return out

    def windows(self, h: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Hash of the k words from each word on, and whether they are of one document."""
        n = h.size
        if n < k:
            return np.zeros(0, np.uint64), np.zeros(0, bool)
        acc = np.full(n - k + 1, k, np.uint64)
        for j in range(k):
            acc = (acc ^ h[j : n - k + 1 + j]) * np.uint64(0xD6E8FEB86659FD93)
            acc ^= acc >> np.uint64(32)
        return mix64(acc), self.doc[: n - k + 1] == self.doc[k - 1 :]

    def digests(self, at: np.ndarray, k: int) -> np.ndarray:
        """64 bits of the BLAKE2b digest of the k words from each word of `at` on, as they stand."""
        raw, f = self.buf.tobytes(), hashlib.blake2b
        ends = self.end[at + k - 1].tolist()
        return np.frombuffer(b"".join([f(raw[a:b], digest_size=8).digest() for a, b in zip(self.start[at].tolist(), ends, strict=True)]), "<u8").astype(np.uint64)


def to_planes(a: np.ndarray) -> bytes:
    """Sorted integers as differences, bytes of equal weight together, so that a block codec can shrink them."""
    d = np.diff(a, prepend=a[:1] * 0).astype(a.dtype)
    return d.view(np.uint8).reshape(-1, a.itemsize).T.tobytes()


def from_planes(b: bytes, dtype) -> np.ndarray:
    size = np.dtype(dtype).itemsize
    d = np.ascontiguousarray(np.frombuffer(b, np.uint8).reshape(size, -1).T).view(dtype).ravel()
    return np.cumsum(d, dtype=dtype)


def plain_planes(a: np.ndarray) -> bytes:
    """Unsorted integers, bytes of equal weight together."""
    return a.view(np.uint8).reshape(-1, a.itemsize).T.tobytes()


def from_plain_planes(b: bytes, dtype) -> np.ndarray:
    size = np.dtype(dtype).itemsize
    return np.ascontiguousarray(np.frombuffer(b, np.uint8).reshape(size, -1).T).view(dtype).ravel()


def text_values(col: pa.Array) -> list[bytes]:
    """Values of a string column as bytes; null gives b''."""
    return [b"" if x is None else x for x in col.cast(pa.binary()).to_pylist()]


def sliced(batches: Iterator[pa.RecordBatch], col: str, most: int) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of at most about `most` bytes of col (one row at least)."""
    for b in batches:
        size = np.asarray(pc.fill_null(pc.binary_length(b.column(col)), 0)).astype(np.int64)
        at = np.cumsum(size)
        i = 0
        while i < b.num_rows:
            j = max(i + 1, int(np.searchsorted(at, (at[i - 1] if i else 0) + most, side="right")))
            yield b.slice(i, j - i)
            i = j


# --------------------------------------------------------------------------- components


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, comp): the smallest node that each node of edges(a, b) can reach.

    Alternating large-star and small-star rounds; each round is two grouped
    minima and joins, written to shared storage, until no edge changes. Stars
    pre-aggregate their minima before the shuffle, so a hub costs one row a
    task, and the joins are ones whose large partitions Spark can split.
    """

    def star(e: DataFrame, both: bool) -> DataFrame:
        if both:
            d = e.select("a", "b").unionAll(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        else:
            d = e.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        low = d.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        j = d.join(low, "a")
        if both:
            return j.filter(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b"))
        return j.select(F.col("b").alias("a"), F.col("m").alias("b")).unionAll(low.select("a", F.col("m").alias("b")))

    e = settle(edges.select(F.col("a").cast("long"), F.col("b").cast("long")).filter("a <> b").distinct())
    last = None
    for _ in range(max_rounds):
        e = settle(star(star(e, True).filter("a <> b").distinct(), False).filter("a <> b").distinct())
        mark = e.agg(F.count("*"), F.bit_xor(F.xxhash64("a", "b")), F.sum(F.xxhash64("b", "a") % 1000003)).first()
        if mark == last:
            break
        last = mark
    else:
        raise RuntimeError(f"components not settled after {max_rounds} rounds")
    return e.select(F.col("a").alias("node"), F.col("b").alias("comp")).unionAll(e.select(F.col("b").alias("node"), F.col("b").alias("comp")).distinct())
