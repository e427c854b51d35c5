"""Removal of passages that already occur in a document with a smaller id.

Fixed-block anchors: every document is cut into non-overlapping reference
blocks of ``(window + 1) // 2`` words, and every rolling window of that many
words probes the index of blocks. Two documents that share ``window`` words
share, wherever the passage lies in either, at least one reference block, so no
repeat is missed. Around each hit the windows of ``window`` words that hold it
are compared, and neighbouring ones that also start in an earlier document grow
into maximal exact repeats.

Equality: hashes of words only select. Words of two windows count as equal if
their rolling hashes and the BLAKE2b digests of their bytes agree, 128 bits
together, so words whose hashes collide stay apart.

Movement of data: documents are packed once into compressed chunks in shared
storage, words set one space apart. Between chunks only sorted hashes and
digests travel, each chunk's own repeats merged before, so a passage found in a
third of all documents costs one entry a chunk. The index is dealt by hash to as
many parts as the corpus needs; a chunk sends rows only to parts that it has
entries for. Chunks go to tasks in turn, so each task holds as many. Nothing is
broadcast and nothing comes to the driver but a sum and a maximum.

A block's hash is cut to 31 bits besides its part's number; a false hit only
adds windows to compare.

Defined cases: null or blank text has no words; a null id counts as larger than
all others; rows with equal ids never remove from one another; an empty table
gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections import defaultdict

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vtask.llm.common import Docs, from_plain_planes, from_planes, mix64, need, parts_for, plain_planes, settle, text_bytes, text_values, tidy, to_planes

_NULL_ID = np.int64(2**63 - 1)
_CHUNK = 8 << 20  # bytes of text in a chunk
_SUB = 2 << 20  # bytes hashed at once
_ROW = "bid long, kind int, part int, data binary"


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    bid, kind, part, data = zip(*rows, strict=True) if rows else ((), (), (), ())
    return pa.RecordBatch.from_arrays([pa.array(bid, pa.int64()), pa.array(kind, pa.int32()), pa.array(part, pa.int32()), pa.array(data, pa.binary())], ["bid", "kind", "part", "data"])


def _packer(chunk: int):
    def pack(batches):
        ids, nulls, texts, size = [], [], [], 0

        def flush():
            k = np.array(ids, np.int64)
            order = np.argsort(k, kind="stable")
            t = [texts[i] for i in order]
            blob = np.int64(len(t)).tobytes() + k[order].tobytes() + np.array(nulls, np.uint8)[order].tobytes() + np.array([len(x) for x in t], np.int64).tobytes() + b"".join(t)
            return pa.RecordBatch.from_arrays([pa.array([zstandard.compress(blob, 1)], pa.binary())], ["data"])

        for b in batches:
            for i, t in zip(b.column(0).to_pylist(), text_values(b.column(1)), strict=True):
                ids.append(_NULL_ID if i is None else i)
                nulls.append(i is None)
                texts.append(b" ".join(t.split()))
                size += len(t)
                if size >= chunk:
                    yield flush()
                    ids, nulls, texts, size = [], [], [], 0
        if ids:
            yield flush()

    return pack


class _Chunk:
    """A packed chunk: ids in rising order, texts, word hashes."""

    def __init__(self, data: bytes):
        raw = zstandard.decompress(data)
        n = int(np.frombuffer(raw, np.int64, 1)[0])
        self.ids = np.frombuffer(raw, np.int64, n, 8)
        self.null = np.frombuffer(raw, np.uint8, n, 8 + 8 * n).astype(bool)
        size = np.frombuffer(raw, np.int64, n, 8 + 9 * n)
        at = np.concatenate(([0], np.cumsum(size))) + 8 + 17 * n
        self.texts = [raw[at[i] : at[i + 1]] for i in range(n)]
        self.size = size

    def subs(self):
        """(first document, Docs) of parts that fit the cache."""
        i, at = 0, np.cumsum(self.size)
        while i < len(self.texts):
            j = max(i + 1, int(np.searchsorted(at, (at[i - 1] if i else 0) + _SUB, side="right")))
            yield i, Docs(self.texts[i:j])
            i = j

    def blocks(self, k: int, parts: int):
        """Per sub: Docs, first document, hashes of words, key and validity of each rolling block, and which are reference blocks."""
        for i, d in self.subs():
            h = d.hashes()
            r, ok = d.windows(h, k)
            key = (((r >> np.uint64(32)) * np.uint64(parts)) >> np.uint64(32)) << np.uint64(31) | (r & np.uint64(0x7FFFFFFF))
            place = np.arange(r.size) - d.word_at[:-1][d.doc[: r.size]]
            yield i, d, h, key, ok, place % k == 0


def _runs(part: np.ndarray):
    """(part, first, behind the last) of each run of equal parts."""
    if not part.size:
        return iter(())
    first = np.flatnonzero(np.concatenate(([True], part[1:] != part[:-1])))
    return zip(part[first].tolist(), first.tolist(), [*first[1:].tolist(), part.size], strict=True)


def _emit_blocks(k: int, parts: int):
    def emit(batches):
        for b in batches:
            for bid, data in zip(b.column("bid").to_pylist(), b.column("data").to_pylist(), strict=True):
                c = _Chunk(data)
                got = [(key[ok] << np.uint64(1)) | (~ref[ok]).astype(np.uint64) for _, _, _, key, ok, ref in c.blocks(k, parts)]
                v = np.sort(np.concatenate(got)) if got else np.zeros(0, np.uint64)
                v = v[np.concatenate(([True], v[1:] >> np.uint64(1) != v[:-1] >> np.uint64(1)))] if v.size else v  # a reference block comes first
                low = (v & np.uint64(0xFFFFFFFF)).astype(np.uint32)
                yield _batch([(bid, 1, p, to_planes(low[a:z])) for p, a, z in _runs(v >> np.uint64(32))])

    return emit


def _gather(batches):
    """Rows by part, once all rows of the partition are here."""
    got = defaultdict(list)
    for b in batches:
        for bid, part, data in zip(b.column("bid").to_pylist(), b.column("part").to_pylist(), b.column("data").to_pylist(), strict=True):
            got[part].append((bid, data))
    return got


def _probe(batches):
    """Which probes of each chunk hit a reference block, where another chunk has the block too."""
    got = _gather(batches)
    for part in sorted(got):
        rows = got.pop(part)
        arrays = [from_planes(x, np.uint32) for _, x in rows]
        who = np.repeat(np.arange(len(rows), dtype=np.uint64), [a.size for a in arrays])
        v = np.concatenate(arrays).astype(np.uint64)
        h = v >> np.uint64(1)
        v = np.sort(h << np.uint64(32) | who << np.uint64(1) | (v & np.uint64(1)))
        h = v >> np.uint64(32)
        first = np.flatnonzero(np.concatenate(([True], h[1:] != h[:-1])))
        count = np.diff(np.append(first, h.size))
        indexed = np.add.reduceat((~v & np.uint64(1)).astype(np.int64), first) > 0
        hit = np.repeat((count > 1) & indexed, count)
        h, who = h[hit].astype(np.uint32), ((v[hit] & np.uint64(0xFFFFFFFF)) >> np.uint64(1)).astype(np.int64)
        order = np.argsort(who, kind="stable")
        h, who = h[order], who[order]
        at = np.searchsorted(who, np.arange(len(rows) + 1))
        yield _batch([(rows[i][0], 2, part, to_planes(h[at[i] : at[i + 1]])) for i in range(len(rows)) if at[i] < at[i + 1]])


def _by_chunk(batches):
    chunk, more = {}, defaultdict(list)
    for b in batches:
        for bid, kind, part, data in zip(*(b.column(x).to_pylist() for x in ("bid", "kind", "part", "data")), strict=True):
            if kind == 0:
                chunk[bid] = data
            else:
                more[bid].append((part, data))
    return chunk, more


def _emit_windows(k: int, w: int, parts: int):
    def emit(batches):
        chunk, more = _by_chunk(batches)
        for bid in sorted(chunk):
            c = _Chunk(chunk.pop(bid))
            subs = list(c.blocks(k, parts))
            every = np.sort(np.concatenate([key[ok] for _, _, _, key, ok, _ in subs])) if subs else np.zeros(0, np.uint64)
            own = every[1:][every[1:] == every[:-1]]
            hits = [np.uint64(p) << np.uint64(31) | from_planes(x, np.uint32).astype(np.uint64) for p, x in more.pop(bid, [])]
            hits = np.unique(np.concatenate([*hits, own]))
            vs, ds, ids = [], [], []
            for i, d, h, key, ok, _ in subs:
                if not hits.size or h.size < w:
                    continue
                at = np.minimum(np.searchsorted(hits, key), hits.size - 1)
                near = np.concatenate(([0], np.cumsum((hits[at] == key) & ok)))
                span = w - k + 1
                win, good = d.windows(h, w)
                at = np.flatnonzero(good & (near[span : span + win.size] > near[: win.size]))
                vs.append(win[at])
                ds.append(d.digests(at, w))
                ids.append(c.ids[i + d.doc[at]])
            if not vs:
                continue
            v, d, low = np.concatenate(vs), np.concatenate(ds), np.concatenate(ids)
            part = ((mix64(v ^ np.uint64(0x5851F42D4C957F2D)) >> np.uint64(32)) * np.uint64(parts)) >> np.uint64(32)
            order = np.lexsort((d, v, part))  # stable, and ids rise, so the first of equal windows has the smallest
            v, d, low, part = v[order], d[order], low[order], part[order]
            one = _new(v, d)
            v, d, low, part = v[one], d[one], low[one], part[one]
            yield _batch([(bid, 3, p, to_planes(v[a:z]) + plain_planes(d[a:z]) + plain_planes(low[a:z])) for p, a, z in _runs(part)])

    return emit


def _new(v: np.ndarray, d: np.ndarray) -> np.ndarray:
    """Which windows differ from the one before, in hash or in digest."""
    out = np.ones(v.size, bool)
    out[1:] = (v[1:] != v[:-1]) | (d[1:] != d[:-1])
    return out


def _earlier(batches):
    """Which windows of each chunk start in a document of another chunk with a smaller id than all of its own."""
    got = _gather(batches)
    for part in sorted(got):
        rows = got.pop(part)
        thirds = [(x[: len(x) // 3], x[len(x) // 3 : len(x) // 3 * 2], x[len(x) // 3 * 2 :]) for _, x in rows]
        arrays = [from_planes(a, np.uint64) for a, _, _ in thirds]
        v, d, low = np.concatenate(arrays), np.concatenate([from_plain_planes(b, np.uint64) for _, b, _ in thirds]), np.concatenate([from_plain_planes(b, np.int64) for _, _, b in thirds])
        who = np.repeat(np.arange(len(rows)), [a.size for a in arrays])
        order = np.lexsort((d, v))
        v, d, low, who = v[order], d[order], low[order], who[order]
        first = np.flatnonzero(_new(v, d))
        least = np.repeat(np.minimum.reduceat(low, first), np.diff(np.append(first, v.size)))
        sel = least < low
        v, d, who = v[sel], d[sel], who[sel]
        order = np.argsort(who, kind="stable")
        v, d = v[order], d[order]
        yield _batch([(rows[i][0], 4, part, to_planes(v[a:z]) + plain_planes(d[a:z])) for i, a, z in _runs(who[order])])


def _strip(w: int):
    def strip(batches):
        chunk, more = _by_chunk(batches)
        for bid in sorted(chunk):
            c = _Chunk(chunk.pop(bid))
            told = [(x[: len(x) // 2], x[len(x) // 2 :]) for _, x in more.pop(bid, [])]
            rv = np.concatenate([np.zeros(0, np.uint64), *(from_planes(a, np.uint64) for a, _ in told)])
            rd = np.concatenate([np.zeros(0, np.uint64), *(from_plain_planes(b, np.uint64) for _, b in told)])
            subs = []
            for i, d in c.subs():
                win, good = d.windows(d.hashes(), w)
                at = np.flatnonzero(good)
                subs.append((i, d, at, win[at]))
            v = np.sort(np.concatenate([np.zeros(0, np.uint64), *(x[3] for x in subs)]))
            known = np.unique(np.concatenate((rv, v[1:][v[1:] == v[:-1]])))
            # windows whose hash occurs more than once, here or by an answer: their words decide
            some = [np.flatnonzero(known[np.minimum(np.searchsorted(known, x[3]), known.size - 1)] == x[3]) if known.size else np.zeros(0, np.int64) for x in subs]
            v = np.concatenate([rv, *(x[3][s] for x, s in zip(subs, some, strict=True))])
            dig = np.concatenate([rd, *(x[1].digests(x[2][s], w) for x, s in zip(subs, some, strict=True))])
            ids = np.concatenate([np.zeros(rv.size, np.int64), *(c.ids[x[0] + x[1].doc[x[2][s]]] for x, s in zip(subs, some, strict=True))])
            drop = np.zeros(v.size, bool)
            if v.size:
                order = np.lexsort((dig, v))
                group = np.cumsum(_new(v[order], dig[order])) - 1
                first = np.flatnonzero(_new(v[order], dig[order]))
                far = np.logical_or.reduceat(order < rv.size, first)
                low = np.minimum.reduceat(np.where(order < rv.size, _NULL_ID, ids[order]), first)
                drop[order] = far[group] | (low[group] < ids[order])
            done = rv.size
            for (i, d, at, _), s in zip(subs, some, strict=True):
                start = at[s[drop[done : done + s.size]]]
                done += s.size
                yield _stripped(c, i, d, start, w)

    return strip


def _stripped(c: _Chunk, i: int, d: Docs, start: np.ndarray, w: int) -> pa.RecordBatch:
    n = d.start.size
    edge = np.zeros(n + 1, np.int64)
    np.add.at(edge, start, 1)
    np.add.at(edge, start + w, -1)
    gone = np.cumsum(edge)[:n] > 0
    total = np.concatenate(([0], np.cumsum(gone)))
    n_words = np.diff(d.word_at)
    n_gone = total[d.word_at[1:]] - total[d.word_at[:-1]]
    # bytes of the words that stay, each with the byte behind it as its space
    flip = np.zeros(d.buf.size + 2, np.int8)
    flip[d.start[~gone]] += 1
    np.subtract.at(flip, d.end[~gone] + 1, 1)
    keep = np.cumsum(flip, dtype=np.int8)[: d.buf.size] > 0
    buf = d.buf.copy()
    buf[d.end] = 0x20
    out = buf[keep].tobytes()
    cost = np.concatenate(([0], np.cumsum(np.where(gone, 0, d.end - d.start + 1))))
    a, b = cost[d.word_at[:-1]], cost[d.word_at[1:]]
    texts = [out[x : max(x, y - 1)] for x, y in zip(a.tolist(), b.tolist(), strict=True)]
    # maximal runs of removed words, by document
    change = np.flatnonzero(np.diff(np.concatenate(([0], gone.astype(np.int8), [0]))))
    run_a, run_b = change[0::2], change[1::2]
    cut = np.setdiff1d(d.word_at[1:-1], np.concatenate((run_a, run_b)))  # runs that cross into the next document
    inside = cut[gone[np.minimum(cut, n - 1)] & (cut < n)] if n else cut
    run_a, run_b = np.sort(np.concatenate((run_a, inside))), np.sort(np.concatenate((run_b, inside)))
    base = d.word_at[:-1]
    of = d.doc[run_a] if run_a.size else run_a
    at = np.concatenate(([0], np.cumsum(np.bincount(of, minlength=d.n)))).astype(np.int32) if d.n else np.zeros(1, np.int32)
    span = pa.StructArray.from_arrays([pa.array(run_a - base[of], pa.int64()), pa.array(run_b - base[of], pa.int64())], ["start", "end"])
    null = c.null[i : i + d.n]
    return pa.RecordBatch.from_arrays(
        [
            pa.array(np.asarray(c.ids[i : i + d.n]), pa.int64(), mask=null), pa.array(n_words, pa.int64()), pa.array(n_gone, pa.int64()),
            pa.array(texts, pa.binary()).cast(pa.string()), pa.ListArray.from_arrays(pa.array(at, pa.int32()), span),
        ],
        ["doc_id", "n_words", "n_removed", "kept_text", "removed_spans"],
    )


def remove_repeated_passages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = 13, chunk_bytes: int = _CHUNK, part_bytes: int = 16 << 20) -> DataFrame:
    """One row per row of docs: doc_id, n_words, n_removed, kept_text, removed_spans.

    removed_spans holds word positions, end exclusive: maximal runs of words
    covered by windows of `window` words that also start in a document with a
    smaller id. kept_text joins the other words by one space.
    """
    need(docs, id_col, text_col)
    if window < 2:
        raise ValueError("window must be at least 2 words")
    spark = docs.sparkSession
    k = (window + 1) // 2
    src = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    parts = parts_for(spark, text_bytes(src, "text"), part_bytes)
    chunks = settle(src.mapInArrow(tidy(_packer(chunk_bytes)), "data binary").select(F.monotonically_increasing_id().alias("bid"), F.lit(0).alias("kind"), F.lit(0).alias("part"), "data"))
    hits = settle(chunks.mapInArrow(tidy(_emit_blocks(k, parts)), _ROW).repartitionById(parts, "part").mapInArrow(tidy(_probe), _ROW))
    # a chunk's id holds its task and its place there; in turn, so that tasks get equal shares
    most = (chunks.agg(F.max(F.col("bid").bitwiseAND((1 << 33) - 1))).first()[0] or 0) + 1
    turn = F.pmod(F.shiftrightunsigned("bid", 33) * F.lit(most) + F.col("bid").bitwiseAND((1 << 33) - 1), F.lit(parts)).cast("int")

    def beside(answers: DataFrame) -> DataFrame:
        return chunks.unionAll(answers).repartitionById(parts, turn)

    later = settle(beside(hits).mapInArrow(tidy(_emit_windows(k, window, parts)), _ROW).repartitionById(parts, "part").mapInArrow(tidy(_earlier), _ROW))
    return beside(later).mapInArrow(tidy(_strip(window)), "doc_id long, n_words long, n_removed long, kept_text string, removed_spans array<struct<start:long,end:long>>")


def op1_substring_dedup(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return remove_repeated_passages(docs).select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept_text").cast("binary"), 256).alias("kept_sha256"))


OP1_SQL = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
win AS (SELECT doc_id, i, array_to_string(ws[i:i + 12], ' ') AS k FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 11)) AS i FROM d WHERE len(ws) >= 13)),
low AS (SELECT k, min(doc_id) AS m FROM win GROUP BY k),
gone AS (SELECT DISTINCT doc_id, i + j AS p FROM (SELECT doc_id, i, unnest(range(0, 13)) AS j FROM win JOIN low USING (k) WHERE m < doc_id)),
word AS (SELECT doc_id, p, ws[p] AS w FROM (SELECT doc_id, ws, unnest(range(1, len(ws) + 1)) AS p FROM d)),
kept AS (SELECT word.doc_id, string_agg(w, ' ' ORDER BY word.p) FILTER (WHERE gone.p IS NULL) AS t, count(gone.p) AS n FROM word LEFT JOIN gone USING (doc_id, p) GROUP BY word.doc_id)
SELECT d.doc_id, len(ws)::BIGINT AS n_words, coalesce(n, 0)::BIGINT AS n_removed, sha256(coalesce(t, '')) AS kept_sha256 FROM d LEFT JOIN kept USING (doc_id)
"""
