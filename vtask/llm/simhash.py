"""SimHash near-duplicates by BK-trees.

A text, A-Z lower-cased, gives the XXH64 of each of its word shingles; a bit of
the 64-bit fingerprint is 1 if more than half of them set it. Fingerprints link
at `radius` differing bits or fewer, and linked fingerprints form components.

Search: only distinct fingerprints take part. By the pigeonhole principle two
fingerprints within the radius agree in at least `c` of `radius + c` blocks of
bits, so each fingerprint joins one shard for every choice of c blocks; c grows
with the number of distinct fingerprints, which keeps shards small. A shard is a
BK-tree: children are keyed by their Hamming distance to the parent, and a
search follows only edges within the radius of the query's own distance. A shard
with too many fingerprints is split once more by the same principle. Trees live
where their shard lands, in one vectorised forest a task, instead of being
broadcast: a broadcast would grow with the corpus. Each task joins what it has
found into stars before it hands on edges, so a cluster of n fingerprints gives
n - 1 edges, never all pairs.

Defined cases: null or blank text has the fingerprint zero and links like any
other; texts of fewer words than a shingle hash their whole word sequence; null
ids get a component but never name one unless no other id is in it; rows with
equal ids are rows of their own; an empty table gives an empty result.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vtask.llm.common import connected_components, need, parts_for, settle, text_values, tidy

# the sixteen values of four bits, each bit in a lane of sixteen
_LANES = np.array([sum(((v >> b) & 1) << (16 * b) for b in range(4)) for v in range(16)], np.uint64)
_LANE_MOST = 60000


def _shingle_hashes(text: bytes, size: int) -> list[int]:
    words = text.lower().split()  # of bytes: A-Z only, and the white space of WORD
    if not words:
        return []
    line = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1)).tolist()
    ends = ends.tolist()
    f = xxhash.xxh64_intdigest
    if len(words) <= size:
        return [f(line, 42)]
    return [f(line[a:b], 42) for a, b in zip(starts, ends[size - 1 :], strict=False)]


def fingerprints_of(texts: list[bytes], size: int) -> np.ndarray:
    """64-bit fingerprints of texts."""
    each = [_shingle_hashes(t, size) for t in texts]
    out = np.zeros(len(texts), np.uint64)
    n = np.array([len(x) for x in each], np.int64)
    full = np.flatnonzero(n)
    if not full.size:
        return out
    h = np.fromiter((x for e in each for x in e), np.uint64, int(n.sum()))
    at = np.concatenate(([0], np.cumsum(n[full])[:-1]))
    cuts = np.concatenate([np.arange(a, a + k, _LANE_MOST) for a, k in zip(at, n[full], strict=True)])  # lanes must not overflow
    doc = np.searchsorted(at, cuts, side="right") - 1
    first = np.searchsorted(doc, np.arange(full.size))
    fp = np.zeros(full.size, np.uint64)
    for nib in range(16):
        lanes = np.add.reduceat(_LANES[(h >> np.uint64(4 * nib)) & np.uint64(15)], cuts)
        for b in range(4):
            ones = np.add.reduceat(((lanes >> np.uint64(16 * b)) & np.uint64(0xFFFF)).astype(np.int64), first)
            fp |= (2 * ones > n[full]).astype(np.uint64) << np.uint64(4 * nib + b)
    out[full] = fp
    return out


def _fingerprint_rows(size: int, sub: int = 2 << 20):
    def run(batches):
        for b in batches:
            texts = text_values(b.column("text"))
            out, i = np.zeros(len(texts), np.uint64), 0
            while i < len(texts):
                j, got = i, 0
                while j < len(texts) and (j == i or got + len(texts[j]) <= sub):
                    got += len(texts[j])
                    j += 1
                out[i:j] = fingerprints_of(texts[i:j], size)
                i = j
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(out.view(np.int64))], ["id", "fp"])

    return run


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 4) -> DataFrame:
    """(id, fp) of each row; fp holds the 64 bits as a signed long."""
    need(docs, id_col, text_col)
    src = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return src.mapInArrow(tidy(_fingerprint_rows(shingle)), "id long, fp long")


class BKForest:
    """BK-trees over fps; tree t holds the elements i with shard[i] == t (shards are runs)."""

    def __init__(self, fps: np.ndarray, shard: np.ndarray):
        n = fps.size
        self.fps = fps
        first = np.flatnonzero(np.concatenate(([True], shard[1:] != shard[:-1]))) if n else np.zeros(0, np.int64)
        self.root = np.repeat(first, np.diff(np.append(first, n)))
        cur = self.root.copy()
        active = np.setdiff1d(np.arange(n), first, assume_unique=True)
        edges, nodes = [], []
        while active.size:
            d = np.bitwise_count(fps[active] ^ fps[cur[active]]).astype(np.int64)
            key = cur[active] * 65 + d
            order = np.argsort(key, kind="stable")
            active, key = active[order], key[order]
            head = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
            edges.append(key[head])
            nodes.append(active[head])
            size = np.diff(np.append(head, key.size))
            cur[active] = np.repeat(active[head], size)
            rest = np.ones(active.size, bool)
            rest[head] = False
            active = active[rest]
        key, node = (np.concatenate(edges), np.concatenate(nodes)) if edges else (np.zeros(0, np.int64),) * 2
        order = np.argsort(key, kind="stable")
        self.key, self.node = key[order], node[order]

    def links(self, radius: int, most: int = 1 << 20):
        """Pairs (query, element) within the radius, in blocks; every element queries its own tree."""
        stack = [(q, self.root[q]) for q in np.array_split(np.arange(self.fps.size), max(1, self.fps.size >> 14))]
        while stack:
            q, node = stack.pop()
            if q.size > most:
                h = q.size // 2
                stack += [(q[:h], node[:h]), (q[h:], node[h:])]
                continue
            d = np.bitwise_count(self.fps[q] ^ self.fps[node]).astype(np.int64)
            hit = (d <= radius) & (q != node)
            if hit.any():
                yield q[hit], node[hit]
            a = np.searchsorted(self.key, node * 65 + np.maximum(d - radius, 0))
            b = np.searchsorted(self.key, node * 65 + np.minimum(d + radius, 64), side="right")
            n = b - a
            if n.any():
                skip = np.concatenate(([0], np.cumsum(n)[:-1]))
                stack.append((np.repeat(q, n), self.node[np.repeat(a - skip, n) + np.arange(int(n.sum()))]))


def _unite(root: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Join the sets of a[i] and b[i]; root[i] is the smallest member of i's set."""
    while True:
        x, y = root[a], root[b]
        apart = x != y
        if not apart.any():
            return root
        a, b = a[apart], b[apart]
        x, y = x[apart], y[apart]
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while True:
            nxt = root[root]
            if (nxt == root).all():
                break
            root = nxt


def _shard_stars(radius: int):
    """Edges (fingerprint, representative) of the sets that a task's shards join."""

    def run(batches):
        got = [(np.asarray(b.column("shard")), np.asarray(b.column("fp"))) for b in batches if b.num_rows]
        if not got:
            return
        shard, fp = np.concatenate([x for x, _ in got]), np.concatenate([x for _, x in got])
        order = np.lexsort((fp, shard))
        shard, fp = shard[order], fp[order]
        same, which = np.unique(fp, return_inverse=True)
        root = np.arange(same.size)
        forest = BKForest(fp.view(np.uint64), shard)
        for q, node in forest.links(radius):
            root = _unite(root, which[q], which[node])
        sel = root != np.arange(same.size)
        yield pa.RecordBatch.from_arrays([pa.array(same[sel]), pa.array(same[root[sel]])], ["a", "b"])

    return run


def shard_plan(n: int, radius: int, load: int = 64) -> tuple[list[tuple[int, int]], list[tuple[int, ...]]]:
    """Blocks (first bit, bits) and the choices of blocks that key the shards, for n distinct fingerprints."""
    for extra in range(1, 9):
        m = radius + extra
        at = [round(i * 64 / m) for i in range(m + 1)]
        blocks = [(at[i], at[i + 1] - at[i]) for i in range(m)]
        picks = list(combinations(range(m), extra))
        if n <= load << min(sum(blocks[i][1] for i in p) for p in picks) or extra == 8:
            return blocks, picks
    raise AssertionError


def _block(a: int, w: int) -> F.Column:
    return F.shiftrightunsigned("fp", a).bitwiseAND(F.lit((1 << w) - 1))


def _split_hot(keyed: DataFrame, blocks: list[tuple[int, int]], picks: list[tuple[int, ...]], radius: int, most: int) -> DataFrame:
    """keyed(fp, shard, pick) with each shard of more than `most` fingerprints in smaller ones.

    Fingerprints of a shard that link differ in `radius` bits or fewer outside
    its pick, so of radius + 1 blocks of the bits outside one agrees at least:
    its number and bits key the smaller shards.
    """
    hot = settle(keyed.groupBy("shard").agg(F.count("*").alias("n")).filter(F.col("n") > most).select("shard"))
    if hot.isEmpty():
        return keyed

    def finer(p):
        rest = [x for i, (a, w) in enumerate(blocks) if i not in p for x in range(a, a + w)]
        cut = [rest[i * len(rest) // (radius + 1) : (i + 1) * len(rest) // (radius + 1)] for i in range(radius + 1)]
        masks = [sum(1 << x for x in c) for c in cut]
        return F.array(*(F.xxhash64("shard", F.lit(i), F.col("fp").bitwiseAND(F.lit(m - (1 << 64) if m >> 63 else m))) for i, m in enumerate(masks)))

    by_pick = F.array(*(finer(p) for p in picks))
    split = keyed.join(hot, "shard", "left_semi").select("fp", F.explode(F.element_at(by_pick, F.col("pick") + 1)).alias("shard"), "pick")
    return keyed.join(hot, "shard", "left_anti").select("fp", "shard", "pick").unionAll(split)


def near_components(fps: DataFrame, radius: int = 4, most: int = 20_000) -> DataFrame:
    """(id, fp, component_id) for each row of fps(id, fp); fps should be settled, as it is read more than once. `most`: fingerprints of one tree."""
    spark = fps.sparkSession
    one = settle(fps.groupBy("fp").agg(F.min("id").alias("low")))
    n = one.count()
    blocks, picks = shard_plan(n, radius)
    # with a pick's number as salt, its blocks' bits are the shard
    keys = [F.xxhash64(F.lit(k), *(_block(*blocks[i]) for i in p)) for k, p in enumerate(picks)]
    parts = parts_for(spark, n * len(picks), 400_000)
    keyed = one.select("fp", F.posexplode(F.array(*keys)).alias("pick", "shard"))
    stars = _split_hot(keyed, blocks, picks, radius, most).repartition(parts, "shard").select("fp", "shard").mapInArrow(tidy(_shard_stars(radius)), "a long, b long")
    comp = connected_components(stars)
    named = one.join(comp, F.col("fp") == F.col("node"), "left").select("fp", "low", F.coalesce("comp", "fp").alias("comp"))
    # written first, so that a component of very many fingerprints joins in a join whose large partitions Spark can split
    low = settle(named.groupBy("comp").agg(F.min("low").alias("component_id")))
    return fps.join(named.join(low, "comp").select("fp", "component_id"), "fp").select("id", "fp", "component_id")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 4, radius: int = 4) -> DataFrame:
    """One row per row of docs: doc_id, fingerprint (16 hex digits), component_id (the smallest id reachable)."""
    rows = near_components(settle(fingerprints(docs, id_col, text_col, shingle)), radius)
    return rows.select(F.col("id").alias("doc_id"), F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def op2_simhash_near_dedup(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))
