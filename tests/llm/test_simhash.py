from __future__ import annotations

import random

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from vtask.llm.common import connected_components
from vtask.llm.simhash import BKForest, near_components, near_duplicates, shard_plan


def fp(text, size=4):
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    sh = [b" ".join(words)] if len(words) <= size else [b" ".join(words[i : i + size]) for i in range(len(words) - size + 1)]
    h = [xxhash.xxh64_intdigest(s, 42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum((x >> b) & 1 for x in h) > len(h))


def components(items, radius):
    """items: (id, fp)."""
    root = list(range(len(items)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(items)):
        for j in range(i):
            if (items[i][1] ^ items[j][1]).bit_count() <= radius:
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    low = {}
    for i, (k, _) in enumerate(items):
        if k is not None:
            low[find(i)] = min(low.get(find(i), k), k)
    return [low.get(find(i)) for i in range(len(items))]


@pytest.mark.parametrize("n", [10, 10**7, 10**12])
def test_plan_covers(n):
    blocks, picks = shard_plan(n, 4)
    assert sum(w for _, w in blocks) == 64
    rng = random.Random(n)
    for _ in range(200):
        bad = {next(i for i, (a, w) in enumerate(blocks) if a <= b < a + w) for b in rng.sample(range(64), 4)}
        assert any(not bad & set(p) for p in picks)


def test_forest_finds_all_links():
    rng = np.random.default_rng(3)
    base = rng.integers(0, 2**63, 40, dtype=np.uint64)
    fps = np.unique(np.concatenate([base ^ (np.uint64(1) << rng.integers(0, 64, 40, dtype=np.uint64)) for _ in range(12)]))
    shard = np.sort(rng.integers(0, 3, fps.size))
    got = {(int(a), int(b)) for q, n in BKForest(fps, shard).links(4, most=500) for a, b in zip(q, n, strict=True)}
    d = np.bitwise_count(fps[:, None] ^ fps[None, :])
    assert got == {(i, j) for i in range(fps.size) for j in range(fps.size) if i != j and shard[i] == shard[j] and d[i, j] <= 4}


def test_components_of_fingerprints(spark):
    rng = random.Random(4)
    base = [rng.getrandbits(64) for _ in range(30)]
    items = []
    for i in rng.sample(range(10**6), 500):
        x = rng.choice(base)
        for b in rng.sample(range(64), rng.randrange(9)):
            x ^= 1 << b
        items.append((i, x))
    df = spark.createDataFrame([(i, x - (x >> 63 << 64)) for i, x in items], "id long, fp long").repartition(5)
    got = {r.id: r.component_id for r in near_components(df).collect()}
    want = dict(zip([i for i, _ in items], components(items, 4), strict=True))
    assert got == want
    assert {r.id: r.component_id for r in near_components(df, most=7).collect()} == want  # most shards are split


def test_chain(spark):
    rng = random.Random(9)
    ids = rng.sample(range(10**6), 200)
    df = spark.createDataFrame(list(zip(ids, ids[1:], strict=False)), "a long, b long")
    got = {r.node: r.comp for r in connected_components(df).collect()}
    assert got == {i: min(ids) for i in ids}
    assert connected_components(df.limit(0)).count() == 0


def test_texts(spark, awkward):
    rng = random.Random(6)
    words = ["Ab", "c", "dé", "EF", "gh", "ij", "kÉ"]
    texts = [" ".join(rng.choice(words) + str(rng.randrange(9)) for _ in range(rng.randrange(60))) for _ in range(40)]
    rows = [(i, rng.choice(texts) + rng.choice(["", " x", " Y z"])) for i in range(120)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = sorted(zip([i for i, _ in rows], [f"{fp(t):016x}" for _, t in rows], components([(i, fp(t)) for i, t in rows], 4), strict=True))
    assert sorted(map(tuple, near_duplicates(df).collect())) == want
    rows = [(r.doc_id, r.text) for r in awkward.collect()]
    want = sorted(zip([i for i, _ in rows], [f"{fp(t):016x}" for _, t in rows], components([(i, fp(t)) for i, t in rows], 4), strict=True), key=str)
    clash = awkward.withColumn("fp", F.lit(1)).withColumn("component_id", F.lit("x"))
    assert sorted(map(tuple, near_duplicates(clash).collect()), key=str) == want
    assert near_duplicates(awkward.limit(0)).count() == 0
