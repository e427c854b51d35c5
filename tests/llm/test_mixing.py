from __future__ import annotations

import random
from collections import defaultdict
from fractions import Fraction

import numpy as np
from pyspark.sql import functions as F

from vtask.llm.mixing import fit_budget, mix_sources, source_targets


def targets(sizes, weights=(1, 2, 3), cap=3):
    """Reshare the excess until no source is above its cap."""
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    w = {s: Fraction(weights[i % len(weights)]) for i, s in enumerate(names)}
    done, free, total = {}, set(names), Fraction(sum(sizes.values()))
    while free:
        left = total - sum(done.values())
        share = {s: left * w[s] / sum(w[x] for x in free) for s in free}
        over = [s for s in free if share[s] > cap * sizes[s]]
        if not over:
            done |= share
            break
        for s in over:
            done[s] = Fraction(cap * sizes[s])
            free.remove(s)
    return {s: float(done[s]) for s in names}


def test_targets(spark):
    rng = random.Random(3)
    for k in (1, 2, 7, 40):
        sizes = {f"s{i}" if i else None: rng.choice([0, 1, 10, 1000, 50000]) for i in range(k)}
        df = spark.createDataFrame(list(sizes.items()), "source string, source_size long")
        got = {r.source: r.target for r in source_targets(df).collect()}
        want = targets(sizes)
        assert all(abs(got[s] - want[s]) <= 1e-9 * max(1, want[s]) for s in sizes), (got, want)


def test_budget_is_met_and_nearest():
    rng = np.random.default_rng(8)
    for _ in range(60):
        size = np.unique(rng.integers(0, 60, 8))
        n = rng.integers(1, 4, size.size)
        total = int((size * n).sum())
        target = float(rng.uniform(0, 3 * total))
        base, extra = fit_budget(size, n, target)
        assert ((extra >= 0) & (extra <= n)).all() and base <= 3
        taken = base * total + int((size * extra).sum())
        assert abs(taken - target) <= max(1, size[size > 0].min(initial=60))
    # huge counts, one very long document
    base, extra = fit_budget(np.array([5, 900, 10**9]), np.array([10**9, 10**6, 1]), 3.3e9)
    assert abs(base * (5 * 10**9 + 9 * 10**8 + 10**9) + int((np.array([5, 900, 10**9]) * extra).sum()) - 3.3e9) <= 3


def test_mix(spark, awkward):
    rng = random.Random(4)
    rows = [(i, " ".join("w" for _ in range(rng.choice([0, 1, 3, 7, 7, 7, 50]))), rng.choice(["a", "a", "a", "b", "é", None])) for i in range(700)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = mix_sources(df).collect()
    assert sorted(r.doc_id for r in got) == list(range(700))
    assert sorted(map(str, mix_sources(df.repartition(7)).collect())) == sorted(map(str, got))
    size, taken, target = defaultdict(int), defaultdict(int), {}
    for r in got:
        i, text, s = rows[r.doc_id]
        assert r.size == len(text.split()) and r.source == s and r.taken == r.times * r.size and 0 <= r.times <= 3
        size[s] += r.size
        taken[s] += r.taken
        target[s] = r.target
    want = targets(size)
    for s in size:
        assert abs(target[s] - want[s]) < 1e-6 * max(1, want[s]) and abs(taken[s] - target[s]) <= 1
    assert all(r.source_size == size[r.source] for r in got)
    odd = mix_sources(awkward.withColumn("size", F.lit("x")).withColumn("target", F.lit(1)).withColumn("id", F.lit(1))).collect()
    assert len(odd) == 12 and {r.size for r in odd if r.doc_id in (2, 3, 4)} == {0}
    assert mix_sources(awkward.limit(0)).count() == 0


def test_rows_that_repeat_an_id_are_split(spark):
    rows = [(None, "w w w w w w w w w w", "a")] * 500 + [(7, "w w w", "a")] * 40 + [(i, "w " * (i % 9), "b") for i in range(900)] + [(None, "w w", None)] * 333
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(5)
    got = mix_sources(df).collect()
    assert len(got) == len(rows)
    taken, target = defaultdict(int), {}
    for r in got:
        taken[r.source] += r.taken
        target[r.source] = r.target
        assert 0 <= r.times <= 3
    assert all(abs(taken[s] - target[s]) <= 1.5 for s in target), (taken, target)
    again = mix_sources(df.repartition(3)).collect()
    assert sorted(map(str, again)) == sorted(map(str, got))
