from __future__ import annotations

import hashlib
import random
import re

from pyspark.sql import functions as F

from vtask.llm.exact_dedup import RadixTrie, exact_duplicates


def brute(rows):
    norm = [(i, re.sub(rb"[\x20\x09-\x0d]+", b" ", (t or "").encode())) for i, t in rows]
    low, n = {}, {}
    for i, t in norm:
        n[t] = n.get(t, 0) + 1
        if i is not None:
            low[t] = min(low.get(t, i), i)
    return sorted(((i, low.get(t), n[t], i == low.get(t), hashlib.sha256(t).hexdigest()) for i, t in norm), key=str)


def got(df):
    return sorted(((r.doc_id, r.keep_id, r.group_size, r.kept, r.text_sha256) for r in df.collect()), key=str)


def test_trie():
    rng = random.Random(1)
    t, want = RadixTrie(), {}
    for i in range(3000):
        s = bytes(rng.choice(b"ab") for _ in range(rng.randrange(12)))
        t.insert(s, i, 1)
        a = want.setdefault(s, [i, 0])
        a[1] += 1
    assert {s: [a, b] for s, a, b in t.walk(t.root, b"")} == want
    path, cut = t.cut_heaviest()
    rest = list(t.walk(t.root, b""))
    assert cut and all(s.startswith(path) for s, *_ in cut) and not any(s.startswith(path) for s, *_ in rest)
    assert {s: [a, b] for s, a, b in cut + rest} == want


def test_copies_and_spill(spark):
    rng = random.Random(2)
    base = ["same prefix " * 5 + " ".join(rng.choice("abcd") for _ in range(rng.randrange(30))) for _ in range(60)]
    rows = [(i, rng.choice(base).replace(" ", rng.choice([" ", "\n", " \t "]))) for i in rng.sample(range(5000), 600)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(6)
    assert got(exact_duplicates(df)) == brute(rows)
    assert got(exact_duplicates(df, budget=1500)) == brute(rows)


def test_awkward(awkward):
    rows = [(r.doc_id, r.text) for r in awkward.collect()]
    clash = awkward.withColumn("part", F.lit(1)).withColumn("keep_id", F.lit("z")).withColumn("id", F.lit(None))
    assert got(exact_duplicates(clash)) == brute(rows)
    assert exact_duplicates(awkward.limit(0)).count() == 0
