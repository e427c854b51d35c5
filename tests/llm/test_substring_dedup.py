from __future__ import annotations

import random

from pyspark.sql import functions as F

from vtask.llm.substring_dedup import remove_repeated_passages


def brute(rows, w):
    words = [(i if i is not None else 2**63 - 1, (t or "").encode().split()) for i, t in rows]
    low = {}
    for i, x in words:
        for j in range(len(x) - w + 1):
            k = tuple(x[j : j + w])
            low[k] = min(low.get(k, i), i)
    out = []
    for (i, x), (raw, _) in zip(words, rows, strict=True):
        gone = [False] * len(x)
        for j in range(len(x) - w + 1):
            if low[tuple(x[j : j + w])] < i:
                gone[j : j + w] = [True] * w
        spans, j = [], 0
        while j < len(x):
            if gone[j]:
                k = j
                while k < len(x) and gone[k]:
                    k += 1
                spans.append((j, k))
                j = k
            else:
                j += 1
        out.append((raw, len(x), sum(gone), b" ".join(y for y, g in zip(x, gone, strict=True) if not g).decode(), tuple(spans)))
    return sorted(out, key=str)


def got(df):
    return sorted(((r.doc_id, r.n_words, r.n_removed, r.kept_text, tuple((s.start, s.end) for s in r.removed_spans)) for r in df.collect()), key=str)


def test_random_repeats(spark):
    rng = random.Random(5)
    passages = [[rng.choice("abcdefghij") + str(rng.randrange(40)) for _ in range(rng.randrange(10, 40))] for _ in range(12)]
    rows = []
    for i in rng.sample(range(1000), 150):
        words = []
        for _ in range(rng.randrange(0, 6)):
            words += rng.choice(passages)[rng.randrange(8) :] if rng.random() < 0.5 else [str(rng.randrange(10**6)) for _ in range(rng.randrange(20))]
        rows.append((i, rng.choice([" ", "\n", "  "]).join(words)))
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    assert got(remove_repeated_passages(df, chunk_bytes=1500)) == brute(rows, 13)
    assert got(remove_repeated_passages(df, window=6, chunk_bytes=700, part_bytes=3000)) == brute(rows, 6)


def test_awkward(spark, awkward):
    rows = [(r.doc_id, r.text) for r in awkward.collect()]
    clash = awkward.withColumn("kept_text", F.lit("x")).withColumn("bid", F.lit(1)).withColumn("n_words", F.lit(None))
    assert got(remove_repeated_passages(clash, chunk_bytes=40)) == brute(rows, 13)
    assert remove_repeated_passages(awkward.limit(0)).count() == 0


def _thue_morse(n):
    t = "a"
    while len(t) < n:
        t += t.translate(str.maketrans("ab", "ba"))
    return t


def test_words_of_equal_polynomial_hash_are_not_equal(spark):
    t = _thue_morse(1024)
    head = " ".join(f"w{i}" for i in range(12))
    rows = [(1, f"{head} {t}"), (2, f"{head} {t.translate(str.maketrans('ab', 'ba'))}"), (3, f"x {head} {t} y")]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    out = got(remove_repeated_passages(df, chunk_bytes=200))
    assert out == brute(rows, 13) and [r[2] for r in out] == [0, 0, 13]


def test_colliding_hashes_are_told_apart_by_the_words(spark, monkeypatch):
    import vtask.llm.substring_dedup as m

    rng = random.Random(9)
    few = [" ".join(rng.choice("ab") + rng.choice("cd") for _ in range(40)) for _ in range(30)]
    rows = list(enumerate(few)) + [(100 + i, few[i] + " z") for i in range(5)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(1)
    docs = df.select("doc_id", "text").toArrow().to_batches()

    def weak(self):  # every word of a length has one hash
        return (self.end - self.start).astype("uint64")

    monkeypatch.setattr(m.Docs, "hashes", weak)
    chunks = [b.column("data").to_pylist()[0] for b in m._packer(600)(iter(docs))]
    parts, k, w = 3, 7, 13

    def stage(kinds, run, by):
        got_ = {}
        for r in kinds:
            got_.setdefault(r[by], []).append(r)
        out = []
        for rows_ in got_.values():
            for b in run(iter([m._batch(rows_)])):
                out += list(zip(*(c.to_pylist() for c in b.columns), strict=True)) if b.num_rows else []
        return out

    packed = [(i, 0, 0, x) for i, x in enumerate(chunks)]
    hits = stage(stage(packed, m._emit_blocks(k, parts), 0), m._probe, 2)
    later = stage(stage(packed + hits, m._emit_windows(k, w, parts), 0), m._earlier, 2)
    res = stage(packed + later, m._strip(w), 0)
    flat = sorted(((i, n, g, t, tuple((s["start"], s["end"]) for s in sp)) for i, n, g, t, sp in res), key=str)
    assert len(chunks) > 2 and flat == brute(rows, w)
