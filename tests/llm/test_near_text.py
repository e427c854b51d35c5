from __future__ import annotations

import random
import re

import corpus_pipeline


def shingles(text, size=5):
    w = re.findall("[^\x20\t-\r]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return {tuple(w[i : i + size]) for i in range(max(1, len(w) - size + 1))}


def survivors(rows):
    """rows: (id, text), ids distinct; the smallest id of each component stays, a null id counts as the largest."""
    sets, root = [shingles(t) for _, t in rows], list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j]):
                root[find(i)] = find(j)
    low = {}
    for i, (k, _) in enumerate(rows):
        low.setdefault(find(i), []).append((k is None, k or 0))
    return sorted(min(v) for v in low.values())


def kept(out):
    return sorted((r.doc_id is None, r.doc_id or 0) for r in out.collect())


def test_near_stage_keeps_one_of_each_component(spark):
    rng = random.Random(11)
    rows = []
    for n in (3, 9, 24, 60, 150, 150, 400):
        base = [f"w{rng.randrange(10**6)}" for _ in range(n)]
        for _ in range(14):
            t = list(base)
            for _ in range(rng.randrange(1 + n // 12)):
                t[rng.randrange(n)] = rng.choice("ABCDé") + str(rng.randrange(10**6))
            rows.append((len(rows), "a line that every text has at its start " * rng.randrange(2) + "  ".join(t)))
    chain = [f"c{i}" for i in range(300)]
    rows += [(len(rows) + k, " ".join(chain[8 * k : 8 * k + 120])) for k in range(20)]  # alike only step by step
    rows += [(9001, None), (9002, ""), (9003, " \t\n"), (9004, "one two"), (9005, "One  TWO"), (9006, "one"), (None, rows[40][1] + " end"), (9007, "é É")]
    ids = [k for k, _ in rows if k is not None]
    names = dict(zip(ids, rng.sample(ids, len(ids)), strict=True))
    rows = [(names.get(k), t) for k, t in rows]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    want = survivors(rows)
    assert len(want) < len(rows) - 40
    assert kept(corpus_pipeline.near_stage(spark, df, "")) == want
    assert corpus_pipeline.near_stage(spark, df.limit(0), "").count() == 0


def test_near_stage_on_the_tables(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text").dropDuplicates(["text"]).cache()
    rows = [tuple(r) for r in docs.collect()]
    assert kept(corpus_pipeline.near_stage(spark, docs, "")) == survivors(rows)


def test_links_of_simhash_are_not_searched_again(spark, monkeypatch):
    from vtask.llm import near_text

    rng = random.Random(4)
    base = [f"w{rng.randrange(10**6)}" for _ in range(600)]
    rows = [(i, " ".join(base[:300] + [f"x{i}"] + base[301:])) for i in range(30)]  # a bit or two apart
    df = spark.createDataFrame(rows, "doc_id long, text string")
    asked, inner = [], near_text._verified
    monkeypatch.setattr(near_text, "_verified", lambda pairs, sets: asked.append(pairs.count()) or inner(pairs, sets))
    assert kept(near_text.first_of_near_copies(df)) == [(False, 0)]
    assert asked == [29, 0, 0]
    # without these links the shingles have them all to find
    asked.clear()
    monkeypatch.setattr(near_text, "near_components", lambda fps: fps.selectExpr("id", "id AS component_id"))
    assert kept(near_text.first_of_near_copies(df)) == [(False, 0)]
    assert asked[0] == 0 and asked[1] >= 29
