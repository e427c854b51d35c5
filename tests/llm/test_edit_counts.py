from __future__ import annotations

import random

import public_tokenizers as P
import pytest
import regex
import tiktoken
from pyspark.sql import functions as F

from vtask.llm.byte_bpe import load_ranks
from vtask.llm.edit_counts import EditTree, PieceCounter, count_after_edits, seeded_edits

FILE = P.path("byte_bpe_50k.tiktoken")


@pytest.fixture(scope="module")
def data():
    return open(FILE, "rb").read()


def test_random_edits(data):
    split, count = regex.compile(P.PATTERN), PieceCounter(data)
    tik = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=load_ranks(data), special_tokens={})
    rng = random.Random(5)
    bits = [" ", "  ", "   ", "the", "ing", "X", "1", "23", "'s", "'", "'l", "l", "\n", "\t", "é", "漢", "!?", " word"]
    for round_ in range(250):
        text = "".join(rng.choice(bits) for _ in range(rng.choice([0, 3, 30, 900])))
        t = EditTree(text, split, count)
        assert t.total == len(tik.encode_ordinary(text))
        for _ in range(12):
            a = rng.randrange(len(text) + 2)
            b = a + rng.choice([0, 0, 1, 3, 40, -2])
            new = "".join(rng.choice(bits) for _ in range(rng.choice([0, 1, 2, 9])))
            t.edit(a, b, new)
            a = min(a, len(text))
            text = text[:a] + new + text[min(max(a, b), len(text)) :]
            assert t.text() == text, round_
            assert [p for leaf in t.leaves for p in leaf] == split.findall(text)
            assert t.total == len(tik.encode_ordinary(text))


def test_edits_touch_little(data):
    split, count = regex.compile(P.PATTERN), PieceCounter(data)
    t = EditTree("some words of a text " * 20000, split, count)
    for i in range(50):
        t.edit(i * 4000, i * 4000 + 5, " other ")
    assert t.encoded < 50 * 20
    t.edit(0, 10**9, "")
    assert (t.total, t.text()) == (0, "")


def test_rows(spark, awkward, data):
    tik = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=load_ranks(data), special_tokens={})
    clash = awkward.withColumn("edits", F.lit(1)).withColumn("n_tokens", F.lit("x"))
    got = count_after_edits(clash, FILE, P.PATTERN, seeded_edits("doc_id", "text")).collect()
    assert len(got) == 12 and all(r.n_tokens_after == len(tik.encode_ordinary(r.text_after)) and r.n_edits == 4 for r in got)
    none = count_after_edits(awkward, FILE, P.PATTERN, F.lit(None)).collect()
    texts = {r.doc_id: r.text or "" for r in awkward.collect()}
    assert all(r.text_after == texts[r.doc_id] and r.n_tokens == r.n_tokens_after == len(tik.encode_ordinary(r.text_after)) for r in none)
    assert count_after_edits(awkward.limit(0), FILE, P.PATTERN, F.lit(None)).count() == 0
