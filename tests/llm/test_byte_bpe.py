from __future__ import annotations

import hashlib
import random

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from pyspark.sql import functions as F

from vtask.llm.byte_bpe import _ID_BITS, decode, encode, fold_words, heap_merge, load_ranks, op7_byte_bpe, rank_rows

FILE = P.path("byte_bpe_50k.tiktoken")


@pytest.fixture(scope="module")
def ranks():
    return load_ranks(open(FILE, "rb").read())


@pytest.fixture(scope="module")
def tik(ranks):
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_rank_rows(ranks):
    off, ent = rank_rows(open(FILE, "rb").read())
    name = {i: p for p, i in ranks.items()}
    rng = random.Random(1)
    some, hits = list(name)[:2000], 0
    for _ in range(50000):
        a, b = rng.choice(some), rng.choice(some)
        e = int(ent[(off[a] + b) & (ent.size - 1)])
        got = e & ((1 << _ID_BITS) - 1) if e >> _ID_BITS == a else None
        assert got == ranks.get(name[a] + name[b])
        hits += got is not None
    assert hits > 100


def test_native_fold(spark, tik):
    words = ["a", "the", "tionally", " ererthing", "éclair", "xyzzyq", "漢字", "", None, "aaaaaaaaaaaaaaaaaaaa"]
    df = spark.createDataFrame([(w,) for w in words], "word string")
    for r in fold_words(df, FILE).collect():
        assert r.ids == (tik.encode_ordinary(r.word) if r.word else None)


def test_heap(ranks, tik):
    rng = random.Random(2)
    for n in (1, 2, 3, 10, 300, 5000):
        w = "".join(rng.choice("abcdethonrsi") for _ in range(n))
        assert heap_merge(w.encode(), ranks) == tik.encode_ordinary(w)


def test_texts(spark, tik, awkward, tmp_path):
    rng = random.Random(3)
    bits = [" ", "  ", "the", "ing", "Xy", "1", "23", "'s", "'", "\n", "\t", "é", "ß漢字", "\U0001f600", "!?", "<|endoftext|>", "tion"]
    rows = [(i, "".join(rng.choice(bits) for _ in range(rng.randrange(60)))) for i in range(300)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    for kw in ({}, {"batch": 200, "long_word": 5}):
        got = decode(encode(df, FILE, P.PATTERN, **kw), FILE).collect()
        assert len(got) == 300
        for r in got:
            t = rows[r.doc_id][1]
            assert np.frombuffer(r.ids, "<u4").tolist() == tik.encode_ordinary(t) and r.decoded.decode() == t and r.n_tokens == len(r.ids) // 4
    awkward.withColumn("ids", F.lit(1)).withColumn("words", F.lit(2)).write.parquet(str(tmp_path / "documents.parquet"))
    texts = {r.doc_id: r.text or "" for r in awkward.collect()}
    got = op7_byte_bpe(spark, str(tmp_path)).collect()
    assert len(got) == 12
    for r in got:
        ids = tik.encode_ordinary(texts[r.doc_id])
        assert (r.n_tokens, r.ids_sha256, r.decoded_sha256) == (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(texts[r.doc_id].encode()).hexdigest())
    assert encode(awkward.limit(0), FILE, P.PATTERN).count() == 0
