from __future__ import annotations

import re
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers as P
import tiktoken
from pyspark.sql import functions as F

import corpus_pipeline
from tests.llm.test_near_text import survivors
from vtask.llm.byte_bpe import load_ranks
from vtask.llm.mixing import fit_budget, word_count


def test_stages_against_plain_versions(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    cols, rows = docs.columns, [r.asDict() for r in docs.collect()]
    (_, quality), (_, exact), (_, near), (_, mix), (_, encode) = corpus_pipeline.STAGES
    kept = quality(spark, docs, "")
    label = {r.doc_id: r.quality for r in spark.read.parquet("/root/testdata/sf0.001/labels.parquet").collect()}
    ids = {r.doc_id for r in kept.collect()}
    assert kept.columns == cols and all(i in ids for i, q in label.items() if q == 1 and i < len(rows))
    # exact copies, whatever their white space; a repeated row; a null text and an empty one
    more = rows + [rows[3] | {"doc_id": 9001, "text": rows[3]["text"].replace(" ", "\n ")}, rows[5], rows[0] | {"doc_id": 9002, "text": None}, rows[0] | {"doc_id": 9003, "text": ""}]
    low = {}
    for r in more:
        t = re.sub("[\x20\t-\r]+", " ", r["text"] or "")
        low[t] = min(low.get(t, r["doc_id"]), r["doc_id"])
    out = exact(spark, spark.createDataFrame(more, docs.schema), "").select(*cols)
    got = [r.doc_id for r in out.collect()]
    assert sorted(got) == sorted(low.values())
    by_id = {r["doc_id"]: r for r in more}
    uniq = [by_id[i] for i in sorted(got)]
    df = spark.createDataFrame(uniq, docs.schema)
    assert sorted(r.doc_id for r in near(spark, df, "").collect()) == [i for _, i in survivors([(r["doc_id"], r["text"]) for r in uniq])]
    mixed = mix(spark, df, "")
    assert mixed.columns == cols
    times = Counter(r.doc_id for r in mixed.collect())
    assert max(times.values()) <= 3
    size, taken = defaultdict(int), defaultdict(int)
    for r in uniq:
        n = len((r["text"] or "").encode().split())
        size[r["source"]] += n
        taken[r["source"]] += n * times[r["doc_id"]]
    from tests.llm.test_mixing import targets

    for s, t in targets(size).items():
        n = np.array(sorted(Counter(len((r["text"] or "").encode().split()) for r in uniq if r["source"] == s).items()))
        base, extra = fit_budget(n[:, 0], n[:, 1], t)
        assert taken[s] == base * size[s] + int((extra * n[:, 0]).sum())
    tik = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=load_ranks(open(P.path("byte_bpe_50k.tiktoken"), "rb").read()), special_tokens={})
    for r in encode(spark, df.limit(40), "").collect():
        assert np.frombuffer(r.ids, "<u4").tolist() == tik.encode_ordinary(by_id[r.doc_id]["text"] or "")
    assert df.agg(F.sum(word_count("text"))).first()[0] == sum(size.values())


def test_whole_run(spark, awkward, tmp_path):
    awkward.write.parquet(str(tmp_path / "a/documents.parquet"))
    out = corpus_pipeline.run(spark, str(tmp_path / "a"))
    assert out.columns[:2] == ["doc_id", "n_tokens"] and out.count() > 0
    awkward.limit(0).write.parquet(str(tmp_path / "b/documents.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path / "b")).count() == 0
