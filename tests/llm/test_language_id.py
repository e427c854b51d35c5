from __future__ import annotations

import math
import re
import time

import numpy as np
from pyspark.sql import functions as F

from vtask.llm.language_id import declared_language, fit_text_model, fuse, gram_features, host_parts, identify_languages, page_evidence, visible


def test_parts():
    assert host_parts("https://u:p@M.Ex.example.NET:80/en/25#top") == ("m.ex.example.net", "example.net", "net")
    assert host_parts(None) == host_parts("nonsense") == ("", "", "")
    assert b"secret" not in visible(b"<p>a<script>secret</script><!-- secret --><style>secret</style>&amp;b")
    of, f = gram_features([b"Ab, c", b"", b"ab c"])
    assert f[of == 0].tolist() == f[of == 2].tolist() and not (of == 1).any()


def test_known_pages(spark):
    d = "/root/testdata/sf0.01"
    rows = identify_languages(spark.read.parquet(f"{d}/pages.parquet"), spark.read.parquet(f"{d}/documents.parquet"), sample=400)
    url = {r.page_id: r.url for r in spark.read.parquet(f"{d}/pages.parquet").collect()}
    got = rows.collect()
    assert len(got) == len(url)
    named = [r for r in got if any(f"/{x}/" in url[r.page_id] for x in ("en", "fr", "de", "es"))]
    hit = sum(f"/{r.lang}/" in url[r.page_id] for r in named)
    assert hit >= 0.95 * len(named), (hit, len(named))


def brute(rows, langs, strength=2.0, alpha=0.5):
    """rows: (id, host, domain, suffix, declared, ll)."""
    k = len(langs)
    p = []
    for *_, ll in rows:
        e = [math.exp(x) for x in ll]
        p.append(np.array([max(round(x / sum(e), 6), 1e-6) for x in e]))
    out = {}
    for n, (r, q) in enumerate(zip(rows, p, strict=True)):
        others = [(x, y) for m, (x, y) in enumerate(zip(rows, p, strict=True)) if m != n]  # a page's own text is counted once only

        def total(c=None, rest=others, me=r):
            return sum((y for x, y in rest if c is None or x[c] == me[c]), np.zeros(k))

        base = (total() + alpha) / (total().sum() + alpha * k)
        dom = (total(2) + strength * base) / (total(2).sum() + strength)
        f = q * (total(1) + strength * dom) / (total(1).sum() + strength)
        for c in (3, 4):
            f = f * (total(c) + alpha) / (total() + alpha * len({x[c] for x in rows}))
        f /= f.sum()
        out[r[0]] = (langs[int(f.argmax())], round(float(f.max()), 6))
    return out


def test_fusion_equals_brute_force(spark):
    rng = np.random.default_rng(4)
    langs = ["aa", "bb", "cc"]
    rows = []
    for i in range(80):
        h, n = int(rng.integers(6)), int(rng.integers(3))
        rows.append((i, f"h{h}.d{h % 2}.x", f"d{h % 2}.x", f"t{n}", ["", "aa", "bb"][n], (-rng.random(3) * 4).round(6).tolist()))
    df = spark.createDataFrame([(*r[:5], 9, r[5]) for r in rows], "id long, host string, domain string, suffix string, declared string, n_features long, ll array<double>").repartition(5)
    got = {r.page_id: (r.lang, r.probability) for r in fuse(df, langs).collect()}
    want = brute(rows, langs)
    assert set(got) == set(want)
    for i, (lang, prob) in want.items():
        assert got[i][0] == lang and abs(got[i][1] - prob) < 2e-6


def test_awkward(spark, awkward):
    pages = spark.createDataFrame([(1, None, None, 1), (None, "http://a.b/", "<html lang='fr'>le la", 2), (1, "", "", 3), (2, "x" * 9000, "<p>" * 50000, 4)], "page_id long, url string, html string, lang int")
    out = identify_languages(pages, awkward.filter("lang is not null"), sample=5).collect()
    assert len(out) == 4 and all(r.lang in ("en", "fr") for r in out)
    assert identify_languages(pages.limit(0), awkward).count() == 0
    assert identify_languages(pages, awkward.withColumn("lang", F.lit(None))).count() == 0
    langs, table = fit_text_model(awkward)
    assert page_evidence(pages, (langs, table)).count() == 4


DROP = re.compile(rb"(?is)<(script|style)\b.*?</\1\s*>|<!--.*?-->|<[^>]*>|&[a-zA-Z#0-9]{1,8};")
LANG = re.compile(rb"(?is)<html\b[^>]*?\blang\s*=\s*[\"']?\s*([a-zA-Z]{2,8})")


def test_markup_equals_plain_patterns():
    rng = np.random.default_rng(3)
    bits = [b"<", b">", b"<!--", b"-->", b"<script", b"</script >", b"<style>", b"</STYLE>", b"text", b" ", b"&amp;", b"<p>", b"<html", b" lang=", b"'fr'", b"de ", b"xml:lang = en", b"-"]
    for _ in range(20000):
        t = b"".join(bits[i] for i in rng.integers(0, len(bits), rng.integers(0, 14)))
        assert b"".join(visible(t).split()) == b"".join(DROP.sub(b" ", t).split()), t
        m = LANG.search(t)
        assert declared_language(t) == (m[1].decode().lower() if m else ""), t


def test_open_markup_takes_linear_time():
    start = time.perf_counter()
    for t in (b"<!-- x ", b"<script a ", b"<html a ", b"<html lang ", b"<", b"</script ", b"<style>", b"&aaaaaaaaa"):
        for end in (b"", b">", b"-->"):
            visible(t * 150_000 + end)
            declared_language(t * 150_000 + end)
    assert time.perf_counter() - start < 30


def test_text_likelihood_by_hand(spark):
    docs = [(1, "abc abd", "en"), (2, "abc", "en"), (3, "xyz", "fr"), (4, None, "fr"), (5, "zzz", None)]
    langs, table = fit_text_model(spark.createDataFrame(docs, "doc_id long, text string, lang string"))
    counts = {"en": {}, "fr": {}}
    for _, t, x in docs:
        if x:
            for f in gram_features([(t or "").encode()])[1].tolist():
                counts[x][f] = counts[x].get(f, 0) + 1
    assert langs == ["en", "fr"]
    for k, x in enumerate(langs):
        n = sum(counts[x].values()) + 0.5 * table.shape[1]
        for f in (0, *counts["en"], *counts["fr"]):
            assert abs(table[k, f] - math.log((counts[x].get(f, 0) + 0.5) / n)) < 1e-12
    page = spark.createDataFrame([(1, "http://a.b/", "<b>abc</b> xyz xyz")], "page_id long, url string, html string")
    got = page_evidence(page, (langs, table)).first()
    f = gram_features([b" abc  xyz xyz"])[1]
    ll = [float(sum(table[k, x] for x in f)) for k in range(2)]
    assert got.n_features == f.size and np.allclose(got.ll, np.array(ll) - max(ll), atol=1e-5)
