"""Language of pages by Bayesian evidence fusion.

Evidence on a page: how likely its visible text is in each language (hashed
three-byte features, naive Bayes from labelled documents), the language that its
markup declares, the suffix of its address, and a prior of its host. A first
posterior from the text alone gives soft counts; grouped sums of these give
P(declared | language) and P(suffix | language), and a prior of each host that
is smoothed by its domain's, which is smoothed by the whole corpus's. A page's
own count is left out of all four, as its text speaks for itself. The fused
posterior is their product.

A text is not a bag of independent draws, so its log-likelihood counts as that
of `cap` features at most. The text model is fitted on a bounded sample: the
`sample` labelled documents of smallest hashed id.

Movement of data: pages are read once; then rows of a few numbers. Sums by host
are merged before they are shuffled, and joins on the host are ones whose large
partitions Spark can split.

Defined cases: null html has no text and declares nothing; a null or odd url
has the host, domain and suffix ''; such evidence is a value like any other; a
page without evidence gets the prior; rows that repeat a page are pages of their
own; no labelled documents, or no pages, give an empty result; other columns are
ignored.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vtask.llm.common import need, settle, sliced, text_values, tidy

_DIM = 1 << 13
_ENTITY = re.compile(rb"&[a-zA-Z#0-9]{1,8};")
_HIDDEN = re.compile(rb"(?i)<(script|style)\b")
_CLOSE = {k: re.compile(rb"(?i)</" + k + rb"\s*+>") for k in (b"script", b"style")}
_HTML = re.compile(rb"(?i)<html\b")
_LANG = re.compile(rb"(?i)\blang\s*+=\s*+[\"']?\s*+([a-zA-Z]{2,8})")
_HOST = re.compile(r"(?i)^[a-z][a-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)")
_LETTER = np.zeros(256, np.uint8)
for _c in range(256):
    _LETTER[_c] = ord(chr(_c).lower()) if _c < 128 and chr(_c).isalpha() else _c if _c >= 128 else 32


def gram_features(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(text of each feature, its number): letters' byte triples, each run of other bytes as one space."""
    buf = np.frombuffer(b" ".join([b"", *texts, b""]), np.uint8)
    text = np.repeat(np.arange(len(texts)), [len(t) + 1 for t in texts]) if texts else np.zeros(0, np.int64)
    text = np.concatenate(([0], text)) if texts else np.zeros(buf.size, np.int64)
    c = _LETTER[buf]
    keep = np.ones(c.size, bool)
    keep[1:] = (c[1:] != 32) | (c[:-1] != 32)
    c, text = c[keep].astype(np.uint64), text[keep]
    if c.size < 3:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    g = (c[:-2] << np.uint64(16)) | (c[1:-1] << np.uint64(8)) | c[2:]
    ok = (text[1:-1] == text[2:]) & (c[1:-1] != 32)  # a middle byte that is a letter, of one text
    return text[1:-1][ok], ((g[ok] * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - 13)).astype(np.int64)


def visible(html: bytes) -> bytes:
    """html with a blank for each comment, script, style, tag and entity; what is never closed counts as a plain tag, or as text if it has no end either. One pass."""
    out, at, never = [], 0, set()
    while (i := html.find(b"<", at)) >= 0:
        end = -1
        m = _HIDDEN.match(html, i)
        kind = b"--" if html.startswith(b"<!--", i) else m[1].lower() if m else None
        if kind and kind not in never:
            if kind == b"--":
                end = html.find(b"-->", i + 4) + 3 if html.find(b"-->", i + 4) >= 0 else -1
            elif c := _CLOSE[kind].search(html, m.end()):
                end = c.end()
            if end < 0:
                never.add(kind)  # nor is there one further on
        if end < 0:
            end = html.find(b">", i) + 1
        out += [html[at:i], b" "]
        if not end:
            at = i
            break
        at = end
    return _ENTITY.sub(b" ", b"".join([*out, html[at:]]))


def declared_language(html: bytes) -> str:
    """The language of the first <html> tag that names one, else ''."""
    at = 0
    while m := _HTML.search(html, at):
        at = html.find(b">", m.end())
        at = len(html) if at < 0 else at
        if got := _LANG.search(html, m.end(), at):
            return got[1].decode().lower()
    return ""


def host_parts(url: str | None) -> tuple[str, str, str]:
    """(host, domain, suffix), lower case."""
    m = _HOST.match(url or "")
    host = m[1].lower().strip(".") if m else ""
    labels = host.split(".")
    return host, ".".join(labels[-2:]), labels[-1] if len(labels) > 1 else ""


def fit_text_model(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", sample: int = 4000, seed: int = 42) -> tuple[list[str], np.ndarray]:
    """Languages and log P(feature | language), from the labelled documents of smallest hashed id."""
    need(docs, id_col, text_col, lang_col)
    key = F.xxhash64(F.lit(seed), F.col(id_col).cast("long"))
    src = docs.filter(F.col(lang_col).isNotNull()).select(F.col(lang_col).cast("string").alias("lang"), F.col(text_col).cast("string").alias("text"), key.alias("k"))
    last = src.select("k").orderBy("k").limit(sample).agg(F.max("k")).first()[0]
    if last is None:
        return [], np.zeros((0, _DIM))

    def run(batches):
        total: dict[str, np.ndarray] = {}
        for b in sliced(batches, "text", 2 << 20):
            langs = b.column("lang").to_pylist()
            of, f = gram_features(text_values(b.column("text")))
            names = sorted(set(langs))
            code = np.array([names.index(x) for x in langs])
            n = np.bincount(code[of] * _DIM + f, minlength=len(names) * _DIM).reshape(-1, _DIM)
            for x, row in zip(names, n, strict=True):
                total[x] = total.get(x, 0) + row
        yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.string()), pa.array([r.tobytes() for r in total.values()], pa.binary())], ["lang", "n"])

    rows = src.filter(F.col("k") <= last).select("lang", "text").mapInArrow(tidy(run), "lang string, n binary").collect()  # a row a language and task, of a sample of fixed size
    total: dict[str, np.ndarray] = {}
    for r in rows:
        total[r.lang] = total.get(r.lang, 0) + np.frombuffer(r.n, np.int64)
    langs = sorted(total)
    n = np.stack([total[x] for x in langs]) + 0.5
    return langs, np.log(n / n.sum(axis=1, keepdims=True))


def page_evidence(pages: DataFrame, model: tuple[list[str], np.ndarray], id_col: str = "page_id", url_col: str = "url", html_col: str = "html", cap: float = 30) -> DataFrame:
    """One row a page: id, host, domain, suffix, declared, n_features, ll (log-likelihood by language, at most cap features' worth)."""
    need(pages, id_col, url_col, html_col)
    langs, table = model
    flat = np.ascontiguousarray(table.T)

    def run(batches):
        for b in sliced(batches, "html", 4 << 20):
            html = text_values(b.column("html"))
            of, f = gram_features([visible(h) for h in html])
            n = np.bincount(of, minlength=len(html))
            ll = np.stack([np.bincount(of, flat[f, k], len(html)).astype(float) for k in range(len(langs))], axis=1) if len(langs) else np.zeros((len(html), 0))
            ll *= (np.minimum(n, cap) / np.maximum(n, 1))[:, None]
            ll = np.round(ll - ll.max(axis=1, keepdims=True), 6) if len(langs) else ll
            declared = list(map(declared_language, html))
            host, domain, suffix = zip(*map(host_parts, b.column("url").to_pylist()), strict=True)
            strings = [pa.array(x, pa.string()) for x in (host, domain, suffix, declared)]
            yield pa.RecordBatch.from_arrays([b.column("id"), *strings, pa.array(n.astype(np.int64)), pa.array(ll.tolist(), pa.list_(pa.float64()))], ["id", "host", "domain", "suffix", "declared", "n_features", "ll"])

    src = pages.select(F.col(id_col).cast("long").alias("id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))
    return src.mapInArrow(tidy(run), "id long, host string, domain string, suffix string, declared string, n_features long, ll array<double>")


def fuse(evidence: DataFrame, langs: list[str], strength: float = 2.0, alpha: float = 0.5) -> DataFrame:
    """One row a page: page_id, lang, probability, text_lang, declared, host, host_prior (of lang)."""
    k = range(len(langs))

    def vector(f):
        return F.array(*(f(i) for i in k))

    def normal(v):  # v: expression of an array of positive numbers
        return F.transform(v, lambda x: x / F.aggregate(v, F.lit(0.0), lambda s, y: s + y))

    # rounded, so that sums do not depend on the order of rows, and never zero
    p = settle(evidence.withColumn("p", F.transform(normal(F.transform("ll", lambda x: F.exp(x))), lambda x: F.greatest(F.round(x, 6), F.lit(1e-6)))))

    def sums(key):
        return p.groupBy(key).agg(*(F.sum(F.col("p")[i].cast("decimal(20,6)")).cast("double").alias(f"s{i}") for i in k)).select(key, vector(lambda i: F.col(f"s{i}")).alias(f"s_{key}"))

    total = p.agg(*(F.sum(F.col("p")[i].cast("decimal(20,6)")).cast("double").alias(f"s{i}") for i in k), F.count_distinct("suffix").alias("suffix"), F.count_distinct("declared").alias("declared")).first()
    overall = [total[i] or 0.0 for i in k]

    def others(s, i):  # the sum without the page's own share, which is in its text already
        return F.greatest(s - F.col("p")[i], F.lit(0.0))

    def likelihood(key):
        """P(value of key | language), by all other pages."""
        return vector(lambda i: (others(F.col(f"s_{key}")[i], i) + alpha) / (others(F.lit(overall[i]), i) + alpha * total[key]))

    def smooth(key, prior):
        """Share of each language among the other pages of key, held towards prior."""
        n = sum((others(F.col(f"s_{key}")[i], i) for i in k), F.lit(0.0))
        return vector(lambda i: (others(F.col(f"s_{key}")[i], i) + strength * prior[i]) / (n + strength))

    every = sum((others(F.lit(x), i) for i, x in enumerate(overall)), F.lit(0.0))
    base = [(others(F.lit(overall[i]), i) + alpha) / (every + alpha * len(langs)) for i in k]
    j = p
    for key in ("host", "domain", "suffix", "declared"):
        j = j.join(sums(key), key)
    j = j.withColumn("d", smooth("domain", base)).withColumn("prior", smooth("host", F.col("d")))
    j = j.withColumn("l_suffix", likelihood("suffix")).withColumn("l_declared", likelihood("declared"))
    j = j.withColumn("fused", normal(vector(lambda i: F.col("p")[i] * F.col("prior")[i] * F.col("l_suffix")[i] * F.col("l_declared")[i])))
    names = F.array(*map(F.lit, langs))

    def best(v):
        return F.element_at(names, F.array_position(v, F.array_max(v)).cast("int"))

    at = F.array_position("fused", F.array_max("fused")).cast("int")
    return j.select(F.col("id").alias("page_id"), best(F.col("fused")).alias("lang"), F.round(F.array_max("fused"), 6).alias("probability"), best(F.col("p")).alias("text_lang"), "declared", "host", F.round(F.element_at("prior", at), 6).alias("host_prior"), "n_features")


def identify_languages(pages: DataFrame, labelled: DataFrame, sample: int = 4000, cap: float = 30) -> DataFrame:
    """Language of each page; labelled has doc_id, text and lang."""
    model = fit_text_model(labelled, sample=sample)
    if not model[0]:
        return pages.sparkSession.createDataFrame([], "page_id long, lang string, probability double, text_lang string, declared string, host string, host_prior double, n_features long")
    return fuse(page_evidence(pages, model, cap=cap), model[0])


def op8_language_id(spark, sf_dir: str) -> DataFrame:
    return identify_languages(spark.read.parquet(f"{sf_dir}/pages.parquet"), spark.read.parquet(f"{sf_dir}/documents.parquet"))
