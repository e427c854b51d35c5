"""Quality by weak labels: heuristic labellers, their accuracies, a hashed linear scorer.

Labellers look at a document's words and vote bad, good or nothing. Their votes
are counted over all documents by pattern (at most 3 ^ labellers rows come to
the driver); expectation-maximisation finds from the counts alone how likely
each labeller's votes are on good and on bad documents, and so the posterior of
each pattern; a labeller that does not vote says nothing. A logistic scorer over hashed word endings and word shapes is then
fitted to the posteriors of a bounded sample, the `sample` documents of
smallest hashed id, and scores every document; documents whose score is above
`reject` go.

Defined cases: null or blank text has no words, gets no votes and is kept;
words of any length count once; rows that repeat an id are scored alike; an
empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vtask.llm.common import Docs, need, sliced, text_values, tidy

# fixed values: common words of the languages at hand
STOP = (
    "the of and to in a is that for it was on are as with he be at by this from "
    "de la le les et des en un une du que qui dans pour sur par est au "
    "der die das und ist nicht ein eine mit von zu den dem im auf für "
    "el los las del y con para su al lo se por como"
).split()
LABELLERS = ("symbols", "shouting", "bars", "stutter", "echo", "common_words")
_DIM = 1 << 14
_NAME = "__votes"

_KIND = np.zeros(256, np.int8)  # 1 lower, 2 upper, 3 symbol, 4 other ASCII punctuation and digits, 5 the rest
_KIND[:] = 5
for _c in range(33, 128):
    _KIND[_c] = 1 if chr(_c).islower() else 2 if chr(_c).isupper() else 3 if chr(_c) in "#$%&*@^~=<>{}\\_" else 4


class _Words:
    """Facts about each word of many documents."""

    def __init__(self, texts: list[bytes]):
        d = self.d = Docs(texts)
        self.n = np.diff(d.word_at)
        kind = _KIND[d.buf]
        latin = np.flatnonzero(d.buf[:-1] == 0xC3) + 1  # accented letters of Latin-1
        kind[latin] = np.where(d.buf[latin] < 0xA0, 2, 1)

        def count(k):
            c = np.concatenate(([0], np.cumsum(kind == k)))
            return c[d.end] - c[d.start]

        self.h = d.hashes()
        lower, upper, symbol = count(1), count(2), count(3)
        self.shout = (upper >= 2) & (lower == 0)
        self.symbol = (symbol >= 2) & (lower + upper + count(5) > 0)
        size = d.end - d.start
        self.bar = (size == 1) & (d.buf[d.start] == ord("|")) if d.start.size else np.zeros(0, bool)
        self.again = np.zeros(self.h.size, bool)
        self.again[1:] = (self.h[1:] == self.h[:-1]) & (d.doc[1:] == d.doc[:-1])
        self.echo = np.zeros(self.h.size, bool)
        self.echo[2:] = (self.h[2:] == self.h[:-2]) & (d.doc[2:] == d.doc[:-2])
        self.stop = np.isin(self.h, _stop_hashes())

    def share(self, flag: np.ndarray) -> np.ndarray:
        c = np.concatenate(([0], np.cumsum(flag)))
        return (c[self.d.word_at[1:]] - c[self.d.word_at[:-1]]) / np.maximum(self.n, 1)

    def votes(self) -> np.ndarray:
        """(documents, labellers): 1 bad, 0 good, 2 nothing."""
        n = self.n
        out = np.full((n.size, len(LABELLERS)), 2, np.int8)
        for j, (flag, bad, good) in enumerate(((self.symbol, 0.25, 0.02), (self.shout, 0.3, 0.05), (self.bar, 0.2, 0.02), (self.again, 0.3, 0.05), (self.echo, 0.2, 0.06))):
            s = self.share(flag)
            out[(s >= bad) & (n > 2), j] = 1
            out[(s <= good) & (n >= 20), j] = 0
        s = self.share(self.stop)
        out[(s <= 0.04) & (n >= 30), 5] = 1
        out[(s >= 0.12) & (n >= 5), 5] = 0
        return out

    def features(self) -> tuple[np.ndarray, np.ndarray]:
        """(document of each word, (words, 2) feature numbers): the hashed ending of three bytes, and the shape."""
        d = self.d
        tail = np.zeros(d.start.size, np.int64)
        for k in range(1, 4):
            at = d.end - k
            tail = tail * 257 + np.where(at >= d.start, d.buf[np.maximum(at, 0)].astype(np.int64) + 1, 0)
        tail = (tail.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(50)).astype(np.int64)
        shape = self.shout + 2 * self.symbol + 4 * self.bar + 8 * self.again + 16 * self.stop
        return d.doc, np.stack([32 + tail % (_DIM - 32), shape.astype(np.int64)], axis=1)


_cache: dict = {}


def _stop_hashes() -> np.ndarray:
    if "stop" not in _cache:
        words = [w.encode() for s in STOP for w in (s, s.capitalize(), s + ",", s + ".")]
        _cache["stop"] = np.unique(Docs(words).hashes())
    return _cache["stop"]


def pattern_counts(src: DataFrame) -> dict[tuple[int, ...], int]:
    """How many documents of src(text) have each pattern of votes."""

    def run(batches):
        total: dict[tuple[int, ...], int] = {}
        for b in sliced(batches, "text", 2 << 20):
            pat, n = np.unique(_Words(text_values(b.column("text"))).votes(), axis=0, return_counts=True)
            for p, c in zip(map(tuple, pat.tolist()), n.tolist(), strict=True):
                total[p] = total.get(p, 0) + c
        yield pa.RecordBatch.from_arrays([pa.array(["".join(map(str, p)) for p in total], pa.string()), pa.array(list(total.values()), pa.int64())], ["pattern", "n"])

    rows = src.select("text").mapInArrow(tidy(run), "pattern string, n long").groupBy("pattern").agg(F.sum("n").alias("n")).collect()
    return {tuple(map(int, r.pattern)): r.n for r in rows}


def label_model(counts: dict[tuple[int, ...], int], rounds: int = 200, prior: float = 1.0) -> tuple[dict[tuple[int, ...], float], np.ndarray]:
    """Posterior of bad for each pattern, and P(vote | class, it votes) as (labeller, class, vote), by expectation-maximisation."""
    pats = sorted(counts)
    if not pats:
        return {}, np.zeros((len(LABELLERS), 2, 2))
    v, n = np.array(pats), np.array([counts[p] for p in pats], float)
    bad, good = (v == 1).sum(axis=1), (v == 0).sum(axis=1)
    post = np.where(bad > 0, 0.9, np.where(good > 0, 0.05, 0.1))  # one complaint outweighs the rest to begin with
    hot = np.stack([v == k for k in range(2)], axis=2).astype(float)
    for _ in range(rounds):
        w = np.stack([n * (1 - post), n * post])
        theta = np.einsum("cp,pjk->jck", w, hot) + prior
        theta /= theta.sum(axis=2, keepdims=True)
        share = (w.sum(axis=1) + prior) / (n.sum() + 2 * prior)
        log = np.log(share) + np.einsum("pjk,jck->pc", hot, np.log(theta))
        new = 1 / (1 + np.exp(np.clip(log[:, 0] - log[:, 1], -50, 50)))
        if np.abs(new - post).max() < 1e-9:
            break
        post = new
    return dict(zip(pats, post.tolist(), strict=True)), theta


def _rows_of(words: _Words, dim: int = _DIM) -> np.ndarray:
    """Dense (documents, dim) square roots of feature shares; for small batches."""
    doc, f = words.features()
    x = np.zeros((words.n.size, dim), np.float32)
    for k in range(f.shape[1]):
        np.add.at(x, (doc, f[:, k]), 1)
    return np.sqrt(x / np.maximum(words.n, 1)[:, None])


def fit_scorer(src: DataFrame, post: dict, sample: int, seed: int) -> tuple[np.ndarray, float]:
    """Weights and offset, from the sample documents of smallest hashed id."""
    key = F.xxhash64(F.lit(seed), "id")
    last = src.select(key.alias("k")).orderBy("k").limit(sample).agg(F.max("k")).first()[0]
    if last is None:
        return np.zeros(_DIM), 0.0

    def run(batches):
        for b in sliced(batches, "text", 1 << 20):
            w = _Words(text_values(b.column("text")))
            doc, f = w.features()
            y = [post[tuple(p)] for p in w.votes().tolist()]
            at = np.searchsorted(doc, np.arange(w.n.size + 1))
            cols, vals = [], []
            for i in range(w.n.size):
                c, n = np.unique(f[at[i] : at[i + 1]], return_counts=True)
                cols.append(c.tolist())
                vals.append(np.sqrt(n / max(1, w.n[i])).tolist())
            yield pa.RecordBatch.from_arrays([b.column("k"), pa.array(y), pa.array(cols, pa.list_(pa.int64())), pa.array(vals, pa.list_(pa.float64()))], ["k", "y", "cols", "vals"])

    rows = src.select("text", key.alias("k")).filter(F.col("k") <= last).mapInArrow(tidy(run), "k long, y double, cols array<long>, vals array<double>").collect()
    rows.sort(key=lambda r: (r.k, r.cols))
    y = np.array([r.y for r in rows])
    size = np.array([len(r.cols) for r in rows])
    row, col, val = np.repeat(np.arange(y.size), size), np.array([c for r in rows for c in r.cols], np.int64), np.array([c for r in rows for c in r.vals])
    weigh = np.where(y > 0.5, 0.5 / max(1, (y > 0.5).sum()), 0.5 / max(1, (y <= 0.5).sum()))  # both classes count alike
    w, bias = np.zeros(_DIM), 0.0
    m, v = np.zeros(_DIM + 1), np.zeros(_DIM + 1)
    for t in range(1, 401):
        p = 1 / (1 + np.exp(-np.clip(np.bincount(row, val * w[col], y.size) + bias, -50, 50)))
        g = weigh * (p - y)
        grad = np.append(np.bincount(col, val * g[row], _DIM) + 1e-6 * w, g.sum())
        m, v = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad**2
        step = 0.1 * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-10)
        w, bias = w - step[:-1], bias - step[-1]
    return np.round(w, 9), round(float(bias), 9)


class QualityModel:
    """Posterior by pattern and the scorer, fitted on docs."""

    def __init__(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", sample: int = 4000, seed: int = 42, reject: float = 0.5):
        need(docs, id_col, text_col)
        src = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
        self.id_col, self.text_col, self.reject = id_col, text_col, reject
        self.counts = pattern_counts(src)
        self.post, self.theta = label_model(self.counts)
        self.weights, self.bias = fit_scorer(src, self.post, sample, seed)

    def _judge(self):
        post, weights, bias, reject = self.post, self.weights, self.bias, self.reject

        def judge(texts: list[bytes]):
            w = _Words(texts)
            doc, f = w.features()
            votes = w.votes()
            # per document and feature, so that the square root is of its share
            key, n = np.unique(np.repeat(doc, 2) * _DIM + f.ravel(), return_counts=True)
            of, col = key // _DIM, key % _DIM
            z = np.bincount(of, np.sqrt(n / np.maximum(w.n, 1)[of]) * weights[col], w.n.size) + bias
            score = 1 / (1 + np.exp(-np.clip(z, -50, 50)))
            kept = (score <= reject) | (w.n == 0)
            return w.n, ["".join(map(str, v)) for v in votes.tolist()], [post.get(tuple(v), 0.5) for v in votes.tolist()], score, kept

        return judge

    def score(self, docs: DataFrame) -> DataFrame:
        """One row per row of docs: doc_id, n_words, votes (a digit a labeller), posterior, score, kept."""
        judge = self._judge()

        def run(batches):
            for b in sliced(batches, "text", 2 << 20):
                n, votes, post, score, kept = judge(text_values(b.column("text")))
                yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(n.astype(np.int64)), pa.array(votes, pa.string()), pa.array(post, pa.float64()), pa.array(score), pa.array(kept)], ["doc_id", "n_words", "votes", "posterior", "score", "kept"])

        src = docs.select(F.col(self.id_col).cast("long").alias("id"), F.col(self.text_col).cast("string").alias("text"))
        return src.mapInArrow(tidy(run), "doc_id long, n_words long, votes string, posterior double, score double, kept boolean")

    def keep(self, docs: DataFrame) -> DataFrame:
        """The rows of docs that are kept, all columns."""
        judge, col = self._judge(), self.text_col

        def run(batches):
            for b in sliced(batches, col, 2 << 20):
                yield b.filter(pa.array(judge(text_values(b.column(col)))[-1]))

        return docs.mapInArrow(tidy(run), docs.schema)


def op10_quality_classifier(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return QualityModel(docs).score(docs).withColumns({"posterior": F.round("posterior", 6), "score": F.round("score", 6)})
