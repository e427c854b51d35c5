"""Token counts that follow edits.

A document's pre-tokens sit in the leaves of a segment tree whose nodes hold the
sums of characters and of tokens below them. An edit descends by characters to
the leaf it begins in, re-encodes from the last pre-token it cannot touch until
a new boundary falls on an old one behind the edit, puts the new pre-tokens in
place of the old and updates the sums on the way up. What the pattern's matches
look at decides how far back that is: a match sees two characters past its end
at most, so pre-tokens that end two or more characters before an edit stay.

Map-only: a document and its edits are one row. Defined cases: null text is
empty; null edits are none; positions are characters, beyond the end they mean
the end; a start behind its end is an insertion at the start; edits apply in
turn to the text as edited so far; an empty table gives an empty result; other
columns are ignored.
"""

from __future__ import annotations

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vtask.llm.byte_bpe import heap_merge, load_ranks
from vtask.llm.common import need, sliced, tidy

_LEAF = 64
_LOOK = 2
_EDITS = "array<struct<start:long,end:long,text:string>>"


class PieceCounter:
    """Tokens of a pre-token, remembered for common ones."""

    def __init__(self, data: bytes, most: int = 400_000):
        self.ranks, self.most, self.known = load_ranks(data), most, {}

    def __call__(self, piece: str) -> int:
        n = self.known.get(piece)
        if n is None:
            b = piece.encode()
            n = 1 if b in self.ranks else len(heap_merge(b, self.ranks))
            if len(self.known) < self.most and len(b) <= 40:
                self.known[piece] = n
        return n


class EditTree:
    """Segment tree over a document's pre-tokens."""

    def __init__(self, text: str, split, count):
        self.split, self.count, self.encoded = split, count, 0
        self._build(split.findall(text))
        self.encoded = 0

    def _build(self, pieces: list[str]) -> None:
        self.leaves = [pieces[i : i + _LEAF] for i in range(0, len(pieces), _LEAF)] or [[]]
        n = 1
        while n < len(self.leaves):
            n *= 2
        self.n = n
        self.chars, self.tokens = [0] * (2 * n), [0] * (2 * n)
        for i, leaf in enumerate(self.leaves):
            self.chars[n + i], self.tokens[n + i] = sum(map(len, leaf)), sum(map(self.count, leaf))
        for k in range(n - 1, 0, -1):
            self._sum(k)

    def _sum(self, k: int) -> None:
        self.chars[k] = self.chars[2 * k] + self.chars[2 * k + 1]
        self.tokens[k] = self.tokens[2 * k] + self.tokens[2 * k + 1]

    @property
    def total(self) -> int:
        return self.tokens[1]

    def text(self) -> str:
        return "".join(p for leaf in self.leaves for p in leaf)

    def _set(self, i: int, leaf: list[str]) -> None:
        self.leaves[i] = leaf
        k = self.n + i
        self.chars[k], self.tokens[k] = sum(map(len, leaf)), sum(map(self.count, leaf))
        while k > 1:
            k //= 2
            self._sum(k)

    def _find(self, at: int) -> tuple[int, int]:
        """Leaf that holds character `at` (the last one at the end) and the characters before the leaf."""
        k, before = 1, 0
        while k < self.n:
            k *= 2
            if at - before >= self.chars[k] and self.chars[k + 1]:
                before += self.chars[k]
                k += 1
        return min(k - self.n, len(self.leaves) - 1), before

    def edit(self, start: int, end: int, new: str) -> None:
        size = self.chars[1]
        start = min(max(start, 0), size)
        end = min(max(end, start), size)
        i, before = self._find(max(start - _LOOK, 0))
        leaf, j, pos = self.leaves[i], 0, before
        while j < len(leaf) and pos + len(leaf[j]) + _LOOK <= start:
            pos += len(leaf[j])
            j += 1
        head = leaf[:j]  # untouched pre-tokens of the first leaf
        # old pieces from here on, until the boundaries meet
        shift = len(new) - (end - start)
        buf, old_ends, k, at = "", [], i, pos
        pieces, sure = leaf[j:], False
        fresh: list[str] = []
        done = pos  # in new coordinates
        while True:
            while at < end + _LOOK or not old_ends or len(old_ends) < 8:  # some old text behind the edit
                if not pieces:
                    if k + 1 >= len(self.leaves):
                        sure = True
                        break
                    k += 1
                    pieces = self.leaves[k]
                    continue
                for p in pieces:
                    buf += p
                    at += len(p)
                    old_ends.append(at)
                pieces = []
            line = buf[: start - pos] + new + buf[end - pos :]
            meet = {e + shift for e in old_ends if e >= end}
            fresh, done, met = [], pos, False
            for m in self.split.finditer(line):
                piece = m[0]
                stop = pos + m.end()
                if not sure and m.end() + _LOOK > len(line):
                    break  # the match may look past the text at hand
                fresh.append(piece)
                done = stop
                if stop in meet:
                    met = True
                    break
            if met or sure:
                break
            old_ends = old_ends[-1:]
            n = len(buf)
            while pieces == [] and k + 1 < len(self.leaves) and len(buf) < 2 * n + 64:  # double the text at hand
                k += 1
                for p in self.leaves[k]:
                    buf += p
                    at += len(p)
                    old_ends.append(at)
            if k + 1 >= len(self.leaves):
                sure = True
        self.encoded += len(fresh)
        # old pre-tokens behind the meeting point stay, in the last leaf read
        rest, p = [], before + sum(map(len, head))
        stop_old = done - shift
        for q in range(i, k + 1):
            for piece in self.leaves[q] if q > i else leaf[j:]:
                if p >= stop_old:
                    rest.append(piece)
                p += len(piece)
        for q in range(i + 1, k + 1):
            self._set(q, [])
        self._set(i, head + fresh + rest)
        if len(self.leaves[i]) > 8 * _LEAF:
            self._build([p for x in self.leaves for p in x])


def count_after_edits(docs: DataFrame, rank_file: str, pattern: str, edits: F.Column, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs: doc_id, n_tokens, n_edits, n_tokens_after, n_reencoded (pre-tokens encoded anew), text_after.

    edits is an expression over docs, an array of (start, end, text).
    """
    need(docs, id_col, text_col)
    with open(rank_file, "rb") as f:
        data = f.read()

    def run(batches):
        split, count = regex.compile(pattern), PieceCounter(data)
        for b in sliced(batches, "text", 4 << 20):
            rows = []
            for i, text, todo in zip(b.column("id").to_pylist(), b.column("text").to_pylist(), b.column("edits").to_pylist(), strict=True):
                t = EditTree(text or "", split, count)
                n, todo = t.total, todo or []
                for e in todo:
                    t.edit(e["start"] or 0, e["end"] or 0, e["text"] or "")
                rows.append((i, n, len(todo), t.total, t.encoded, t.text()))
            kinds = [pa.int64()] * 5 + [pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], ["doc_id", "n_tokens", "n_edits", "n_tokens_after", "n_reencoded", "text_after"])

    src = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"), edits.cast(_EDITS).alias("edits"))
    return src.mapInArrow(tidy(run), "doc_id long, n_tokens long, n_edits long, n_tokens_after long, n_reencoded long, text_after string")


def seeded_edits(id_col: str, text_col: str, n: int = 4, seed: int = 42) -> F.Column:
    """A stated set of edits: n a document, at hashed places, in turn a replacement, an insertion and a deletion."""
    size = F.coalesce(F.length(F.col(text_col).cast("string")), F.lit(0)) + 1
    out = []
    for k in range(n):
        at = F.pmod(F.xxhash64(F.lit(seed), F.lit(k), F.col(id_col).cast("long")), size)
        long = (12, 0, 9)[k % 3]
        text = (F.concat(F.lit(" edit "), F.coalesce(F.col(id_col).cast("string"), F.lit("none"))), F.lit("ing, the"), F.lit(""))[k % 3]
        out.append(F.struct(at.cast("long").alias("start"), (at + long).cast("long").alias("end"), text.alias("text")))
    return F.array(*out)


def op4_edit_token_counts(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    out = count_after_edits(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, seeded_edits("doc_id", "text"))
    return out.select("doc_id", "n_tokens", "n_edits", "n_tokens_after", "n_reencoded", F.sha2(F.col("text_after").cast("binary"), 256).alias("after_sha256"))
