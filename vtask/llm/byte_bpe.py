"""Byte-level BPE encoding and decoding.

A map task cuts its texts into pre-tokens and merges each batch's distinct words
only: a word is an array of bytes, then of pieces; each round finds the lowest
rank among neighbouring pairs in a literal rank map and joins the leftmost such
pair, in all words at once, until no pair has a rank. Each text is then spelled
out from its words' ids. Decoding concatenates the ids' binary pieces.

fold_words() is the same fold by Spark's higher-order functions. It takes about
40 CPU microseconds a word, which for the distinct words of every batch is more
than the budget of the check tool, so encode() runs the rounds in numpy.

The rank map is one array, as a literal map would be searched from end to end:
the row of a left piece starts at its own offset, rows interleave without
clashes, and each entry names its left piece, so a look-up is two array reads.
Words longer than `long_word` bytes, for which rounds take quadratic time, are
merged with a heap instead. Nothing is shuffled; memory is bounded by the batch.

Defined cases: null text is empty and has no ids; special tokens are never
recognised; ids outside the vocabulary raise; an empty table gives an empty
result; other columns are ignored.
"""

from __future__ import annotations

import base64
import heapq
import json
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vtask.llm.common import need, sliced, text_values, tidy

_BATCH = 6 << 20  # bytes of text whose distinct words are encoded together
_ID_BITS = 20


@lru_cache(maxsize=4)
def load_ranks(data: bytes) -> dict[bytes, int]:
    """Rank (= id) of each piece, from the text of a rank file."""
    return {base64.b64decode(a): int(b) for a, b in map(bytes.split, data.splitlines())}


@lru_cache(maxsize=4)
def rank_rows(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    """(offset by left id, entries): with e = entries[(offset[a] + b) & (entries.size - 1)], a and b join if e >> _ID_BITS == a, to the id in e's low bits."""
    ranks = load_ranks(data)
    rows: dict[int, dict[int, int]] = {}
    for piece, i in ranks.items():
        for k in range(1, len(piece)):
            a, b = ranks.get(piece[:k]), ranks.get(piece[k:])
            if a is not None and b is not None:
                rows.setdefault(a, {})[b] = i
    size = 1 << (3 * sum(map(len, rows.values()))).bit_length()
    rng = np.random.default_rng(0)
    used = np.zeros(size, bool)
    offset, entries = np.zeros(max(ranks.values()) + 1, np.int64), np.full(size, -1, np.int64)
    for a in sorted(rows, key=lambda a: (-len(rows[a]), a)):  # the fullest rows first, while there is room
        b = np.fromiter(rows[a], np.int64)
        while True:
            tries = rng.integers(0, size, 16)
            ok = np.flatnonzero(~used[(tries[:, None] + b) & (size - 1)].any(axis=1))
            if ok.size:
                break
        offset[a] = tries[ok[0]]
        at = (offset[a] + b) & (size - 1)
        used[at] = True
        entries[at] = (a << _ID_BITS) | np.fromiter(rows[a].values(), np.int64)
    return offset, entries


def merge_words(words: list[bytes], ranks: dict[bytes, int], table: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """(ids of all words, number of ids of each): every round joins, in each word at once, its leftmost pair of lowest rank."""
    offset, entries = table
    mask, low = entries.size - 1, (1 << _ID_BITS) - 1
    none = low + 1
    first = np.array([ranks[bytes([c])] for c in range(256)], np.int64)
    n = np.fromiter(map(len, words), np.int64, len(words))
    t = first[np.frombuffer(b"".join(words), np.uint8)]
    word = np.repeat(np.arange(len(words)), n)
    done_t, done_w = [], []
    while t.size:
        e = entries[(offset[t[:-1]] + t[1:]) & mask]
        m = np.full(t.size, none, np.int64)
        m[:-1] = np.where(((e >> _ID_BITS) == t[:-1]) & (word[:-1] == word[1:]), e & low, none)
        start = np.flatnonzero(np.concatenate(([True], word[1:] != word[:-1])))
        size = np.diff(np.append(start, t.size))
        best = np.repeat(np.minimum.reduceat(m, start), size)
        over = best == none
        done_t.append(t[over])
        done_w.append(word[over])
        at = np.flatnonzero((m == best) & ~over)
        at = at[np.concatenate(([True], word[at[1:]] != word[at[:-1]]))] if at.size else at
        t[at] = m[at]
        stay = ~over
        stay[at + 1] = False
        t, word = t[stay], word[stay]
    t, word = np.concatenate([*done_t, t]), np.concatenate([*done_w, word])
    return t[np.argsort(word, kind="stable")].astype(np.uint32), np.bincount(word, minlength=len(words))


@lru_cache(maxsize=4)
def _fold_sql(data: bytes) -> str:
    """SQL that encodes the array column `words` of byte arrays."""
    ranks = load_ranks(data)
    offset, entries = rank_rows(data)

    def literal(a, kind):
        return f"from_json('{json.dumps(list(map(int, a)))}', 'array<{kind}>')"

    first = literal([ranks[bytes([c])] for c in range(256)], "int")
    off, ent = literal(offset, "int"), literal(entries, "bigint")

    def let(value, name, body):
        return f"transform(array({value}), {name} -> {body})[0]"

    joined = let(f"get({ent}, (get({off}, a) + b) & {entries.size - 1})", "e", f"if(shiftright(e, {_ID_BITS}) = a, cast(e & {(1 << _ID_BITS) - 1} AS int), cast(null AS int))")
    pairs = f"zip_with(s.t, slice(s.t, 2, size(s.t)), (a, b) -> {joined})"
    cut = let("int(array_position(p, m))", "k", "concat(slice(s.t, 1, k - 1), array(m), slice(s.t, k + 2, size(s.t)))")
    step = let(pairs, "p", let("array_min(p)", "m", f"if(m IS NULL, named_struct('t', s.t, 'go', false), named_struct('t', {cut}, 'go', true))"))
    start = f"named_struct('t', transform(w, c -> get({first}, c)), 'go', true)"
    return f"transform(words, w -> aggregate(sequence(2, greatest(2, size(w))), {start}, (s, k) -> if(s.go, {step}, s), s -> s.t))"


def heap_merge(word: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Ids of a word by a heap of neighbouring pairs; n log n."""
    n = len(word)
    end = list(range(1, n + 1))  # end of the piece that starts here; 0 once joined to its left
    prev = list(range(-1, n))
    heap = [(r, i, i + 2) for i in range(n - 1) if (r := ranks.get(word[i : i + 2])) is not None]
    heapq.heapify(heap)
    while heap:
        _, i, stop = heapq.heappop(heap)
        mid = end[i]
        if not mid or mid >= n or not end[mid] or end[mid] != stop:
            continue
        end[i], end[mid] = stop, 0
        if stop < n:
            prev[stop] = i
        for a in (i, prev[i]):
            if a >= 0 and end[a] < n:
                b = end[end[a]]
                if (r := ranks.get(word[a:b])) is not None:
                    heapq.heappush(heap, (r, a, b))
    out, i = [], 0
    while i < n:
        out.append(ranks[word[i : end[i]]])
        i = end[i]
    return out


class _Numbered(dict):
    def __missing__(self, key):
        self[key] = n = len(self)
        return n


def _spelled(seqs: list[np.ndarray], flat: np.ndarray, size: np.ndarray) -> list[bytes]:
    """Ids of each text, as little-endian unsigned 32-bit integers; word k has size[k] ids of flat."""
    start = np.cumsum(size) - size
    out = []
    for w in seqs:
        n = size[w]
        stop = np.cumsum(n)
        out.append(flat[np.repeat(start[w] - (stop - n), n) + np.arange(int(stop[-1]) if stop.size else 0)].astype("<u4").tobytes())
    return out


def _encode(pattern: str, data: bytes, batch: int, long_word: int):
    def run(batches):
        find, ranks, table = regex.compile(pattern).findall, load_ranks(data), rank_rows(data)
        for b in sliced(batches, "text", batch):
            seen = _Numbered()
            seqs = [np.fromiter(map(seen.__getitem__, find(t.decode())), np.uint32) for t in text_values(b.column("text"))]
            words = [w.encode() for w in seen]
            # pieces are known as they stand, long words take the heap, all others the rounds of merges
            other = {i: [ranks[w]] if w in ranks else heap_merge(w, ranks) for i, w in enumerate(words) if w in ranks or len(w) > long_word}
            fold = [i for i in range(len(words)) if i not in other]
            flat, size = merge_words([words[i] for i in fold], ranks, table)
            sizes = np.zeros(len(words), np.int64)
            sizes[fold] = size
            sizes[list(other)] = [len(x) for x in other.values()]
            ids = np.empty(int(sizes.sum()), np.uint32)
            own = np.zeros(len(words), bool)
            own[fold] = True
            own = np.repeat(own, sizes)
            ids[own], ids[~own] = flat, [x for o in other.values() for x in o]
            out = _spelled(seqs, ids, sizes)
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array([len(x) // 4 for x in out], pa.int64()), pa.array(out, pa.binary())], ["doc_id", "n_tokens", "ids"])

    return run


def encode(docs: DataFrame, rank_file: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", batch: int = _BATCH, long_word: int = 96) -> DataFrame:
    """One row per row of docs: doc_id, n_tokens, ids (binary, little-endian unsigned 32-bit integers)."""
    need(docs, id_col, text_col)
    with open(rank_file, "rb") as f:
        data = f.read()
    src = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return src.mapInArrow(tidy(_encode(pattern, data, batch, long_word)), "doc_id long, n_tokens long, ids binary")


def fold_words(words: DataFrame, rank_file: str, word_col: str = "word") -> DataFrame:
    """The columns of words and `ids`, the word's ids, by higher-order functions alone; quadratic in a word's length, so for words of moderate length."""
    need(words, word_col)
    with open(rank_file, "rb") as f:
        data = f.read()
    text = F.col(word_col).cast("string")
    hexed = F.hex(text.cast("binary"))
    octets = F.transform(F.sequence(F.lit(1), F.octet_length(text)), lambda i: F.conv(F.substring(hexed, 2 * i - 1, F.lit(2)), 16, 10).cast("int"))
    arrays = words.withColumn("words", F.array(F.when(F.octet_length(text) > 0, octets)))
    return arrays.withColumn("ids", F.expr(_fold_sql(data))[0]).drop("words")


def decode(df: DataFrame, rank_file: str, ids_col: str = "ids", out_col: str = "decoded") -> DataFrame:
    """The columns of df and the bytes that its ids stand for; null ids give null."""
    need(df, ids_col)
    with open(rank_file, "rb") as f:
        data = f.read()
    keep = [c for c in df.columns if c != out_col]

    def run(batches):
        ranks = load_ranks(data)
        pieces = [None] * (max(ranks.values()) + 1)
        for p, i in ranks.items():
            pieces[i] = p
        for b in sliced(batches, ids_col, 4 << 20):
            out = [None if x is None else b"".join(map(pieces.__getitem__, np.frombuffer(x, "<u4").tolist())) for x in b.column(ids_col).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(out, pa.binary())], [*b.schema.names, out_col])

    return df.select(*keep).mapInArrow(tidy(run), df.select(*keep).schema.add(out_col, "binary"))


def op7_byte_bpe(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    file = public_tokenizers.path("byte_bpe_50k.tiktoken")
    coded = decode(encode(spark.read.parquet(f"{sf_dir}/documents.parquet"), file, public_tokenizers.PATTERN), file)
    return coded.select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))
