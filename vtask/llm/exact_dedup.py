"""Exact duplicates by compressed radix tries that own the smallest id of every text.

Texts, each white-space run replaced by one space, are dealt by their length
and a hash of their content; the trie of a part holds the full byte strings, so
equality is decided by bytes and not by the hash. A terminal node keeps the
smallest id and the number of rows. Every map task first inserts its own rows
into a trie of its own, so a text that a third of all rows share crosses the
network once a task. Where a task's tries outgrow its budget, the largest hands its heaviest
subtree, and whatever later belongs to it, to a further round in which subtrees
are dealt anew; these rows go through shared storage.

Defined cases: null equals the empty text; a null id is larger than all others;
rows that repeat an id together with its text are one row and share its
decision; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections import defaultdict

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vtask.llm.common import need, parts_for, settle, sliced, text_bytes, text_values, tidy

_BUDGET = 32 << 20  # bytes of text resident in a task's tries
_NODE = 500  # what a node costs besides its label


class RadixTrie:
    """Compressed byte trie. A node is [label, children by first byte, value]; a value is [smallest id, rows]."""

    def __init__(self):
        self.root = [b"", {}, None]
        self.size = 0

    def insert(self, text: bytes, low: int | None, rows: int) -> None:
        node, at = self.root, 0
        while True:
            if at == len(text):
                old = node[2]
                if old is None:
                    node[2] = [low, rows]
                else:
                    old[1] += rows
                    if old[0] is None or (low is not None and low < old[0]):
                        old[0] = low
                return
            child = node[1].get(text[at])
            if child is None:
                node[1][text[at]] = [text[at:], {}, [low, rows]]
                self.size += len(text) - at + _NODE
                return
            label = child[0]
            if not text.startswith(label, at):
                n = _common(label, text[at : at + len(label)])
                node[1][text[at]] = child = [label[:n], {label[n]: [label[n:], child[1], child[2]]}, None]
                self.size += _NODE
                label = child[0]
            node, at = child, at + len(label)

    @staticmethod
    def walk(node: list, path: bytes):
        """(text, smallest id, rows) of every terminal at or below node."""
        stack = [(node, path)]
        while stack:
            n, p = stack.pop()
            p += n[0]
            if n[2] is not None:
                yield p, *n[2]
            stack += [(c, p) for c in n[1].values()]

    def cut_heaviest(self) -> tuple[bytes, list]:
        """Take off the heaviest subtree below the first branching node: its path and its terminals."""
        node, path = self.root, b""
        while node[2] is None and len(node[1]) == 1:
            (node,) = node[1].values()
            path += node[0]
        if not node[1]:
            return b"", []
        weigh = {k: sum(len(t) for t, *_ in self.walk(c, b"")) for k, c in node[1].items()}
        key = max(weigh, key=weigh.get)
        child = node[1].pop(key)
        got = list(self.walk(child, path))
        self.size -= weigh[key]
        return path + bytes([key]), got


def _common(a: bytes, b: bytes) -> int:
    """Length of the common prefix, by halving."""
    low, high = 0, min(len(a), len(b))
    while low < high:
        mid = (low + high + 1) // 2
        if a[low:mid] == b[low:mid]:
            low = mid
        else:
            high = mid - 1
    return low


_REP = "part int, path binary, text binary, low long, rows long"
_NAMES = ["part", "path", "text", "low", "rows"]


def _reps(rows: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) or [()] * 5
    kinds = (pa.int32(), pa.binary(), pa.binary(), pa.int64(), pa.int64())
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], _NAMES)


def _pieces(rows, most: int):
    """Record batches of rows of at most about `most` bytes."""
    got, size = [], 0
    for r in rows:
        got.append(r)
        size += len(r[2]) + 64
        if size >= most:
            yield _reps(got)
            got, size = [], 0
    if got:
        yield _reps(got)


def _own(budget: int):
    """A map task's own rows, equal texts merged."""

    def own(batches):
        tries, size = defaultdict(RadixTrie), 0

        def out():
            for part, t in tries.items():
                for text, low, rows in t.walk(t.root, b""):
                    yield part, b"", text, low, rows

        for b in sliced(batches, "text", 4 << 20):
            for part, i, text in zip(b.column("part").to_pylist(), b.column("id").to_pylist(), text_values(b.column("text")), strict=True):
                t = tries[part]
                before = t.size
                t.insert(text, i, 1)
                size += t.size - before
            if size > budget:
                yield from _pieces(out(), 4 << 20)
                tries.clear()
                size = 0
        yield from _pieces(out(), 4 << 20)

    return own


def _owners(budget: int):
    """Tries of whole parts (or subtrees), within one budget for the task; path is null for finished texts and names the subtree of texts left for the next round."""

    def owners(batches):
        tries: dict = defaultdict(RadixTrie)
        cut: dict = defaultdict(list)
        held = 0
        for b in sliced(batches, "text", 4 << 20):
            for part, path, text, low, rows in zip(*(b.column(x).to_pylist() for x in _NAMES), strict=True):
                key = (part, path)
                gone = next((p for p in cut[key] if text.startswith(p)), None)
                if gone is not None:
                    yield from _pieces([(part, gone, text, low, rows)], 1)
                    continue
                t = tries[key]
                before = t.size
                t.insert(text, low, rows)
                held += t.size - before
                while held > budget:
                    key, t = max(tries.items(), key=lambda x: x[1].size)
                    before = t.size
                    gone, got = t.cut_heaviest()
                    if not got:  # one text is all there is
                        break
                    held += t.size - before
                    cut[key].append(gone)
                    yield from _pieces(((key[0], gone, *x) for x in got), 8 << 20)
        for (part, _), t in tries.items():
            yield from _pieces(((part, None, *x) for x in t.walk(t.root, b"")), 4 << 20)

    return owners


def text_owners(docs: DataFrame, parts: int, budget: int = _BUDGET) -> DataFrame:
    """(text_sha256, keep_id, group_size) of each distinct text of docs(id, text)."""
    dealt = F.pmod(F.xxhash64(F.octet_length("text"), F.xxhash64("text")), F.lit(parts)).cast("int")
    rows = docs.select(dealt.alias("part"), "id", "text").mapInArrow(tidy(_own(budget)), _REP).repartitionById(parts, "part")
    done = None
    while True:  # each round ends some texts of every trie and takes the others further down
        # finished texts shrink to their digest before they are written
        out = settle(rows.mapInArrow(tidy(_owners(budget)), _REP).select("part", "path", F.when(F.col("path").isNotNull(), F.col("text")).alias("text"), F.when(F.col("path").isNull(), F.sha2("text", 256)).alias("text_sha256"), "low", "rows"))
        got = out.filter("path IS NULL").select("text_sha256", F.col("low").alias("keep_id"), F.col("rows").alias("group_size"))
        done = got if done is None else done.unionAll(got)
        left = out.filter("path IS NOT NULL").select("part", "path", "text", "low", "rows")
        if left.isEmpty():
            return done
        rows = left.repartition(parts, "part", "path")


def normal_text(text_col: str) -> F.Column:
    return F.regexp_replace(F.coalesce(F.col(text_col).cast("string"), F.lit("")), r"[\x20\x09-\x0D]+", " ")


def normal_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("id"), normal_text(text_col).alias("text"))


def exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", budget: int = _BUDGET, part_bytes: int = 16 << 20) -> DataFrame:
    """One row per row of docs: doc_id, keep_id, group_size, kept, text_sha256 (of the normalised text)."""
    need(docs, id_col, text_col)
    src = normal_texts(docs, id_col, text_col)
    parts = parts_for(docs.sparkSession, text_bytes(docs, text_col), part_bytes)
    keyed = src.select(F.col("id").alias("doc_id"), F.sha2(F.col("text").cast("binary"), 256).alias("text_sha256"))
    return keyed.join(text_owners(src, parts, budget), "text_sha256").select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256")


def op9_exact_dedup(spark, sf_dir: str) -> DataFrame:
    return exact_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))


OP9_SQL = r"""
WITH d AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS t FROM documents)
SELECT doc_id, min(doc_id) OVER (PARTITION BY t) AS keep_id, count(*) OVER (PARTITION BY t) AS group_size,
    doc_id = min(doc_id) OVER (PARTITION BY t) AS kept, sha256(t) AS text_sha256 FROM d
"""
