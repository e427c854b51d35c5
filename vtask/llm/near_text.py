"""Near copies by the Jaccard similarity of word shingles: SimHash links first, the rest found whole, all verified.

A text, A-Z lower-cased, is the set of hashes of its runs of `size` words; two
texts are linked if the sets' Jaccard similarity is 0.8 or more, and linked
texts form components.

Search: fingerprints of the same shingles that the BK-trees of `simhash` link
within its radius give the first candidates, and texts that these join, once
verified, are not held against each other again: large groups of near copies end
here. Texts so alike can differ in more bits than any radius that can be
searched, so shingles find the links that are left: two sets
so alike share one of the first n - ceil(0.8 n) + 1 elements of each, in any
order that is the same for all sets. The order is by the number of texts that
have a shingle, rarest first; shingles of one text alone fill a prefix without
ever matching, so a text without near copies mostly hands on nothing, and a line
that most texts have comes last. No link is lost.

Candidates: texts under a shared element are first held against the smallest of
them, which joins a large group by a row a member; only pairs that are in
different components after that are held against each other. The join that makes
pairs lets through only those whose sets can be alike enough: their differences
are at least the shingles that no other text has, and the bits in which parity
maps of the shared ones differ. Every pair let through is verified.

Defined cases: fewer words than a shingle hash as one shingle, and so does no
word or a null text; rows with equal id and text are one text.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vtask.llm.common import Docs, connected_components, mix64, need, settle, sliced, text_values, tidy
from vtask.llm.pii import _BITS, _bitmap
from vtask.llm.simhash import fingerprints, near_components

_MAPS = 8  # longs of a parity map
_PREFIX = 128  # of shingles before one, that are looked through for an earlier match


def shingle_sets(texts: list[bytes], size: int) -> tuple[np.ndarray, np.ndarray]:
    """(document, shingle hash) of each distinct shingle of each text, by document and hash."""
    d = Docs([t.lower() for t in texts])
    h = d.hashes()
    w, whole = d.windows(h, size)
    at = np.flatnonzero(whole)
    n = np.diff(d.word_at)
    few = np.flatnonzero(n < size)
    short = np.zeros(few.size, np.uint64)
    for j in range(size - 1):
        has = n[few] > j
        short[has] = mix64(short[has] * np.uint64(0xD6E8FEB86659FD93) + h[d.word_at[few[has]] + j])
    doc, h = np.concatenate([d.doc[at], few]), np.concatenate([w[at], short])
    order = np.lexsort((h, doc))
    doc, h = doc[order], h[order]
    new = np.ones(h.size, bool)
    new[1:] = (doc[1:] != doc[:-1]) | (h[1:] != h[:-1])
    return doc[new], h[new]


def _counts(size: int):
    def run(batches):
        for b in sliced(batches, "text", 2 << 20):
            h, n = np.unique(shingle_sets(text_values(b.column("text")), size)[1], return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(n.astype(np.int64))], ["h", "df"])

    return run


def _shared(size: int, bitmap: bytes):
    def run(batches):
        bits = np.frombuffer(bitmap, np.uint8)
        for b in sliced(batches, "text", 2 << 20):
            doc, h = shingle_sets(text_values(b.column("text")), size)
            n = np.bincount(doc, minlength=b.num_rows)
            slot = h & np.uint64(_BITS - 1)
            sel = (bits[(slot >> np.uint64(3)).astype(np.int64)] >> (slot & np.uint64(7)).astype(np.uint8)) & 1 > 0
            doc, h = doc[sel], h[sel]
            node = np.asarray(b.column("node"))
            yield pa.RecordBatch.from_arrays([pa.array(node[doc]), pa.array(n[doc]), pa.array(h.view(np.int64))], ["node", "n", "h"])

    return run


def _verified(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The pairs (a, b) whose sets have a Jaccard similarity of 0.8 or more, by shared shingles: others are in one text only."""
    x = sets.select(F.col("node").alias("a"), F.col("n").alias("na"), F.col("hs").alias("ha"))
    y = sets.select(F.col("node").alias("b"), F.col("n").alias("nb"), F.col("hs").alias("hb"))
    both = F.size(F.array_intersect("ha", "hb"))
    return pairs.join(x, "a").join(y, "b").filter(9 * both >= 4 * (F.col("na") + F.col("nb"))).select("a", "b")


def near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 5) -> DataFrame:
    """(node, comp) of the texts that have a near copy; node_of() gives the node of a row."""
    need(docs, id_col, text_col)
    src = docs.select(node_of(id_col, text_col).alias("node"), F.col(text_col).cast("string").alias("text"))
    counts = src.select("text").mapInArrow(tidy(_counts(size)), "h long, df long").groupBy("h").agg(F.sum("df").alias("df"))
    common = settle(counts.filter("df > 1"))
    rows = src.mapInArrow(tidy(_shared(size, _bitmap(common.select(F.col("h").alias("term"))))), "node long, n long, h long").join(common, "h")
    # equal rows give equal shingles twice, so a set is made of them
    sets = rows.groupBy("node", "n").agg(F.array_sort(F.collect_set(F.struct("df", "h"))).alias("x"))
    lead = F.expr("n - cast(ceil(4 * n / 5) AS long) + 1 - (n - size(x))")

    def parity(k):
        own = F.filter("hs", lambda h: F.shiftrightunsigned(h, 6).bitwiseAND(F.lit(_MAPS - 1)) == k)
        return F.aggregate(own, F.lit(0).cast("long"), lambda m, h: m.bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), h.bitwiseAND(F.lit(63)).cast("int"))))

    sets = settle(sets.select("node", "n", F.col("x.h").alias("hs"), lead.cast("int").alias("lead")).select("*", F.array(*map(parity, range(_MAPS))).alias("map")))
    spread = F.posexplode(F.slice("hs", F.lit(1), F.col("lead"))).alias("place", "h")
    # the text with the fewest shingles of its own comes first, as it is alike to most
    near = near_components(settle(fingerprints(src, "node", "text", size)))
    likely = near.filter("id <> component_id").select(F.col("component_id").alias("a"), F.col("id").alias("b"))
    linked = settle(_verified(likely.distinct(), sets))
    tied = sets.filter("lead > 0").join(connected_components(linked), "node", "left").withColumns({"alone": F.col("n") - F.size("hs"), "of": F.coalesce("comp", "node")})
    keys = settle(tied.select(F.struct("alone", "node", "n", "map", "of").alias("t"), spread))

    def can_be_alike(a, b):
        bits = sum((F.bit_count(a["map"][k].bitwiseXOR(b["map"][k])) for k in range(_MAPS)), a["alone"] + b["alone"])
        return (9 * bits <= a["n"] + b["n"]) & (5 * a["n"] >= 4 * b["n"]) & (5 * b["n"] >= 4 * a["n"])

    first = keys.groupBy("h").agg(F.min("t").alias("a"), F.max("t").alias("z")).filter("a.node <> z.node").select(F.col("h").alias("g"), "a")
    b = keys.select(F.col("t").alias("b"), "h")
    stars = b.join(first, (F.col("h") == F.col("g")) & (F.col("a.of") != F.col("b.of")) & can_be_alike(F.col("a"), F.col("b"))).select(F.col("a.node").alias("a"), F.col("b.node").alias("b"))
    links = settle(linked.unionAll(_verified(stars.distinct(), sets)))
    comp = connected_components(links)
    named = keys.join(comp, F.col("t.node") == F.col("node"), "left").select("t", "place", "h", F.coalesce("comp", "t.node").alias("comp"))
    apart = named.groupBy("h").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).filter("lo < hi").select("h")
    # a pair is made under the first shingle that both prefixes have, as far as these are looked through
    before = F.when(F.col("place") <= _PREFIX, F.slice("hs", F.lit(1), F.col("place"))).otherwise(F.array().cast("array<bigint>"))
    open_ = named.join(apart, "h", "left_semi").join(sets.select("node", "hs"), F.col("t.node") == F.col("node"))
    open_ = settle(open_.select("t", "h", "comp", before.alias("before")))
    a = open_.select("h", F.col("t").alias("a"), F.col("comp").alias("ca"), F.col("before").alias("pa"))
    b = open_.select(F.col("h").alias("g"), F.col("t").alias("b"), F.col("comp").alias("cb"), F.col("before").alias("pb"))
    cross = a.join(b, (F.col("h") == F.col("g")) & (F.col("a.node") < F.col("b.node")) & (F.col("ca") != F.col("cb")) & can_be_alike(F.col("a"), F.col("b")) & ~F.arrays_overlap("pa", "pb"))
    more = settle(_verified(cross.select(F.col("a.node").alias("a"), F.col("b.node").alias("b")).distinct(), sets))
    return connected_components(links.unionAll(more)) if more.head(1) else comp


def node_of(id_col: str, text_col: str):
    return F.xxhash64(F.col(id_col).cast("long"), F.col(text_col).cast("string"))


def first_of_near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs without the rows that have a near copy of smaller id in their component; a null id is the largest."""
    comp = settle(near_copies(docs, id_col, text_col))
    ids = docs.select(node_of(id_col, text_col).alias("node"), F.col(id_col).cast("long").alias("id")).join(comp, "node")
    rank = F.struct(F.col("id").isNull().alias("none"), "id", "node")
    low = ids.groupBy("comp").agg(F.min(rank).alias("low"))
    gone = settle(comp.join(low, "comp").filter(F.col("node") != F.col("low.node")).select(F.col("node").alias("__node")))
    return docs.join(gone, node_of(id_col, text_col) == F.col("__node"), "left_anti")
