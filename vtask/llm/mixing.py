"""Mixing sources to target weights by subset-sum budget fitting.

Sizes are word counts. Sources in code-point order, null last, take the weights
in turn; their targets share the corpus by weight, but none exceeds `cap` times
its source: with caps, the shares are min(cap * size, level * weight) for one
common level, which a running sum over the sources in order of size / weight
finds.

Each source takes every document `base` times and fills the rest of its target
from a histogram of exact lengths: the same share of each length first, then
single documents by largest remainder, then a bounded-knapsack dynamic program
over the lengths left, which ends at the reachable sum nearest to the target. A
length's documents are taken in seeded hash order up to a cut, found from counts
of hash buckets, so no length's documents gather in one task.

Movement of data: (id, source, size) rows only; text is read once. One row a
source is sorted in one task (with spill); a source's histogram has a row a
distinct length.

Rows that repeat an id at one size of a source are told apart by `tie`, a number
whose bits from the 34th on name a group of rows small enough for one task; such
rows are alike in the result, so reruns agree whichever of them is taken.

Defined cases: null text has size 0; null source is a source; null ids repeat
like any other; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vtask.llm.common import WORD, need, settle

_DP_WORDS = 1 << 16  # what is left to the dynamic program, in words
_DP_MOST = 1 << 25  # its largest table


def word_count(text_col: str) -> F.Column:
    return F.coalesce(F.regexp_count(F.col(text_col).cast("string"), F.lit(WORD)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[float, ...] = (1, 2, 3), cap: float = 3) -> DataFrame:
    """(source, source_size, rank, target) from sizes(source, source_size), one row a source."""
    order = Window.orderBy(F.col("source").asc_nulls_last())
    w = F.element_at(F.array(*(F.lit(float(x)) for x in weights)), F.pmod(F.col("rank"), F.lit(len(weights))).cast("int") + 1)
    s = sizes.select("source", "source_size", (F.row_number().over(order) - 1).alias("rank")).withColumn("w", w)
    s = s.withColumn("top", F.lit(float(cap)) * F.col("source_size"))
    before = Window.orderBy((F.col("top") / F.col("w")).asc(), "rank").rowsBetween(Window.unboundedPreceding, -1)
    every = Window.partitionBy(F.lit(0))
    s = s.select("*", F.sum("source_size").over(every).alias("total"), F.sum("w").over(every).alias("ws"), F.coalesce(F.sum("top").over(before), F.lit(0.0)).alias("below"), F.coalesce(F.sum("w").over(before), F.lit(0.0)).alias("wbelow"))
    # sources up to here are capped if they stop below the level that the others would have
    capped = F.col("top") * (F.col("ws") - F.col("wbelow")) <= (F.col("total") - F.col("below")) * F.col("w")
    s = s.withColumn("capped", capped)
    level = (F.col("total") - F.sum(F.when(F.col("capped"), F.col("top")).otherwise(0.0)).over(every)) / F.sum(F.when(F.col("capped"), 0.0).otherwise(F.col("w"))).over(every)
    return s.withColumn("level", level).select("source", "source_size", "rank", F.when(F.col("capped"), F.col("top")).otherwise(F.col("level") * F.col("w")).alias("target"))


def fit_budget(size: np.ndarray, n: np.ndarray, target: float) -> tuple[int, np.ndarray]:
    """How often every document is taken, and of how many documents of each size one more copy is."""
    total = int((size * n).sum())
    extra = np.zeros(size.size, np.int64)
    if not total or target <= 0:
        return 0, extra
    base = int(target // total)
    rest = target - base * total
    share = rest / total * n
    extra = np.where(size > 0, np.floor(share), 0).astype(np.int64)
    left = rest - float((size * extra).sum())
    for i in np.lexsort((size, -(share - extra))):  # single documents, largest remainder first
        if left <= _DP_WORDS:
            break
        if 0 < size[i] <= left and extra[i] < n[i]:
            extra[i] += 1
            left -= size[i]
    for i in np.argsort(-size, kind="stable"):  # whatever one of each length could not hold
        if left <= _DP_WORDS:
            break
        if 0 < size[i] <= left:
            k = min(int(left // size[i]), int(n[i] - extra[i]))
            extra[i] += k
            left -= float(size[i] * k)
    best = None
    for room in (0, _DP_WORDS >> 6, _DP_WORDS >> 3, _DP_WORDS):  # more is given back to the program as long as it finds no exact sum
        kept, free = extra.copy(), left
        for i in np.argsort(size, kind="stable"):
            if size[i] > 0 and free < room:
                k = min(int(kept[i]), int((room - free) // size[i]) + 1)
                kept[i] -= k
                free += float(size[i] * k)
        got = kept + _knapsack(size, n - kept, free)
        off = abs(float((size * got).sum()) - rest)
        if best is None or off < best[0]:
            best = off, got
        if best[0] <= 0.5:
            break
    return base, best[1]


def _knapsack(size: np.ndarray, n: np.ndarray, left: float) -> np.ndarray:
    """Bounded knapsack: counts whose sum of sizes is as near to left as can be (the smaller of two as near)."""
    out = np.zeros(size.size, np.int64)
    free = np.flatnonzero((n > 0) & (size > 0))
    if not free.size or left < 0.5:
        return out
    top = int(left) + int(size[free].min())
    if top > _DP_MOST:  # every document left is longer than any table: one or none
        i = free[np.argmin(size[free])]
        out[i] = abs(size[i] - left) < left
        return out
    first = np.full(top + 1, -1, np.int64)  # the item that first reaches a sum
    reach = np.zeros(top + 1, bool)
    reach[0] = True
    items = []
    goal = round(left)
    for i in free[np.argsort(-size[free], kind="stable")]:
        some, k = min(int(n[i]), top // int(size[i])), 1
        while some > 0:
            k = min(k, some)
            w = k * int(size[i])
            new = reach[: top + 1 - w] & ~reach[w:]
            first[w:][new] = len(items)
            reach[w:] |= new
            items.append((i, k, w))
            some -= k
            k *= 2
        if reach[goal]:
            break
    sums = np.flatnonzero(reach)
    s = int(sums[np.argmin(np.abs(sums - left))])
    while s:
        i, k, w = items[first[s]]
        out[i] += k
        s -= w
    return out


def _fit(pdf: pd.DataFrame) -> pd.DataFrame:
    pdf = pdf.sort_values("size")
    base, extra = fit_budget(pdf["size"].to_numpy(), pdf["n"].to_numpy(), float(pdf["target"].iloc[0]))
    return pd.DataFrame({"rank": pdf["rank"], "size": pdf["size"], "n": pdf["n"], "base": base, "extra": extra})


def mix_plan(sized: DataFrame, weights: tuple[float, ...] = (1, 2, 3), cap: float = 3, seed: int = 42) -> DataFrame:
    """A row a (source, size) of sized(id, source, size, tie): how often its documents are taken, and the cut in hash order up to which they are taken once more."""
    hist = settle(sized.groupBy("source", "size").agg(F.count("*").alias("n")))
    src = settle(source_targets(hist.groupBy("source").agg(F.sum(F.col("size") * F.col("n")).alias("source_size")), weights, cap))
    ranked = _beside(hist, src, ["source"]).select("rank", "size", "n", "target")
    fit = ranked.groupBy("rank").applyInPandas(_fit, "rank long, size long, n long, base long, extra long")
    plan = settle(fit.join(src, "rank").select("source", "size", "n", "source_size", "target", "base", "extra", F.ceil(F.sqrt("n")).alias("buckets")))
    # the cut: the bucket in which the last document taken lies, its place among the ids there, then among rows that repeat the id
    some = plan.filter("extra > 0 AND extra < n").select("source", "size", "extra", "buckets")
    rows = _beside(sized, some, ["source", "size"]).select("source", "size", "id", "tie", "extra", "buckets", hash_key(seed).alias("h")).withColumn("b", F.pmod("h", "buckets"))
    count = rows.groupBy("source", "size", "b", "extra").agg(F.count("*").alias("c"))
    last = _reached(count, ["b"], "extra").select("source", "size", "b", "place")
    ids = _beside(rows, last, ["source", "size", "b"]).groupBy("source", "size", "b", "h", "id", "place").agg(F.count("*").alias("c"))
    at = settle(_reached(ids, ["h", "id"], "place").select("source", "size", "b", "h", "id", "place", "c"))
    tied = _beside(sized, at.filter("place < c").select("source", "size", "id", "place"), ["source", "size", "id"]).withColumn("task", F.shiftrightunsigned("tie", 33))
    tasks = _reached(tied.groupBy("source", "size", "place", "task").agg(F.count("*").alias("c")), ["task"], "place").select("source", "size", "task", F.col("place").alias("turn"))
    turn = F.row_number().over(Window.partitionBy("source", "size", "task").orderBy("tie"))
    ties = _beside(tied.drop("place"), tasks, ["source", "size", "task"]).withColumn("now", turn).filter("now = turn").select("source", "size", "tie")
    cut = _beside(at, ties, ["source", "size"], "left").select("source", "size", F.struct("b", "h", "id", F.coalesce("tie", F.lit(2**63 - 1)).alias("tie")).alias("cut"))
    return _beside(plan, cut, ["source", "size"], "left").select("source", "size", "source_size", "target", "base", F.when(F.col("extra") == F.col("n"), 1).otherwise(0).alias("all_once_more"), "cut", "buckets")


def _reached(counts: DataFrame, order: list[str], goal: str) -> DataFrame:
    """The row of each (source, size) in which the running sum of c reaches goal, with place, what goal is within the row."""
    before = F.coalesce(F.sum("c").over(Window.partitionBy("source", "size").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    now = counts.withColumn("__goal", F.col(goal)).withColumn("__before", before).filter("__before < __goal AND __before + c >= __goal")
    return now.withColumn("place", F.col("__goal") - F.col("__before")).drop("__goal", "__before")


def _beside(a: DataFrame, b: DataFrame, keys: list[str], how: str = "inner") -> DataFrame:
    """Join on keys that may be null; the result has each key once."""
    b = b.withColumnsRenamed({k: f"r_{k}" for k in keys})
    on = [F.col(k).eqNullSafe(F.col(f"r_{k}")) for k in keys]
    return a.join(b, on, how).drop(*(f"r_{k}" for k in keys))


def hash_key(seed: int) -> F.Column:
    return F.xxhash64(F.lit(seed), F.col("id"))


def apply_plan(rows: DataFrame, plan: DataFrame, seed: int = 42) -> DataFrame:
    """rows(id, source, size, tie, ...) with source_size, target and times; plan as mix_plan made it, with the same seed."""
    h = hash_key(seed)
    own = F.struct(F.pmod(h, F.col("buckets")).alias("b"), h.alias("h"), F.col("id").alias("id"), F.col("tie").alias("tie"))
    once = F.coalesce(own <= F.col("cut"), F.lit(False)).cast("int")
    times = F.col("base") + F.col("all_once_more") + once
    return _beside(rows, plan, ["source", "size"]).withColumn("times", times).drop("base", "all_once_more", "cut", "buckets", "tie")


def mix_sources(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[float, ...] = (1, 2, 3), cap: float = 3, seed: int = 42) -> DataFrame:
    """One row per row of docs: doc_id, source, size, source_size, target, times, taken (= times * size)."""
    need(docs, id_col, text_col, source_col)
    sized = settle(docs.select(F.col(id_col).cast("long").alias("id"), F.col(source_col).cast("string").alias("source"), word_count(text_col).alias("size"), F.monotonically_increasing_id().alias("tie")))
    out = apply_plan(sized, mix_plan(sized, weights, cap, seed), seed)
    return out.select(F.col("id").alias("doc_id"), "source", "size", "source_size", "target", "times", (F.col("times") * F.col("size")).alias("taken"))


def op3_mix_sources(spark, sf_dir: str) -> DataFrame:
    return mix_sources(spark.read.parquet(f"{sf_dir}/documents.parquet")).select("doc_id", "size", "source_size", "target", "taken", "times", "source")
