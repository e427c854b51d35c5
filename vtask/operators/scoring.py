"""Support, calibration, selection, ensembles and measures as Spark plans.

The count backbone's tables are literals, so a support is a projection. Measures
group by distinct score before any ordering: calibrated scores are discrete, so
no window runs over raw rows.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from vtask.operators.tasks import ALPHA, total

EPS = 1e-9


def fit_counts(df: DataFrame, label: Column, view: dict[str, Column]) -> dict:
    """Class sizes and token counts by class: a closed-form posterior predictive; one aggregation of classes * tokens rows."""
    toks = F.array(F.struct(F.lit("").alias("attr"), F.lit("").alias("tok")), *(F.struct(F.lit(a).alias("attr"), c.alias("tok")) for a, c in view.items()))
    rows = df.select(label.alias("y"), F.explode(toks).alias("t")).groupBy("y", "t.attr", "t.tok").agg(F.count("*").alias("n")).collect()
    size = {r.y: r.n for r in rows if r.attr == ""}
    table: dict = {a: {} for a in view}
    for r in rows:
        if r.attr:
            table[r.attr].setdefault(r.tok, {})[r.y] = r.n
    return {"size": size, "table": table}


def counts_support(model: dict, label: Column, view: dict[str, Column]) -> Column:
    """Probability of each row's own label, rounded; a tiny constant where the context lacks it."""
    size, n = model["size"], sum(model["size"].values())
    logs = {}
    for y, ny in sorted(size.items()):
        terms = [F.lit(float(ny) / n)]
        lp = F.log(terms[0])
        for a, c in view.items():
            hits = {v: float(by[y]) for v, by in model["table"][a].items() if by.get(y)}
            got = F.coalesce(F.element_at(F.create_map(*(F.lit(x) for kv in sorted(hits.items()) for x in kv)), c), F.lit(0.0)) if hits else F.lit(0.0)
            lp = lp + F.log((got + ALPHA) / F.lit(ny + ALPHA * (len(model["table"][a]) + 1)))
        logs[y] = lp
    best = F.array_max(F.array(*logs.values()))
    own = F.lit(None).cast("double")
    for y, lp in logs.items():
        own = F.when(label == F.lit(y), lp).otherwise(own)
    denom = total([F.exp(lp - best) for lp in logs.values()])
    return F.round(F.coalesce(F.exp(own - best) / denom, F.lit(EPS)), 6)


def surprisal(kappa: Column, levels: list[float]) -> Column:
    """-log of the smoothed share of nominal supports at or below kappa, by binary search in Arrow batches; levels is bounded by the held-out rows."""
    lv = np.sort(np.array(levels, float))

    @F.pandas_udf("double")
    def search(k: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(lv, k.to_numpy(), side="right").astype(float))

    return F.round(-F.log((search(kappa) + 1) / F.lit(float(len(lv) + 1))), 6)


def cand_stats(support: DataFrame) -> DataFrame:
    """(task, cand, med, var, rho, gap) from support(task, cand, kind, kappa)."""
    nom, vio = F.when(F.col("kind") == "nom", F.col("kappa")), F.when(F.col("kind") == "vio", F.col("kappa"))
    base = support.groupBy("task", "cand").agg(F.percentile(nom, F.lit(0.5)).alias("med"), F.var_pop(nom).alias("var"), F.percentile(nom, F.lit(0.25)).alias("q1"), F.percentile(vio, F.lit(0.75)).alias("q3"))
    out = base.join(separation_auc(support), ["task", "cand"])
    return out.select("task", "cand", F.round("med", 6).alias("med"), F.round("var", 6).alias("var"), "rho", F.round(F.col("q1") - F.col("q3"), 6).alias("gap"))


def separation_auc(support: DataFrame, ties: float = 0.0) -> DataFrame:
    """(task, cand, rho): share of (nominal, probe) pairs with the nominal support larger, by ranks over distinct supports."""
    lv = support.groupBy("task", "cand", "kappa").agg(F.sum((F.col("kind") == "nom").cast("long")).alias("u"), F.sum((F.col("kind") == "vio").cast("long")).alias("v"))
    w = Window.partitionBy("task", "cand").orderBy("kappa").rowsBetween(Window.unboundedPreceding, -1)
    below = F.coalesce(F.sum("v").over(w), F.lit(0))
    wins = F.col("u") * (below + F.lit(ties) * F.col("v"))
    return lv.withColumn("wins", wins).groupBy("task", "cand").agg(F.round(F.sum("wins") / (F.sum("u").cast("double") * F.sum("v")), 6).alias("rho"))


def avg_rank(col: Column, *part: str) -> Column:
    """Normalised badness rank in [0, 1], ties averaged; col ascending is better first."""
    w, same = Window.partitionBy(*part), Window.partitionBy(*part, col)
    r = F.rank().over(w.orderBy(col)) + (F.count("*").over(same) - 1) / 2
    return (r - 1) / F.greatest(F.lit(1), F.count("*").over(w) - 1)


def intra_filter(stats: DataFrame, coherent: float = 0.7) -> DataFrame:
    """Coherent candidates; where a task has none, its candidate of largest rho."""
    w = Window.partitionBy("task")
    s = stats.withColumn("ok", F.max((F.col("med") >= coherent).cast("int")).over(w)).withColumn("first", F.row_number().over(w.orderBy(F.desc("rho"), "cand")))
    return s.filter(((F.col("ok") == 1) & (F.col("med") >= coherent)) | ((F.col("ok") == 0) & (F.col("first") == 1))).drop("ok", "first")


def intra_shortlist(stats: DataFrame, coherent: float = 0.7, share: float = 0.70, least: int = 2) -> DataFrame:
    w = Window.partitionBy("task")
    s = intra_filter(stats, coherent).withColumn("n", F.count("*").over(w)).withColumn("r", F.row_number().over(w.orderBy(F.desc("rho"), "cand")))
    return s.filter(F.col("r") <= F.least(F.col("n"), F.greatest(F.lit(least), F.ceil(F.lit(share) * F.col("n"))))).drop("n", "r")


def intra_pick(stats: DataFrame, **kw) -> DataFrame:
    """One candidate a task, with its summed badness."""
    s = intra_shortlist(stats, **kw)
    s = s.withColumn("badness", F.round(avg_rank(-F.col("med"), "task") + avg_rank(F.col("var"), "task") + avg_rank(-F.col("gap"), "task"), 6))
    return s.withColumn("r", F.row_number().over(Window.partitionBy("task").orderBy("badness", "cand"))).filter("r = 1").drop("r")


def inter_prefilter(reps: DataFrame, separate: float = 0.50) -> DataFrame:
    one = reps.withColumn("g", F.lit(0))
    w = Window.partitionBy("g")
    s = one.withColumn("ok", F.max((F.col("rho") >= separate).cast("int")).over(w)).withColumn("first", F.row_number().over(w.orderBy(F.desc("rho"), "task")))
    return s.filter(((F.col("ok") == 1) & (F.col("rho") >= separate)) | ((F.col("ok") == 0) & (F.col("first") == 1))).drop("ok", "first", "g")


def inter_rank(reps: DataFrame, separate: float = 0.50, w_auc: float = 1.5) -> DataFrame:
    s = inter_prefilter(reps, separate).withColumn("g", F.lit(0))
    b = F.lit(w_auc) * avg_rank(-F.col("rho"), "g") + avg_rank(-F.col("med"), "g") + avg_rank(F.col("var"), "g") + avg_rank(-F.col("gap"), "g")
    s = s.select("task", "cand", F.round(b, 6).alias("badness"), "g")
    return s.withColumn("place", F.row_number().over(Window.partitionBy("g").orderBy("badness", "task"))).withColumn("n", F.count("*").over(Window.partitionBy("g"))).drop("g")


def retain(ranked: DataFrame, policy: str = "all") -> DataFrame:
    keep = {"all": F.col("n"), "best": F.lit(1), "topk": F.ceil(F.col("n") * 0.5)}[policy]
    return ranked.filter(F.col("place") <= keep).select("task", "cand", "badness", "place")


# --- ensembles over an array column of task scores


def ens_min(s: Column) -> Column:
    return F.array_min(s)


def ens_low2mean(s: Column) -> Column:
    two = F.slice(F.array_sort(s), 1, 2)
    return F.aggregate(two, F.lit(0.0), lambda a, x: a + x) / F.size(two)


def ens_weighted(s: Column, w: list[float]) -> Column:
    return total([F.element_at(s, i + 1) * F.lit(float(x)) for i, x in enumerate(w)])


# --- measures


def _levels(scored: DataFrame) -> DataFrame:
    return scored.groupBy("dataset", "score").agg(F.sum("is_anom").cast("long").alias("p"), F.sum(1 - F.col("is_anom")).cast("long").alias("q"))


def auroc(scored: DataFrame) -> DataFrame:
    """(dataset, auroc) from scored(dataset, score, is_anom), ties half; null for one-class sets."""
    below = F.coalesce(F.sum("q").over(Window.partitionBy("dataset").orderBy("score").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    lv = _levels(scored).withColumn("w", F.col("p") * (below + F.col("q") / 2))
    pairs = F.sum("p").cast("double") * F.sum("q")
    return lv.groupBy("dataset").agg(F.when(pairs > 0, F.round(F.sum("w") / pairs, 6)).alias("auroc"))


def average_precision(scored: DataFrame) -> DataFrame:
    w = Window.partitionBy("dataset").orderBy(F.desc("score")).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    lv = _levels(scored).withColumn("cp", F.sum("p").over(w)).withColumn("cq", F.sum("q").over(w))
    term = F.col("cp").cast("double") / (F.col("cp") + F.col("cq")) * F.col("p")
    return lv.withColumn("t", term).groupBy("dataset").agg(F.when((F.sum("p") > 0) & (F.sum("q") > 0), F.round(F.sum("t") / F.sum("p"), 6)).alias("ap"))
