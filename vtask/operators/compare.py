"""Comparing methods over datasets: ranks, Elo by Bradley-Terry, Top-k, total rank, imputation, size groups."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Methods come to the driver as a square matrix; more are not a comparison table.
MAX_METHODS = 1000


def ranked(results: DataFrame) -> DataFrame:
    """results(dataset, method, value) with competition ranks: equal values share the best rank."""
    return results.withColumn("rnk", F.rank().over(Window.partitionBy("dataset").orderBy(F.desc("value"))))


def summary(results: DataFrame) -> DataFrame:
    """Mean value of each method and the deviation over seeds of its per-seed mean."""
    by_seed = results.groupBy("method", "seed").agg(F.avg("value").alias("v"))
    return by_seed.groupBy("method").agg(F.round(F.avg("v"), 6).alias("mean_value"), F.round(F.stddev_pop("v"), 6).alias("sd_value"))


def avg_rank(results: DataFrame) -> DataFrame:
    return ranked(results).groupBy("method").agg(F.round(F.avg("rnk"), 6).alias("avg_rank"))


def topk_ratio(results: DataFrame, k: int = 3) -> DataFrame:
    return ranked(results).groupBy("method").agg(F.round(F.avg((F.col("rnk") <= k).cast("double")), 6).alias("top_ratio"))


def rank_box(results: DataFrame) -> DataFrame:
    q = [F.round(F.percentile("rnk", F.lit(p)), 6).alias(n) for n, p in (("lo", 0.0), ("q1", 0.25), ("mid", 0.5), ("q3", 0.75), ("hi", 1.0))]
    return ranked(results).groupBy("method").agg(*q)


def win_matrix(results: DataFrame) -> DataFrame:
    """(a, b, points, games): a win counts one, a tie half. The join is by dataset, within which methods are few."""
    a, b = results.select("dataset", F.col("method").alias("a"), F.col("value").alias("va")), results.select("dataset", F.col("method").alias("b"), F.col("value").alias("vb"))
    p = F.when(F.col("va") > F.col("vb"), 1.0).when(F.col("va") == F.col("vb"), 0.5).otherwise(0.0)
    return a.join(b, "dataset").filter("a <> b").groupBy("a", "b").agg(F.sum(p).alias("points"), F.count("*").alias("games"))


def bradley_terry(points: np.ndarray, games: np.ndarray, rounds: int) -> np.ndarray:
    """Strengths with geometric mean one, by minorise-maximise rounds."""
    beta = np.ones(len(points))
    for _ in range(rounds):
        den = (games / (beta[:, None] + beta[None, :])).sum(axis=1)
        beta = np.maximum(points.sum(axis=1), 1e-9) / np.maximum(den, 1e-12)
        beta = beta / np.exp(np.log(beta).mean())
    return beta


def elo(results: DataFrame, rounds: int = 200) -> DataFrame:
    """(method, elo): 1000 + 400 log10 of the strength."""
    rows = win_matrix(results).limit(MAX_METHODS**2 + 1).collect()
    if len(rows) > MAX_METHODS**2:
        raise ValueError(f"more than {MAX_METHODS} methods")
    names = sorted({r.a for r in rows})
    p, g = np.zeros((len(names), len(names))), np.zeros((len(names), len(names)))
    for r in rows:
        p[names.index(r.a), names.index(r.b)], g[names.index(r.a), names.index(r.b)] = r.points, r.games
    beta = bradley_terry(p, g, rounds) if names else np.zeros(0)
    return results.sparkSession.createDataFrame([(n, round(float(1000 + 400 * np.log10(b)), 4)) for n, b in zip(names, beta, strict=True)], "method string, elo double")


def elo_expected(ratings: DataFrame) -> DataFrame:
    """(a, b, expected): expected score of a against b."""
    a, b = ratings.select(F.col("method").alias("a"), F.col("elo").alias("ra")), ratings.select(F.col("method").alias("b"), F.col("elo").alias("rb"))
    return a.join(b, F.col("a") < F.col("b")).select("a", "b", F.round(1 / (1 + F.pow(F.lit(10.0), (F.col("rb") - F.col("ra")) / 400)), 6).alias("expected"))


def impute(results: DataFrame, datasets: DataFrame, methods: DataFrame) -> DataFrame:
    """The whole grid; a missing value is the mean of the other methods on that dataset."""
    grid = datasets.select("dataset").join(methods.select("method"), F.lit(True))
    full = grid.join(results, ["dataset", "method"], "left")
    mean = F.avg("value").over(Window.partitionBy("dataset"))
    return full.select("dataset", "method", F.round(F.coalesce("value", mean), 6).alias("value"), F.col("value").isNull().alias("imputed"))


def complete_only(results: DataFrame, n_methods: int) -> DataFrame:
    """Only datasets on which every method ran."""
    return results.withColumn("k", F.count("*").over(Window.partitionBy("dataset"))).filter(F.col("k") == n_methods).drop("k")


def total_rank(measures: DataFrame, larger: list[str], smaller: list[str]) -> DataFrame:
    """(method, total_rank): mean over the measures of each method's rank."""
    one = measures.withColumn("g", F.lit(0))
    w = Window.partitionBy("g")
    parts = [F.rank().over(w.orderBy(F.desc(c))) for c in larger] + [F.rank().over(w.orderBy(c)) for c in smaller]
    out = parts[0]
    for p in parts[1:]:
        out = out + p
    return one.select("method", F.round(out / len(parts), 6).alias("total_rank"))


def size_group(n) -> F.Column:
    return F.when(n < 1000, "below 1K").when(n < 10000, "1K-10K").otherwise("10K and more")
