"""What the split queries' SQL cannot say: the iterated prototypes against one process, and the trained classifiers' supports."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from vtask.operators import tasks as tk
from vtask.plans.splits import fit_kproto, split_by_ratio, trained_support


def test_prototypes_are_a_fixed_point(spark):
    g = np.random.default_rng(0)
    rows = [(float(x), "a" if x < 2 else "b") for x in g.integers(0, 4, 200)]
    df = spark.createDataFrame(rows, "n double, c string")
    codes = {"n": F.col("n")}
    protos = fit_kproto(df, codes, ["c"], 2)
    got = np.array([r.k for r in df.select(tk.assign_kproto(codes, ["c"], protos).alias("k")).collect()])
    for i, (mean, mode) in enumerate(protos):
        own = [r for r, k in zip(rows, got, strict=True) if k == i]
        assert own and abs(np.mean([x for x, _ in own]) - mean[0]) < 1e-6
        values, n = np.unique([c for _, c in own], return_counts=True)
        assert mode == [values[n.argmax()]]
    assert fit_kproto(df.filter("false"), codes, ["c"], 2) == []


def test_split_takes_less_context_where_anomalies_are_many(spark):
    few = spark.range(4000).select(F.col("id").cast("string").alias("rid"), (F.col("id") % 10 == 0).cast("int").alias("is_anom"))
    many = few.withColumn("is_anom", (F.col("rid") % 2 == 0).cast("int"))
    for df, share in ((few, 0.6), (many, 0.5)):
        out = split_by_ratio(df)
        assert out.filter("is_anom = 1 AND split = 'context'").count() == 0
        assert abs(out.filter("split = 'context'").count() / df.filter("is_anom = 0").count() - share) < 0.04
    assert split_by_ratio(few.filter("false")).count() == 0


def test_trained_support_follows_the_law(spark):
    rows = [(str(i), "context" if i % 2 else "query", int(i % 20 == 0), "x" if i % 3 else "y", ("p" if i % 3 else "q") if i % 20 else "r") for i in range(600)]
    df = spark.createDataFrame(rows, "rid string, split string, is_anom int, label string, a string")
    for kind in ("forest", "logit"):
        got = {r.is_anom: r.k for r in trained_support(df, "label", ["a"], kind).filter("rid % 2 = 0").groupBy("is_anom").agg(F.avg("kappa").alias("k")).collect()}
        assert got[0] > 0.9 and got[1] < got[0]
