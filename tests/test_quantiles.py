"""Exact quantiles without a map of all values: equal to Spark's percentile, also where a sketch misses, and no query fits by percentile."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from vtask.operators import tasks as tk
from vtask.plans.queries import QUERIES

D = "/root/testdata/sf0.001"
PS = [0.0, 0.25, 1 / 3, 0.5, 0.75, 1.0]


@pytest.fixture(scope="module")
def values(spark):
    i = F.col("id")
    skew = F.when(i % 3 == 0, F.lit(0.0)).otherwise(F.pow(i % 9973, F.lit(3.0)) - 1e6)
    cols = {"few": (i % 7).cast("double"), "many": F.sin(i.cast("double")), "skew": skew, "holes": F.when(i % 11 > 8, i * -0.5), "one": F.when(i == 5, F.lit(2.5)), "none": F.lit(None).cast("double"), "whole": i % 1000}
    return spark.range(60_000).select(*(c.alias(a) for a, c in cols.items())).repartition(7).cache()


def plain(df):
    row = df.agg(*(F.percentile(a, F.array(*map(F.lit, PS))).alias(a) for a in df.columns)).first()
    return {a: list(row[a] or []) for a in df.columns}


def test_equal_to_percentile(values):
    assert tk._quantiles(values, {a: F.col(a) for a in values.columns}, PS, False) == plain(values)


def test_missed_brackets_are_searched_again(values, monkeypatch):
    asked = []
    inner = tk._values_at

    def misled(df, wanted):
        asked.append(len(wanted))
        return inner(df, [(i, c, [(5e8, 6e8)] if len(asked) == 1 else ends, ranks) for i, c, ends, ranks in wanted])

    monkeypatch.setattr(tk, "_values_at", misled)
    assert tk._quantiles(values, {a: F.col(a) for a in values.columns}, PS, False) == plain(values)
    assert asked == [6, 6]


@pytest.mark.parametrize("name", ["robust_params_line_num", "global_numeric_label", "masked_numeric_label", "radial_label", "kmeans_assign_fixed", "kmeans_fit"])
def test_fits_hold_no_map_of_values(spark, name, monkeypatch):
    def percentile(*_):
        raise AssertionError("percentile holds every distinct value in one task")

    monkeypatch.setattr(tk.F, "percentile", percentile)
    assert QUERIES[name](spark, D).count() > 0


def test_nearest_rounds_ties_alike(spark):
    t, centres = tk.raw(["x"]), [[1.0], [3.0], [3.0000001]]
    rows = spark.range(2001).select((F.col("id") / 500).alias("x")).unionAll(spark.createDataFrame([(2.0000001,), (1.9999999,), (None,)], "x double"))
    was = tk.nearest([F.round((F.col("x") - F.lit(m)) * (F.col("x") - F.lit(m)), 6) for (m,) in centres])
    assert rows.filter(~was.eqNullSafe(tk.assign_kmeans(t, ["x"], centres))).count() == 0
