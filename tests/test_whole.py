"""The detector as one plan: labels against the numpy tasks, held-out calibration, selection by brute force, and its physical plan."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from vtask.kernels.detector import Schema
from vtask.kernels.tasks import Spec, Task, grid, instantiations
from vtask.operators import scoring as sc
from vtask.plans.whole import FOLDS, Fit, _detected, candidates, eligible_targets
from vtask.sources.fixtures import FIXTURES, fixture

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def fitted(spark):
    df = fixture(spark, SF, "line_cat")
    return df, Fit(df, list(FIXTURES["line_cat"].cat))


def test_labels_equal_those_of_the_numpy_tasks(fitted):
    df, fit = fitted
    pdf = df.select("rid", *fit.attrs, *(y.alias(c) for c, (y, _) in fit.labels.items() if c[0] == "S")).toPandas()
    wide = df.withColumns(fit.scalars).select("rid", *(y.alias(c) for c, (y, _) in fit.labels.items() if c[0] != "S")).toPandas().set_index("rid").loc[pdf["rid"]]
    rows = fit.context.toPandas().sort_values("rid", ignore_index=True)
    schema = Schema.fit(rows, fit.attrs)
    f, every = schema.frame(rows), schema.frame(pdf)
    for x in candidates(fit.attrs):
        t = Task.fit(Spec(x.task, "cat", bins=x.bins, draw=x.draw), f, 0)
        assert sorted(t.names) == sorted(x.attrs)
        same = (t.label(every).astype(str) == wide[x.cand].to_numpy()).mean()
        assert same > 0.999, (x, same)  # scalars are rounded to 6 and to 9 digits
    assert {s.target for s in grid(f, schema)["S"]} == set(fit.targets)


def test_every_task_has_four_candidates(fitted):
    _, fit = fitted
    schema = Schema.fit(fit.context.toPandas(), fit.attrs)
    g = grid(schema.frame(fit.context.toPandas()), schema)
    assert set(g) == {t for t, _ in instantiations(schema.profile)} and all(4 <= len(v) <= 8 for v in g.values())


def test_levels_are_held_out(fitted):
    df, fit = fitted
    counts = fit.context.groupBy("fold").count().collect()
    assert {r.fold for r in counts} == {-1, *range(FOLDS)} and all(r["count"] == fit.h for r in counts if r.fold >= 0)
    support = fit.supports().toPandas()
    assert (support.groupby(["cand", "kind"]).size() == FOLDS * fit.h).all()
    # one candidate by plain loops
    c = fit.context.toPandas()
    attrs = [a for a in fit.attrs if a != "return_flag"]
    want = []
    for s in range(FOLDS):
        train, own = c[c["fold"] != s], c[c["fold"] == s]
        for _, r in own.head(40).iterrows():
            lp = {}
            for y, part in train.groupby("return_flag"):
                lp[y] = np.log(len(part) / len(train)) + sum(np.log(((part[a] == r[a]).sum() + 1) / (len(part) + train[a].nunique() + 1)) for a in attrs)
            top = max(lp.values())
            want.append(np.exp(lp[r["return_flag"]] - top) / sum(np.exp(v - top) for v in lp.values()))
    got = support[(support["cand"] == "S:return_flag") & (support["kind"] == "nom")]["kappa"].to_numpy()
    assert all(np.abs(got - w).min() < 2e-6 for w in want)


def test_separation_by_pairs(spark):
    g = np.random.default_rng(3)
    rows = [(t, c, k, float(round(v, 1))) for t in "SL" for c in (1, 2) for k in ("nom", "vio") for v in g.random(37)]
    got = {(r.task, r.cand): r.rho for r in sc.separation_auc(spark.createDataFrame(rows, "task string, cand int, kind string, kappa double")).collect()}
    for t, c in got:
        u, v = ([x[3] for x in rows if x[:3] == (t, c, k)] for k in ("nom", "vio"))
        assert got[t, c] == round(sum(a > b for a in u for b in v) / (len(u) * len(v)), 6)


def test_targets():
    counts = {"a": {"x": 500, "y": 500}, "b": {"x": 990, "y": 10}, "c": {str(i): 10 for i in range(100)}, "d": {"x": 996, "y": 4}, "e": {"x": 300, "y": 300, "z": 400}}
    assert eligible_targets(counts, 1000) == ["e", "a"]


def test_scoring_the_table_never_shuffles(spark):
    out = _detected(spark, SF)
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Window" not in plan
    assert out.filter(F.col("score").isNull()).count() == 0
