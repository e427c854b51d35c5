"""The measures over results against a plain computation, and what contamination must keep."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pytest

from vtask.kernels import detector as det
from vtask.plans import comparison as cp


@pytest.fixture(scope="module")
def res(spark):
    g = np.random.default_rng(1)
    rows = [(f"d{i}", f"m{k}", seed, float(round(g.uniform(0.4, 1) + 0.02 * k, 3)), float(round(g.uniform(0.1, 0.9), 3)), 500 * (i + 1)) for i in range(4) for k in range(5) for seed in (0, 1)]
    rows = [(*r[:3], None, None, r[5]) if r[:2] == ("d0", "m2") else r for r in rows]  # a method that failed
    return spark.createDataFrame(rows, "dataset string, method string, seed int, auroc double, ap double, n_context long")


def _plain(res, measure):
    pdf = res.toPandas()
    v = pdf.dropna(subset=[measure]).groupby(["dataset", "method"])[measure].mean().round(6).unstack()
    return v.apply(lambda r: r.fillna(round(r.mean(), 6)), axis=1)


def test_table(res):
    v = _plain(res, "auroc")
    got = {r.method: r for r in cp.table(cp.imputed(cp.values(res, "auroc"))).collect()}
    rank = v.rank(axis=1, method="min", ascending=False)
    for m in v.columns:
        assert got[m].mean_value == pytest.approx(v[m].mean(), abs=2e-6)
        assert got[m].avg_rank == pytest.approx(rank[m].mean(), abs=1e-6)
        assert got[m].top_ratio == pytest.approx((rank[m] <= 3).mean(), abs=1e-6)


def test_total_rank_is_over_eight_measures(res):
    tables = [cp.table(cp.imputed(cp.values(res, m))).toPandas().set_index("method") for m in ("auroc", "ap")]
    ranks = [t[c].rank(method="min", ascending=c == "avg_rank") for t in tables for c in ("mean_value", "avg_rank", "elo", "top_ratio")]
    want = sum(ranks) / 8
    assert len(ranks) == 8
    assert {r.method: r.total_rank for r in cp.total(res).collect()} == pytest.approx(want.to_dict(), abs=1e-6)


def test_complete_leaves_out_the_dataset_of_a_failure(res):
    assert {r.dataset for r in cp.complete(cp.values(res, "auroc")).collect()} == {"d1", "d2", "d3"}
    groups = {r.size_group for r in cp.elo_by_size(cp.values(res, "auroc")).collect()}
    assert groups == {"below 1K", "1K-10K"}


def test_contamination_keeps_queries_and_ratio():
    rows = pd.DataFrame({"rid": [str(i) for i in range(400)], "split": ["context"] * 200 + ["query"] * 200, "is_anom": [0] * 300 + [1] * 100, "x": np.arange(400.0)})
    out = {p: cp.contaminate(p)(rows, 0) for p in cp.SHARES}
    queries = [tuple(o.loc[o["split"] == "query", "rid"]) for o in out.values()]
    assert len(set(queries)) == 1
    for p, o in out.items():
        c, q = o[o["split"] == "context"], o[o["split"] == "query"]
        assert len(c) == 200 and c["is_anom"].sum() == round(p * 200)
        assert q["is_anom"].mean() == pytest.approx(0.5, abs=0.01)
        assert not set(c["rid"]) & set(q["rid"])
    few = rows[(rows["is_anom"] == 0) | (rows["x"] < 330)].reset_index(drop=True)  # 30 anomalies, 20 of which the worst setting takes
    assert cp.contaminate(0.0)(few, 0).empty


def test_efficiency_times_both_selections():
    g = np.random.default_rng(0)
    x = pd.DataFrame(g.normal(size=(300, 4)), columns=list("abcd"))
    three, one = cp.efficiency(x.iloc[:200], x.iloc[200:], list("abcd"), det.Config(backbone="counts"))
    assert (three["splits"], one["splits"]) == (3, 1) and three["fit_calls"] == 3 * one["fit_calls"] and three["chain_calls"] == 3
    assert all(v > 0 for r in (three, one) for k, v in r.items() if k.endswith(("_s", "_row")) or k.startswith("ratio"))
