"""Every query with an SQL twin against DuckDB on the smallest tables, and what only Spark can say against the kernels."""

from __future__ import annotations

import math

import duckdb
import numpy as np
import pytest

from vtask.plans import baseline_queries, splits, surroundings, workloads  # noqa: F401
from vtask.plans.queries import ORACLES, QUERIES
from vtask.sources.dialect import TABLES

D = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{D}/{t}.parquet'")
    return c


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else round(v, 9) + 0.0
    return float(v) if v.__class__.__name__ == "Decimal" else v


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_against_sql(spark, duck, name):
    df = QUERIES[name](spark, D)
    cols = sorted(df.columns)
    got = sorted(str([plain(r[c]) for c in cols]) for r in df.collect())
    res = duck.execute(ORACLES[name])
    at = {x[0]: i for i, x in enumerate(res.description)}
    assert sorted(at) == cols
    assert got == sorted(str([plain(r[at[c]]) for c in cols]) for r in res.fetchall())


def test_scoring_never_shuffles(spark):
    from vtask.kernels import detector as det
    from vtask.plans.workloads import BASE, score_rows
    from vtask.sources.fixtures import FIXTURES, fixture

    df = fixture(spark, D, "order_wide")
    c = df.filter("split = 'context'").limit(200).toPandas()
    m = det.fit(c, FIXTURES["order_wide"].attrs, BASE)
    base = spark.createDataFrame(df.limit(50).toPandas(), df.schema)
    plan = score_rows(base, m)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "MapInPandas" in plan
    rows = score_rows(base, m).collect()
    want = m.score(base.toPandas())
    assert np.allclose([r.score for r in rows], want, atol=1e-6) and set(rows[0].by_task) == {t.task for t in m.kept}


def test_modes_agree(spark):
    """A dataset scored in the grouped map gives what the kernels give in one process."""
    from vtask.plans import workloads as w

    res = w.run_suite(spark, D, ["order_wide"], {"x": w.BASE}, ["knn"]).collect()
    rows = w._rows(w._frame(spark, D, "order_wide").toPandas(), "order_wide")
    f = w.FIXTURES["order_wide"]
    rows = w.plant(rows, list(f.num), list(f.cat), "law_break", 0)
    c, q = rows[rows["split"] == "context"], rows[rows["split"] == "query"]
    s = w.det.fit(c, f.attrs, w.BASE).score(q)
    assert {r.method: r.auroc for r in res}["x"] == round(w.sel.auroc(s, q["is_anom"].to_numpy()), 4)


def test_labels_do_not_matter(spark):
    from vtask.plans import workloads as w

    rows = w._rows(w._frame(spark, D, "part_dep").toPandas(), "part_dep")
    c, q = rows[rows["split"] == "context"], rows[rows["split"] == "query"]
    m = w.det.fit(c, w.FIXTURES["part_dep"].attrs, w.BASE)
    assert (m.score(q) == m.score(q.assign(is_anom=1 - q["is_anom"]))).all()


def test_stream_equals_batch(spark):
    from vtask.streaming.jobs import score_events

    got = sorted(tuple(r) for r in QUERIES["stream_scores_memory"](spark, D).collect())
    want = sorted(tuple(r) for r in score_events(spark.read.parquet(f"{D}/events.parquet")).select("event_id", "user_id", "surprisal").collect())
    assert got == want


def test_models_round_trip(spark, tmp_path):
    from vtask.kernels import detector as det
    from vtask.sources.sinks import load_model, save_model
    from vtask.plans.workloads import BASE
    from vtask.sources.fixtures import FIXTURES, fixture

    pdf = fixture(spark, D, "order_wide").limit(300).toPandas()
    m = det.fit(pdf.iloc[:200], FIXTURES["order_wide"].attrs, BASE)
    save_model(spark, m, str(tmp_path / "model"))
    assert (load_model(spark, str(tmp_path / "model")).score(pdf) == m.score(pdf)).all()


def test_published_ranks_replay():
    """Total rank is the mean of the eight ranks; three rows of the published table."""
    for ranks, total in (((1, 1, 1, 1, 1, 1, 1, 1), 1.00), ((2, 2, 2, 2, 2, 2, 2, 4), 2.25), ((3, 3, 5, 3, 3, 3, 8, 10), 4.75)):
        assert np.mean(ranks) == total


def test_stream_results_stay_off_the_driver(spark, monkeypatch):
    from vtask.streaming import jobs

    monkeypatch.setattr(jobs, "run_once", None)  # its table lies in the driver's memory
    df = QUERIES["stream_scores_memory"](spark, D)
    assert df.inputFiles() and df.count() == spark.read.parquet(f"{D}/events.parquet").count()
