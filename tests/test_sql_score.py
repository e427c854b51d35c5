"""The table function and the streamed state against one process."""

from __future__ import annotations

import numpy as np

from vtask.functions import sqlapi
from vtask.kernels import detector as det
from vtask.plans.workloads import BASE
from vtask.sources import sinks
from vtask.sources.fixtures import FIXTURES, fixture

D = "/root/testdata/sf0.001"


def test_table_function_scores_as_the_model(spark, tmp_path):
    df = fixture(spark, D, "order_wide")
    f = FIXTURES["order_wide"]
    c = df.filter("split = 'context'").limit(150).toPandas()
    sinks.save_model(spark, det.fit(c, f.attrs, det.with_(BASE, backbone="counts")), str(tmp_path / "m"))
    sqlapi.register(spark, str(tmp_path / "m"))
    model = sinks.load_model(spark, str(tmp_path / "m"))
    rows = df.filter("split = 'query'").toPandas()
    df.filter("split = 'query'").createOrReplaceTempView("to_score")
    got = {r.rid: r.score for r in spark.sql("SELECT * FROM vt_score(TABLE(to_score))").collect()}
    assert len(got) == len(rows)
    assert np.allclose([got[r] for r in rows["rid"]], model.score(rows), atol=1e-6)
    df.filter("false").createOrReplaceTempView("to_score")
    assert spark.sql("SELECT * FROM vt_score(TABLE(to_score))").count() == 0
