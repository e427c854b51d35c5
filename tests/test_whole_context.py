"""Queries whose context is larger than any table of the test data."""

from __future__ import annotations

import duckdb
import numpy as np
from pyspark.sql import functions as F

from vtask.kernels.baselines import PCA
from vtask.plans import baseline_queries  # noqa: F401
from vtask.plans.queries import ORACLES, QUERIES
from vtask.sources.fixtures import FIXTURES, fixture


def test_kernel_support_takes_the_whole_context(spark, tmp_path):
    n = 12000  # of these more than 5,000 are context; balances rise with the key, so that no part stands for the whole
    rows = spark.range(n).select(F.col("id").alias("s_suppkey"), F.concat(F.lit("s"), "id").alias("s_name"), (F.col("id") % 25).cast("int").alias("s_nationkey"), (F.col("id") * 11000.0 / n - 1000).alias("s_acctbal"))
    rows.write.parquet(str(tmp_path / "supplier.parquet"))
    spark.read.parquet("/root/testdata/sf0.001/nation.parquet").write.parquet(str(tmp_path / "nation.parquet"))
    duck = duckdb.connect()
    for t in ("supplier", "nation"):
        duck.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tmp_path}/{t}.parquet/*.parquet'")
    want = dict(duck.execute(ORACLES["kernel_support_small"]).fetchall())
    got = {r.rid: r.kappa for r in QUERIES["kernel_support_small"](spark, str(tmp_path)).collect()}
    assert len(want) > 4000 and got.keys() == want.keys()
    assert max(abs(got[k] - want[k]) for k in want) < 2e-6


def test_pca_takes_the_whole_context(spark):
    d, cols = "/root/testdata/sf0.01", list(FIXTURES["line_num"].num)
    rows = fixture(spark, d, "line_num").select("rid", "split", *cols).toPandas()
    c, q = rows[rows.split == "context"], rows[rows.split == "query"]
    assert len(c) > 20000
    want = dict(zip(q.rid, PCA().fit(c[cols].to_numpy(float)).score(q[cols].to_numpy(float)), strict=True))
    got = {r.rid: r.score for r in QUERIES["pca_line_num"](spark, d).collect()}
    assert got.keys() == want.keys() and np.allclose([got[k] for k in want], list(want.values()), atol=1e-3)
