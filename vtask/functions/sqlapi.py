"""SQL surface: temporary functions for the method's scalars and a table function that scores rows by a saved model."""

from __future__ import annotations

from pyspark.sql import SparkSession


def register(spark: SparkSession, model_path: str | None = None) -> None:
    """vt_qbin, vt_surprisal, vt_low2mean and vt_u01, as SQL expressions that Catalyst inlines; with a saved model, the table function vt_score too."""
    for text in (
        "vt_qbin(z DOUBLE, b ARRAY<DOUBLE>) RETURNS INT RETURN size(filter(b, x -> x < z))",
        "vt_surprisal(k DOUBLE, q ARRAY<DOUBLE>) RETURNS DOUBLE RETURN -ln((1 + size(filter(q, x -> x <= k))) / (1D + size(q)))",
        "vt_low2mean(s ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(slice(array_sort(s), 1, 2), 0D, (a, x) -> a + x) / least(2, size(s))",
        "vt_u01(seed INT, k STRING) RETURNS DOUBLE RETURN cast(conv(substr(md5(concat_ws('|', seed, 'sql', k)), 1, 13), 16, 10) AS DOUBLE) / 4503599627370496D",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {text}")
    if model_path is not None:
        from vtask.sources.sinks import load_model

        spark.udtf.register("vt_score", scorer(load_model(spark, model_path)))


def scorer(model, batch: int = 4096):
    """Table function of (rid, score) over a table with rid and the model's attributes: SELECT * FROM vt_score(TABLE(t)).

    Rows are scored in batches, so a partition of any size takes the memory of
    one; the model goes out with the function, as it is bounded by its context.
    """
    import pandas as pd
    from pyspark.sql.functions import udtf

    class Score:
        def __init__(self):
            self.rows = []

        def eval(self, row):
            self.rows.append(row.asDict())
            if len(self.rows) >= batch:
                yield from self.flush()

        def terminate(self):
            yield from self.flush()

        def flush(self):
            rows, self.rows = self.rows, []
            if rows:
                pdf = pd.DataFrame(rows)
                for rid, z in zip(pdf["rid"], model.score(pdf), strict=True):
                    yield str(rid), round(float(z), 6)

    return udtf(Score, returnType="rid string, score double")
