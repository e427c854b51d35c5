"""Writers of scores and fitted models."""

from __future__ import annotations

import base64
import json
import pickle

from pyspark.sql import DataFrame, SparkSession


def write_scores(df: DataFrame, path: str, by: str | None = None, fmt: str = "parquet") -> None:
    w = df.write.mode("overwrite").format(fmt)
    (w.partitionBy(by) if by else w).save(path)


def save_model(spark: SparkSession, model, path: str) -> None:
    """One text row on any file system that Spark can write; bounded by the model's context."""
    row = json.dumps({"kind": type(model).__name__, "data": base64.b64encode(pickle.dumps(model)).decode()})
    spark.createDataFrame([(row,)], "value string").coalesce(1).write.mode("overwrite").text(path)


def load_model(spark: SparkSession, path: str):
    """A model that save_model wrote; only load what you trust, as it is pickled."""
    return pickle.loads(base64.b64decode(json.loads(spark.read.text(path).first().value)["data"]))
