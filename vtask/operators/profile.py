"""Attribute statistics, kinds and the dataset's profile, as Spark plans.

One aggregation finds all statistics: a row an attribute, so what comes to the
driver is as small as the schema. With approx=True the distinct counts are
sketched first and counted exactly only where the estimate is near the largest
threshold (20); everything else is far from it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vtask.kernels.table import CAT, CONST, DROPPED, NUM, dataset_profile

_NEAR = 40


def _is_text(df: DataFrame, a: str) -> bool:
    return dict(df.dtypes)[a].startswith(("string", "varchar", "char"))


def attr_stats(df: DataFrame, attrs: list[str], approx: bool = False) -> DataFrame:
    """(name, n_valid, n_distinct, int_like) of each attribute."""
    few = None
    if approx:
        est = df.agg(*(F.approx_count_distinct(a).alias(a) for a in attrs)).first()
        few = {a for a in attrs if est[a] <= _NEAR}

    def whole(a):
        return F.lit(False) if _is_text(df, a) else F.coalesce(F.min(F.col(a) == F.floor(F.col(a))), F.lit(False))

    def distinct(a):
        return F.count_distinct(a) if few is None or a in few else F.approx_count_distinct(a)

    one = df.agg(*(F.struct(F.lit(a).alias("name"), F.count(a).alias("n_valid"), distinct(a).alias("n_distinct"), whole(a).alias("int_like")).alias(f"s{i}") for i, a in enumerate(attrs)))
    return one.select(F.explode(F.array(*(f"s{i}" for i in range(len(attrs))))).alias("s")).select("s.*")


def card_threshold(n: Column) -> Column:
    return F.least(F.lit(20), F.greatest(F.lit(2), F.ceil(F.sqrt(n)))).cast("long")


def with_kinds(stats: DataFrame, text: list[str]) -> DataFrame:
    """stats with threshold and kind; text names the string attributes."""
    u, n = F.col("n_distinct"), F.col("n_valid")
    few, share = u <= F.col("threshold"), u / n
    kind = (
        F.when((n == 0) | (u <= 1), CONST)
        .when(F.col("name").isin(text) & few & (share <= 0.5), CAT)
        .when(F.col("name").isin(text), F.when(share <= 0.5, NUM).otherwise(DROPPED))
        .when(((u < 10) | few) & (F.col("int_like") | few) & (share <= 0.5), CAT)
        .otherwise(NUM)
    )
    return stats.withColumn("threshold", card_threshold(n)).withColumn("kind", kind)


def infer_types(df: DataFrame, attrs: list[str], approx: bool = False) -> DataFrame:
    return with_kinds(attr_stats(df, attrs, approx), [a for a in attrs if _is_text(df, a)])


def profile_of(df: DataFrame, attrs: list[str]) -> str:
    return dataset_profile([r.kind for r in infer_types(df, attrs).select("kind").collect()])
