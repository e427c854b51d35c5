"""Feature helpers and relational helpers around the method."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from vtask.operators.tasks import u01


def with_rid(df: DataFrame) -> DataFrame:
    """A stable row id: an md5 of all columns and a number among exact copies."""
    key = F.md5(F.concat_ws("|", *(F.coalesce(F.col(c).cast("string"), F.lit("\x00")) for c in sorted(df.columns))).cast("binary"))
    k = df.withColumn("__h", key)
    return k.withColumn("rid", F.concat_ws("-", "__h", F.row_number().over(Window.partitionBy("__h").orderBy("__h")).cast("string"))).drop("__h")


def previous_event(df: DataFrame, key: str, ts: str, ident: str) -> DataFrame:
    """The last earlier row of the same key, and the seconds since: an as-of self join as a window."""
    w = Window.partitionBy(key).orderBy(ts, ident)
    return df.withColumn("prev_id", F.lag(ident).over(w)).withColumn("gap_s", F.unix_timestamp(ts) - F.unix_timestamp(F.lag(ts).over(w)))


def events_within(df: DataFrame, key: str, ts: str, seconds: int) -> DataFrame:
    """How many rows of the same key lie in the `seconds` before each row, itself included."""
    w = Window.partitionBy(key).orderBy(F.unix_timestamp(ts)).rangeBetween(-seconds, 0)
    return df.withColumn("n_recent", F.count("*").over(w))


def topk(df: DataFrame, by: Column, k: int, per: str | None = None) -> DataFrame:
    """The k rows of largest `by`; per group with `per`."""
    if per is None:
        return df.orderBy(by.desc()).limit(k)
    return df.withColumn("__r", F.row_number().over(Window.partitionBy(per).orderBy(by.desc()))).filter(F.col("__r") <= k).drop("__r")


def exact_sample(df: DataFrame, key: str, n: int, seed: int) -> DataFrame:
    """n rows without replacement, by the order of a draw."""
    return df.orderBy(u01(seed, "sample", F.col(key)), key).limit(n)


def threshold_sample(df: DataFrame, key: str, share: float, seed: int) -> DataFrame:
    """About a share of the rows, without a sort: for tables of any size, on a hash."""
    return df.filter(F.pmod(F.xxhash64(F.lit(seed), F.col(key)), F.lit(1 << 30)) < int(share * (1 << 30)))


def level_lookup(df: DataFrame, levels: DataFrame, value: str) -> DataFrame:
    """Each row with the level [lo, hi) it falls in; levels are a small stated table."""
    return df.join(F.broadcast(levels.limit(100_000)), (F.col(value) >= F.col("lo")) & (F.col(value) < F.col("hi")), "left")


def unseen(df: DataFrame, column: str, context: DataFrame) -> DataFrame:
    """Rows whose value the context lacks."""
    return df.join(context.select(column).distinct(), column, "left_anti")
