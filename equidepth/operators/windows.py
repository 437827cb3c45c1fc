"""Windows over keys with many groups: ranks, frames and sessions by Spark's own window functions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.keys import orders


def running(df: DataFrame, by: list[str], order, value: Column, name: str = "running") -> DataFrame:
    w = Window.partitionBy(*by).orderBy(*[o.column() for o in orders(order)]).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return df.withColumn(name, F.sum(value).over(w))


def moving_avg_rows(df: DataFrame, by: list[str], order, value: Column, before: int, after: int = 0, name: str = "moving") -> DataFrame:
    w = Window.partitionBy(*by).orderBy(*[o.column() for o in orders(order)]).rowsBetween(-before, after)
    return df.withColumn(name, F.avg(value).over(w))


def range_frame(df: DataFrame, by: list[str], order: Column, agg: Column, before: int, after: int, name: str) -> DataFrame:
    """agg over rows whose order value lies within [-before, +after] of the row's; order must be a number."""
    return df.withColumn(name, agg.over(Window.partitionBy(*by).orderBy(order).rangeBetween(-before, after)))


def sessionize(df: DataFrame, by: str, ts: str, gap_seconds: int) -> DataFrame:
    """df with `session`, counted from 1 in each key: a new one where the pause is longer than the gap."""
    w = Window.partitionBy(by).orderBy(ts)
    pause = F.unix_micros(F.col(ts).cast("timestamp")) - F.unix_micros(F.lag(ts).over(w).cast("timestamp"))
    fresh = df.withColumn("_new", F.when(pause.isNull() | (pause > gap_seconds * 1_000_000), 1).otherwise(0))
    return fresh.withColumn("session", F.sum("_new").over(w.rangeBetween(Window.unboundedPreceding, Window.currentRow)).cast("long")).drop("_new")


def partitioned_ranks(df: DataFrame, by: list[str], order, ranked, tiles: int) -> DataFrame:
    """df with rn and tile by `order`, and rnk, drnk, prnk, cdist by `ranked`, in each group."""
    w, r = (Window.partitionBy(*by).orderBy(*[o.column() for o in orders(x)]) for x in (order, ranked))
    return df.withColumns({"rn": F.row_number().over(w), "tile": F.ntile(tiles).over(w), "rnk": F.rank().over(r), "drnk": F.dense_rank().over(r), "prnk": F.percent_rank().over(r), "cdist": F.cume_dist().over(r)})


def partitioned_values(df: DataFrame, by: list[str], order, value: str, nth: int, k: int) -> DataFrame:
    """df with the first, last and nth value of its group by `order`, and those k rows before and after."""
    w = Window.partitionBy(*by).orderBy(*[o.column() for o in orders(order)])
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return df.withColumns({"first": F.first(value).over(whole), "last": F.last(value).over(whole), "nth": F.nth_value(value, nth).over(whole), "lag": F.lag(value, k).over(w), "lead": F.lead(value, k).over(w)})
