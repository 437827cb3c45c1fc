"""Duplicates and set operations on sliced rows."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.extsort import PID, model_sort, train_for, with_slices
from ..plans.keys import Order, orders, resolve


def model_distinct(df: DataFrame, cols: list[str] | None = None, *, f: int = 16) -> DataFrame:
    """Distinct rows of cols: equal rows share the leading column's slice. Where a leading value is heavier than a slice, repeats go before the exchange."""
    cols = cols or df.columns
    sf = model_sort(df.select(*cols), cols[:1], f=f)
    if sf.model.heaviest * f > 1:
        return sf.sliced.dropDuplicates([PID, *cols]).select(*cols)
    return sf.exchanged.dropDuplicates([PID, *cols]).select(*cols)


def dedup_keep_first(df: DataFrame, key: str, order, *, f: int = 16) -> DataFrame:
    """The first row of each key by order; null is a key. Rising orders go by least rows, found in part before the exchange; others by slices."""
    from pyspark.sql import Window

    by = orders(order)
    if all(o.nulls_lead and not o.descending for o in by) and dict(df.dtypes)[key] == "string":
        # by digest: 16 bytes and the length are compared instead of whole keys
        marks = [F.md5(F.col(key)).alias("_d"), F.length(key).alias("_n")]
        row = F.struct(*[F.col(o.name).alias(f"o{i}") for i, o in enumerate(by)], *[F.col(c).alias(f"c{i}") for i, c in enumerate(df.columns)])
        first = df.select(*marks, row.alias("_r")).groupBy("_d", "_n").agg(F.min("_r").alias("_r"))
        return first.select(*[F.col(f"_r.c{i}").alias(c) for i, c in enumerate(df.columns)])
    sf = model_sort(df, [key], f=f)
    w = Window.partitionBy(PID, key).orderBy(*[o.column() for o in orders(order)])
    return sf.exchanged.withColumn("_n", F.row_number().over(w)).filter(F.col("_n") == 1).select(*df.columns)


def _same(l: str, r: str, cols: list[str]) -> Column:
    return reduce(lambda a, b: a & b, [F.col(f"{l}.{c}").eqNullSafe(F.col(f"{r}.{c}")) for c in cols])


def _semi(left: DataFrame, right: DataFrame, how: str, f: int) -> DataFrame:
    cols = left.columns
    spec = resolve(left, Order(cols[0]), strip_prefix=False)
    model, _ = train_for(left, spec)
    # repeats go before the exchange
    l = with_slices(left.distinct(), spec, model, f).repartitionById(f, F.col(PID)).alias("l")
    r = with_slices(right.toDF(*cols).distinct(), spec, model, f).repartitionById(f, F.col(PID)).alias("r")
    joined = l.join(r, (F.col(f"l.{PID}") == F.col(f"r.{PID}")) & _same("l", "r", cols), how)
    return joined.select(*[F.col(f"l.{c}") for c in cols])


def model_intersect(left: DataFrame, right: DataFrame, *, f: int = 16) -> DataFrame:
    """Distinct rows that both hold; nulls equal each other."""
    return _semi(left, right, "left_semi", f)


def model_except(left: DataFrame, right: DataFrame, *, f: int = 16) -> DataFrame:
    """Distinct rows of left that right lacks; nulls equal each other."""
    return _semi(left, right, "left_anti", f)
