"""Is it sorted, is it the same rows, do slices follow each other?"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.extsort import PID, SortedFrame
from ..plans.keys import orders


def checksum(df: DataFrame, cols: list[str] | None = None) -> DataFrame:
    """(rows, total, mixed): equal for equal multisets of rows, whatever their order."""
    h = F.xxhash64(*[F.col(c) for c in (cols or df.columns)])
    return df.agg(F.count("*").alias("rows"), F.coalesce(F.sum(h.cast("decimal(38,0)")), F.lit(0).cast("decimal(38,0)")).alias("total"), F.coalesce(F.bit_xor(h), F.lit(0)).alias("mixed"))


def check_sorted(placed: DataFrame, by, rn: str = "rn") -> DataFrame:
    """(rows, gaps, unordered, dups) of rows with their place.

    Places are cut into runs; neighbours inside a run are compared there, and each run's first row is also
    sent to the run before, so no window spans more than a run.
    """
    run = 100_000
    names = [o.name for o in orders(by)]
    rows = placed.select(*dict.fromkeys(names), F.col(rn).alias("_rn"))
    home = rows.withColumn("_run", F.floor((F.col("_rn") - 1) / run))
    edge = home.filter((F.col("_rn") - 1) % run == 0).withColumn("_run", F.col("_run") - 1)
    both = home.unionByName(edge)
    w = Window.partitionBy("_run").orderBy("_rn")
    nxt = F.lead(F.struct("_rn", *names)).over(w)
    seen = both.withColumn("_n", nxt)
    wrong, same = F.lit(False), F.lit(True)
    for o in orders(by):
        a, b = F.col(o.name), F.col(f"_n.{o.name}")
        a_first, b_first = (a.isNull(), b.isNull()) if o.nulls_lead else (a.isNotNull() & b.isNull(), b.isNotNull() & a.isNull())
        worse = F.when(a.isNull() | b.isNull(), (b_first & ~a_first) if o.nulls_lead else (~a.isNotNull() & b.isNotNull())).otherwise((b > a) if o.descending else (b < a))
        wrong = wrong | (same & F.coalesce(worse, F.lit(False)))
        same = same & a.eqNullSafe(b)
    has = F.col("_n").isNotNull()
    counted = seen.agg(
        F.sum((has & (F.col("_n._rn") != F.col("_rn") + 1)).cast("long")).alias("gaps"), F.sum((has & wrong).cast("long")).alias("unordered"), F.sum((has & same).cast("long")).alias("dups"),
    )
    return rows.agg(F.count("*").alias("rows")).crossJoin(counted).select("rows", *[F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("gaps", "unordered", "dups")])


def invariant_violations(df: DataFrame, key: Column, pid: str | Column = PID) -> DataFrame:
    """(violations): neighbouring non-empty slices whose key ranges overlap."""
    bounds = df.select(key.alias("k"), (F.col(pid) if isinstance(pid, str) else pid).alias("p")).filter(F.col("k").isNotNull()).groupBy("p").agg(F.min("k").alias("low"), F.max("k").alias("high"))
    before = F.max("high").over(Window.orderBy("p").rowsBetween(Window.unboundedPreceding, -1))  # one row a slice
    return bounds.withColumn("b", before).agg(F.coalesce(F.sum((F.col("b") > F.col("low")).cast("long")), F.lit(0)).alias("violations"))


def validate_all(df: DataFrame, sf: SortedFrame) -> DataFrame:
    """(rows, unordered, gaps, same_rows, violations) of a sort of df."""
    placed = sf.with_rn()
    a, b = checksum(df), checksum(placed.select(*sf.columns), df.columns)
    same = a.crossJoin(b.toDF("r2", "t2", "m2")).select(((F.col("rows") == F.col("r2")) & (F.col("total") == F.col("t2")) & (F.col("mixed") == F.col("m2"))).alias("same_rows"))
    v = invariant_violations(sf.sliced.withColumn("_code", sf.spec.code()), F.col("_code")) if sf.spec else df.sparkSession.createDataFrame([(0,)], "violations long")
    return check_sorted(placed, sf.by).crossJoin(same).crossJoin(v)
