"""Grouping: by slices (ordered, one exchange of rows) or by hash (partial sums before the exchange)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.extsort import PID, SortedFrame, model_sort


def model_group_by(df: DataFrame, keys: list[str], aggs: list[Column], *, f: int = 16, **options) -> DataFrame:
    """Groups made inside slices of the first key: the groups of slice i come before those of i + 1.

    For keys with few rows each, where partial sums would not shrink what is exchanged. Where the sample shows a key heavier than a
    slice, partial sums come first and the groups are dealt to their slices.
    """
    sf = model_sort(df, keys, f=f, **options)
    if sf.model.heaviest * f > 1:
        groups = sf.sliced.groupBy(PID, *keys).agg(*aggs)
        return groups.repartitionById(f, F.col(PID)).drop(PID)
    return sf.exchanged.groupBy(PID, *keys).agg(*aggs).drop(PID)


def hash_group_by(df: DataFrame, keys: list[str], aggs: list[Column]) -> DataFrame:
    """Partial sums first: for keys with many rows each."""
    return df.groupBy(*keys).agg(*aggs)


def heavy_keys(df: DataFrame, key: str, k: int) -> DataFrame:
    """The k most frequent keys; ties by key."""
    return df.groupBy(key).agg(F.count("*").alias("n")).orderBy(F.desc("n"), F.col(key).asc_nulls_last()).limit(k)


def heavy_share(df: DataFrame, key: str, rate: float = 0.01, seed: int = 42) -> float:
    """Estimated share of the heaviest key, from a sample."""
    r = df.select(key).sample(rate, seed).groupBy(key).count().agg(F.max("count"), F.sum("count")).first()
    return float(r[0] or 0) / float(r[1] or 1)


def salted_group_by(df: DataFrame, keys: list[str], sums: list[str], *, salts: int = 16) -> DataFrame:
    """Sums in two steps, for keys so heavy that one reducer would take most rows."""
    salt = F.pmod(F.xxhash64(*df.columns), F.lit(salts))
    first = df.withColumn("_s", salt).groupBy(*keys, "_s").agg(*[F.sum(c).alias(c) for c in sums], F.count("*").alias("_n"))
    return first.groupBy(*keys).agg(*[F.sum(c).alias(c) for c in sums], F.sum("_n").alias("n"))


def approx_percentile(df: DataFrame, col: str, qs: list[float], accuracy: int = 10_000) -> DataFrame:
    found = df.agg(F.percentile_approx(col, qs, accuracy).alias("v"))
    return found.select(F.posexplode("v").alias("i", "value")).select(F.element_at(F.array(*[F.lit(q) for q in qs]), F.col("i") + 1).alias("q"), "value")


def kll_percentile(df: DataFrame, col: str, qs: list[float], k: int = 200) -> DataFrame:
    """(q, value) from a mergeable quantile sketch of fixed size, made in part before the exchange."""
    sketch = df.agg(F.kll_sketch_agg_double(F.col(col).cast("double"), k).alias("s"))
    pairs = F.array(*[F.struct(F.lit(float(q)).alias("q"), F.kll_sketch_get_quantile_double("s", F.lit(float(q))).alias("value")) for q in qs])
    return sketch.select(F.explode(pairs).alias("p")).select("p.q", "p.value")


def approx_distinct(df: DataFrame, col: str, rsd: float = 0.02) -> DataFrame:
    return df.agg(F.approx_count_distinct(col, rsd).alias("n"))


def grouping_sets(df: DataFrame, sets: list[list[str]], columns: list[str], aggs: list[Column]) -> DataFrame:
    """One row for each group of each set; columns outside a set are null."""
    return df.groupingSets([[F.col(c) for c in s] for s in sets], *[F.col(c) for c in columns]).agg(*aggs)


def slices_of(sf: SortedFrame) -> DataFrame:
    """(_pid, rows)."""
    return sf.sliced.groupBy(PID).agg(F.count("*").alias("rows"))
