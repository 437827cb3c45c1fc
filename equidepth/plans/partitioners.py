"""Slice ids by other means than the model: equal widths, splitters, sketches, exact ranks, hashes."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .cdf_model import _tree


def radix_pid(code: Column, low: float, high: float, f: int) -> Column:
    """Equal-width intervals of [low, high]."""
    if high <= low:
        return F.when(code.isNotNull(), F.lit(0))
    at = F.floor((code.cast("double") - F.lit(float(low))) / F.lit(float(high) - float(low)) * f).cast("int")
    return F.greatest(F.lit(0), F.least(F.lit(f - 1), at))


def radix_bits_pid(code: Column, code_bits: int, bits: int) -> Column:
    """The leading `bits` of a non-negative integer code of `code_bits` bits: 2**bits slices."""
    return F.shiftright(code.cast("long"), max(code_bits - bits, 0)).cast("int")


def splitters_of(sample: np.ndarray, f: int) -> np.ndarray:
    ordered = np.sort(np.asarray(sample, np.float64))
    if not len(ordered):
        return ordered
    return np.unique(ordered[np.minimum(len(ordered) - 1, (np.arange(1, f) * len(ordered)) // f)])


def quantile_pid(code: Column, sample: np.ndarray, f: int) -> Column:
    """Splitters at the sample's quantiles."""
    return F.when(code.isNotNull(), _tree(code.cast("double"), splitters_of(sample, f)))


def sketch_pid(df: DataFrame, code: Column, f: int, accuracy: int = 10_000) -> Column:
    """Splitters from one approximate-percentile pass over all rows."""
    cuts = [i / f for i in range(1, f)]
    found = df.select(code.cast("double").alias("c")).agg(F.percentile_approx("c", cuts, accuracy)).first()[0] if cuts else []
    return F.when(code.isNotNull(), _tree(code.cast("double"), np.unique(np.array(found or [], np.float64))))


def exact_pid(df: DataFrame, code: Column, f: int) -> DataFrame:
    """df with `pid` by exact ranks (rows of equal code may part): a row's place among all, from slices and the sizes before them."""
    from .extsort import model_sort

    placed = model_sort(df.withColumn("_c", code), ["_c"])
    base, more = divmod(sum(placed.sizes), f)
    r, edge = F.col("_rn") - 1, more * (base + 1)
    pid = F.when(r < edge, F.floor(r / (base + 1))).otherwise(F.lit(more) + F.floor((r - edge) / F.lit(max(base, 1))))
    return placed.with_rn("_rn").withColumn("pid", pid.cast("int")).drop("_c", "_rn")


def hash_pid(key: Column, f: int) -> Column:
    """Even slices that keep no order."""
    return F.pmod(F.xxhash64(key), F.lit(f)).cast("int")
