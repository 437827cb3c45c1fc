"""Generated records: a key of printable characters and a payload, uniform or skewed."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class SkewSpec:
    """A table of `entries` prefixes of `prefix` characters replaces the keys' start for `share` of the rows.

    rule "log2": entry = floor(log2(row)) mod entries; "uniform": any entry, equally likely.
    """

    entries: int = 128
    prefix: int = 6
    share: float = 1.0
    rule: str = "log2"


def _char(*parts: Column) -> Column:
    return F.char(F.pmod(F.xxhash64(*parts), F.lit(95)) + 32)


def generate_records(spark: SparkSession, n: int, *, seed: int = 1, skew: SkewSpec | None = None, key: int = 10, payload: int = 90, parts: int | None = None) -> DataFrame:
    """(rec_idx, key, payload): each key character uniform over 95 characters and independent of the others."""
    rows = spark.range(0, n, 1, parts or max(1, min(n // 50_000 + 1, 10_000))).withColumnRenamed("id", "rec_idx")
    i, s = F.col("rec_idx"), F.lit(seed)
    plain = [_char(i, F.lit(k), s) for k in range(key)]
    if skew is None:
        text = F.concat(*plain)
    else:
        entry = F.pmod(F.floor(F.log2(F.greatest(i, F.lit(1)))), F.lit(skew.entries)) if skew.rule == "log2" else F.pmod(F.xxhash64(i, F.lit("entry"), s), F.lit(skew.entries))
        fixed = [_char(entry, F.lit(k), F.lit("table"), s) for k in range(skew.prefix)]
        hit = F.pmod(F.xxhash64(i, F.lit("share"), s), F.lit(1_000_000)) < int(skew.share * 1_000_000)
        text = F.when(hit, F.concat(*fixed, *plain[skew.prefix :])).otherwise(F.concat(*plain))
    body = F.substring(F.repeat(F.md5(F.concat_ws("-", i.cast("string"), s.cast("string"))), payload // 32 + 1), 1, payload)
    return rows.select("rec_idx", text.alias("key"), body.alias("payload"))


def calibrate_share(spark: SparkSession, n: int, target_percent: float, *, bins: int = 1000, steps: int = 7, **skew) -> float:
    """The share of skewed rows whose 1000-bin deviation comes near target_percent of the mean."""
    from ..measures.metrics import bin_skew, equi_width_histogram
    from ..plans.keys import ascii_code

    low, high = 0.0, 1.0
    for _ in range(steps):
        mid = (low + high) / 2
        df = generate_records(spark, n, skew=SkewSpec(share=mid, **skew)).select(ascii_code(F.col("key")).cast("double").alias("c"))
        got = bin_skew(equi_width_histogram(df, "c", bins, low=0.0, high=float(95**9)), bins).first()["deviation_percent"]
        low, high = (mid, high) if got < target_percent else (low, mid)
    return (low + high) / 2
