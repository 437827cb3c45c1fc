"""Numeric codes of sort keys: whole-stage expressions, monotone in the key's order.

A code only has to be weakly monotone: equal codes share a slice and the in-slice sort compares whole
keys, so a narrow code costs balance and never order.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Printable ASCII is 32..126, that is 95 characters; one more digit marks "no character".
FIRST, BASE, LOW_BASE = 32, 95, 96


def ascii_code(col: Column, width: int = 9, *, variable: bool = False, pad: str = "low") -> Column:
    """Printable ASCII to a long: base 95 over `width` characters.

    variable: shorter keys are padded. pad="low" gives a missing character the digit 0 of base 96, below
    every real one; pad="paper" subtracts the offset from a zero byte, which breaks the order of some
    keys and is kept to show that.
    """
    if pad not in ("low", "paper"):
        raise ValueError("pad is 'low' or 'paper'")
    low = variable and pad == "low"
    base, code = (LOW_BASE if low else BASE), F.lit(0).cast("long")
    for i in range(1, width + 1):
        byte = F.ascii(F.substring(col, i, 1))
        digit = F.when(F.length(col) >= i, byte - (FIRST - 1)).otherwise(0) if low else byte - FIRST
        code = code + digit.cast("long") * F.lit(base ** (width - i)).cast("long")
    return code


def byte_code(col: Column, width: int = 7, skip: int = 0) -> Column:
    """The first `width` UTF-8 bytes after `skip` as a base-256 long; missing bytes are 0, null stays null."""
    raw = F.substring(F.encode(col, "UTF-8"), skip + 1, width)
    return F.conv(F.hex(F.rpad(raw, width, F.lit(bytes(1)))), 16, 10).cast("long")


def code_capacity(width: int, base: int = BASE) -> dict[str, float]:
    """Bits that a code of this width needs: of its largest value, and by the sum with one factor more."""
    top = base**width - 1
    return {"width": width, "base": base, "bits": math.log2(top), "bits_by_sum": math.log2(sum(base**k for k in range(1, width + 1))), "fits": top < 2**63}


def widest(base: int = BASE) -> int:
    """Most characters whose code fits a signed 64-bit integer."""
    return max(w for w in range(1, 64) if base**w - 1 < 2**63)


def common_prefix_len(df: DataFrame, col: str) -> int:
    """Bytes that all values share at the start: those that the least and the greatest share."""
    low, high = df.agg(F.min(col), F.max(col)).first()
    if low is None:
        return 0
    a, b = low.encode(), high.encode()
    return next((i for i, (x, y) in enumerate(zip(a, b, strict=False)) if x != y), min(len(a), len(b)))


@dataclass(frozen=True)
class Order:
    """One column of an ORDER BY."""

    name: str
    descending: bool = False
    nulls_first: bool | None = None

    @property
    def nulls_lead(self) -> bool:
        return (not self.descending) if self.nulls_first is None else self.nulls_first

    def column(self) -> Column:
        c = F.col(self.name)
        if self.descending:
            return c.desc_nulls_first() if self.nulls_lead else c.desc_nulls_last()
        return c.asc_nulls_first() if self.nulls_lead else c.asc_nulls_last()


def orders(by) -> list[Order]:
    """Names, "-name" for descending, or Orders."""
    by = [by] if isinstance(by, (str, Order)) else list(by)
    return [b if isinstance(b, Order) else Order(b.lstrip("-"), b.startswith("-")) for b in by]


@dataclass(frozen=True)
class KeySpec:
    """How the leading sort column becomes a code: kind number, date, time, flag or bytes; skip: shared prefix."""

    order: Order
    kind: str
    skip: int = 0
    width: int = 7

    def level(self, k: int) -> KeySpec:
        """The code of the bytes after the first k codes' bytes."""
        return KeySpec(self.order, self.kind, self.skip + k * self.width, self.width)

    def code(self) -> Column:
        """A double that rises with the order asked for; null where the key is null."""
        c = F.col(self.order.name)
        if self.kind == "bytes":
            out = byte_code(c, self.width, self.skip).cast("double")
        elif self.kind == "date":
            out = F.unix_date(c).cast("double")
        elif self.kind == "time":
            out = F.unix_micros(c.cast("timestamp")).cast("double")
        elif self.kind == "flag":
            out = c.cast("int").cast("double")
        elif self.kind == "double":
            largest = F.lit(1e150)  # beyond it codes tie and the in-slice sort decides
            out = F.when(c.isNotNull(), F.when(F.isnan(c), largest).otherwise(F.greatest(-largest, F.least(largest, c.cast("double")))))
        else:
            out = c.cast("double")
        return -out if self.order.descending else out


def resolve(df: DataFrame, order: Order, *, strip_prefix: bool = True) -> KeySpec:
    """From the column's type; of strings the shared prefix is found by one aggregate and skipped."""
    kind = dict(df.dtypes)[order.name]
    if kind in ("string", "binary"):
        skip = common_prefix_len(df, order.name) if strip_prefix and kind == "string" else 0
        return KeySpec(order, "bytes", skip)
    if kind == "date":
        return KeySpec(order, "date")
    if kind.startswith("timestamp"):
        return KeySpec(order, "time")
    if kind == "boolean":
        return KeySpec(order, "flag")
    if kind in ("float", "double"):
        return KeySpec(order, "double")
    if kind in ("tinyint", "smallint", "int", "bigint") or kind.startswith("decimal"):
        return KeySpec(order, "number")
    raise TypeError(f"cannot sort by {order.name} of type {kind}")


def profile(df: DataFrame, spec: KeySpec) -> dict:
    """Rows, nulls, least and greatest code, in one pass over the key column."""
    code = spec.code()
    r = df.agg(F.count("*").alias("rows"), F.sum(code.isNull().cast("long")).alias("nulls"), F.min(code).alias("low"), F.max(code).alias("high")).first()
    return {"rows": r[0], "nulls": r[1] or 0, "low": r[2], "high": r[3]}


def code_collisions(df: DataFrame, code: Column, col: str) -> DataFrame:
    """Distinct keys, distinct codes, and their ratio."""
    return df.agg(F.countDistinct(col).alias("keys"), F.countDistinct(code).alias("codes")).withColumn("ratio", F.col("codes") / F.col("keys"))
