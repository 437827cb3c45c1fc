"""Whole-table ranks, neighbours and running sums from slices and their offsets: no global window.

Equal leading keys share a slice, so a rank inside the slice plus what lies before the slice is the rank in
the whole.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.extsort import PID, SortedFrame
from ..plans.keys import Order


def _leading(sf: SortedFrame, keys: int) -> list[Order]:
    return sf.by[:keys]


def _spread(sf: SortedFrame, numbered: DataFrame) -> DataFrame:
    return numbered.join(F.broadcast(sf.offsets_frame().select(PID, "row_offset")), PID)  # f rows


def global_row_number(sf: SortedFrame, name: str = "rn") -> DataFrame:
    return sf.with_rn(name)


def _by_counts(sf: SortedFrame, keys: int, most: int = 100_000) -> DataFrame | None:
    """Rows with _upto, the rows up to their key's last, and _same, those of their key; None where there are more than `most` keys.

    Counts by key suffice for them: no row is exchanged or sorted, however many a key has.
    """
    names = [o.name for o in _leading(sf, keys)]
    counts = sf.sliced.groupBy(PID, *names).agg(F.count("*").alias("_same"))
    if counts.limit(most + 1).count() > most:
        return None
    upto = F.sum("_same").over(sf.window(_leading(sf, keys)).rowsBetween(Window.unboundedPreceding, Window.currentRow))
    table = _spread(sf, counts.withColumn("_in", upto)).select(*[F.col(n).alias(f"_k{i}") for i, n in enumerate(names)], "_same", (F.col("row_offset") + F.col("_in")).alias("_upto"))
    on = [F.col(n).eqNullSafe(F.col(f"_k{i}")) for i, n in enumerate(names)]
    return sf.sliced.join(F.broadcast(table), on)  # at most `most` rows


def global_rank(sf: SortedFrame, keys: int = 1, name: str = "rnk") -> DataFrame:
    """rank() over the first `keys` sort columns."""
    few = _by_counts(sf, keys)
    if few is not None:
        return few.select(*sf.columns, (F.col("_upto") - F.col("_same") + 1).cast("long").alias(name))
    numbered = sf.exchanged.withColumn("_k", F.rank().over(sf.window(_leading(sf, keys))))
    return _spread(sf, numbered).select(*sf.columns, (F.col("row_offset") + F.col("_k")).cast("long").alias(name))


def global_dense_rank(sf: SortedFrame, keys: int = 1, name: str = "drnk") -> DataFrame:
    """dense_rank(): distinct keys before the slice come from a count by slice."""
    names = [o.name for o in _leading(sf, keys)]
    found = {r[0]: r[1] for r in sf.sliced.select(PID, *names).distinct().groupBy(PID).count().collect()}
    rows, before = [], 0
    for i in range(sf.f):
        rows.append((i, before))
        before += found.get(i, 0)
    starts = sf.spark.createDataFrame(rows, f"{PID} int, _before long")
    numbered = sf.exchanged.withColumn("_k", F.dense_rank().over(sf.window(_leading(sf, keys))))
    return numbered.join(F.broadcast(starts), PID).select(*sf.columns, (F.col("_before") + F.col("_k")).cast("long").alias(name))


def global_percent_rank(sf: SortedFrame, keys: int = 1, name: str = "prnk") -> DataFrame:
    n = sum(sf.sizes)
    ranked = global_rank(sf, keys, "_r")
    return ranked.select(*sf.columns, (F.when(F.lit(n) > 1, (F.col("_r") - 1) / F.lit(float(max(n - 1, 1)))).otherwise(0.0)).alias(name))


def global_cume_dist(sf: SortedFrame, keys: int = 1, name: str = "cdist") -> DataFrame:
    """Share of rows at or before the key."""
    few = _by_counts(sf, keys)
    if few is not None:
        return few.select(*sf.columns, (F.col("_upto") / F.lit(float(max(sum(sf.sizes), 1)))).alias(name))
    w = sf.window(_leading(sf, keys)).rangeBetween(Window.unboundedPreceding, Window.currentRow)
    numbered = sf.exchanged.withColumn("_k", F.count(F.lit(1)).over(w))
    n = float(max(sum(sf.sizes), 1))
    return _spread(sf, numbered).select(*sf.columns, ((F.col("row_offset") + F.col("_k")) / F.lit(n)).alias(name))


def global_ntile(sf: SortedFrame, k: int, name: str = "tile") -> DataFrame:
    """ntile(k): the first n mod k tiles take one row more."""
    n = sum(sf.sizes)
    base, more = divmod(n, k)
    r = F.col("_rn") - 1
    edge = more * (base + 1)
    late = F.lit(more) + F.floor((r - edge) / F.lit(max(base, 1)))
    tile = F.when(r < edge, F.floor(r / (base + 1))).otherwise(late) + 1
    return sf.with_rn("_rn").select(*sf.columns, F.col("_rn").alias("rn"), tile.cast("int").alias(name))


def global_lag(sf: SortedFrame, col: str, k: int = 1, name: str = "prev", lead: bool = False) -> DataFrame:
    """The column's value k rows before (or after) in the whole, with rn.

    In-slice neighbours come from the slice; the k rows at each slice's border (f * k rows in all) are joined
    by place.
    """
    w = sf.window()
    offset = (F.lead if lead else F.lag)(F.struct(F.col(col).alias("v")), k).over(w)
    numbered = _spread(sf, sf.exchanged.withColumns({"_k": F.row_number().over(w), "_near": offset}))
    placed = numbered.withColumn("rn", (F.col("row_offset") + F.col("_k")).cast("long"))
    sizes = sf.spark.createDataFrame(list(enumerate(sf.sizes)), f"{PID} int, _size long")
    border = F.col("_k") <= k if lead else F.col("_k") > F.col("_size") - k
    edges = placed.join(F.broadcast(sizes), PID).filter(border).select((F.col("rn") + (-k if lead else k)).alias("_to"), F.col(col).alias("_far"))
    joined = placed.join(F.broadcast(edges), placed["rn"] == edges["_to"], "left")  # at most f * k rows
    return joined.select(*sf.columns, "rn", F.when(F.col("_near").isNotNull(), F.col("_near.v")).otherwise(F.col("_far")).alias(name))


def global_running(sf: SortedFrame, value: Column, name: str = "running") -> DataFrame:
    """Sum of value over all rows up to this one, with rn."""
    found = {r[0]: r[1] for r in sf.sliced.groupBy(PID).agg(F.sum(value)).collect()}
    rows, before = [], 0
    for i in range(sf.f):
        rows.append((i, before))
        before += found.get(i) or 0
    kind = sf.sliced.select(F.sum(value).alias("s")).schema[0].dataType.simpleString()
    starts = sf.spark.createDataFrame(rows, f"{PID} int, _before {kind}")
    inside = F.sum(value).over(sf.window().rowsBetween(Window.unboundedPreceding, Window.currentRow))
    numbered = _spread(sf, sf.exchanged.withColumns({"_k": F.row_number().over(sf.window()), "_in": inside}))
    return numbered.join(F.broadcast(starts), PID).select(*sf.columns, (F.col("row_offset") + F.col("_k")).cast("long").alias("rn"), (F.col("_before") + F.coalesce("_in", F.lit(0))).cast(kind).alias(name))


def top_k(sf: SortedFrame, k: int) -> DataFrame:
    """The first k rows with rn: only slices that hold them are exchanged and sorted."""
    return limit_offset(sf, 0, k)


def limit_offset(sf: SortedFrame, offset: int, k: int) -> DataFrame:
    """Rows offset + 1 .. offset + k of the order, with rn."""
    before, need = 0, []
    for i, n in enumerate(sf.sizes):
        if before < offset + k and before + n > offset:
            need.append(i)
        before += n
    if not need:
        return sf.with_rn().limit(0)
    part = sf.slice_range(need[0], need[-1])
    skipped = sum(sf.sizes[: need[0]])
    inside = part.with_rn("_r").withColumn("rn", F.col("_r") + skipped)
    return inside.filter(F.col("rn").between(offset + 1, offset + k)).select(*sf.columns, "rn")


def exact_percentile(sf: SortedFrame, qs: list[float]) -> DataFrame:
    """(q, value): the least value whose share of non-null rows at or below is at least q; only its slice is sorted."""
    key = sf.by[0].name
    nulls = sf.sliced.filter(F.col(key).isNull()).groupBy(PID).count().collect()
    none = {r[0]: r[1] for r in nulls}
    sizes = [n - none.get(i, 0) for i, n in enumerate(sf.sizes)]
    n, parts = sum(sizes), []
    for q in qs:
        target, before = max(1, -(-int(q * n * 1_000_000) // 1_000_000)), 0
        for i, size in enumerate(sizes):
            if before + size >= target and size:
                counts = sf.slice_range(i, i).sliced.filter(F.col(key).isNotNull()).groupBy(key).agg(F.count("*").alias("_n"))
                w = Window.orderBy(sf.by[0].column()).rowsBetween(Window.unboundedPreceding, Window.currentRow)  # the distinct values of one slice
                reached = counts.withColumn("_k", F.sum("_n").over(w)).filter((F.col("_k") >= target - before) & (F.col("_k") - F.col("_n") < target - before))
                parts.append(reached.select(F.lit(q).alias("q"), F.col(key).alias("value")))
                break
            before += size
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out
