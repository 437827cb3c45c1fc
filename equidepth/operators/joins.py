"""Joins: sides sliced by one model meet slice by slice; intervals and nearest keys use the slices' order."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.cdf_model import CdfModel
from ..plans.extsort import PID, train_for, with_slices
from ..plans.keys import KeySpec, Order, resolve
from ..plans.sampling import SampleSpec
from ..session import written


def shared_model(left: DataFrame, lkey: str, right: DataFrame, rkey: str, sample: SampleSpec = SampleSpec()) -> tuple[CdfModel, KeySpec, KeySpec]:
    """One model, and code specs of both sides that mean the same."""
    ls, rs = resolve(left, Order(lkey), strip_prefix=False), resolve(right, Order(rkey), strip_prefix=False)
    both = left.select(F.col(lkey).alias("k")).unionByName(right.select(F.col(rkey).alias("k")))
    model, _ = train_for(both, KeySpec(Order("k"), ls.kind, 0, ls.width), sample=sample)
    return model, ls, rs


def _heavy_pairs(left: DataFrame, lkey: str, right: DataFrame, rkey: str, model: CdfModel, f: int, sample: SampleSpec) -> DataFrame | None:
    """(_hk, _salts): keys that both sides hold and that fill more than a slice on either; None where the model saw no such key."""
    if model.heaviest * f <= 1:
        return None
    l, r = (d.groupBy(F.col(k).alias("_hk")).agg(F.count("*").alias(n)) for d, k, n in ((left.filter(F.col(lkey).isNotNull()), lkey, "_nl"), (right.filter(F.col(rkey).isNotNull()), rkey, "_nr")))
    sizes = [d.agg(F.sum(n)).first()[0] or 0 for d, n in ((l, "_nl"), (r, "_nr"))]
    met = l.join(r, "_hk").filter((F.col("_nl") * f > sizes[0]) | (F.col("_nr") * f > sizes[1]))  # fewer than 2 f keys
    salts = F.greatest(F.ceil(F.col("_nl") * f / F.lit(float(max(sizes[0], 1)))), F.ceil(F.col("_nr") * f / F.lit(float(max(sizes[1], 1)))))
    return met.select("_hk", salts.cast("int").alias("_salts"))


def model_merge_join(left: DataFrame, right: DataFrame, lkey: str, rkey: str, how: str = "inner", *, f: int = 16, condition: Column | None = None) -> DataFrame:
    """Both sides are dealt by the same model and merge-joined on (slice, key) without a further exchange.

    Keys that fill more than a slice and that both sides hold are joined on their own: the side with more rows of them is spread over salts
    and the other copied to each (not where a further condition could leave an outer row of such a key alone).
    Column names of the sides must differ. Null keys match nothing.
    """
    model, ls, rs = shared_model(left, lkey, right, rkey)
    heavy = None if condition is not None and how != "inner" else _heavy_pairs(left, lkey, right, rkey, model, f, SampleSpec())
    if heavy is not None:
        keys = written(heavy, "heavy-keys")
        few = F.broadcast(keys)  # fewer than 2 f keys
        rest = _dealt_join(left.join(few, F.col(lkey) == F.col("_hk"), "left_anti"), right.join(few, F.col(rkey) == F.col("_hk"), "left_anti"), lkey, rkey, how, model, ls, rs, f, condition)
        if how == "left_anti":
            return rest  # a heavy key has a match
        if how == "left_semi":
            return rest.unionByName(left.join(few, F.col(lkey) == F.col("_hk"), "left_semi"))
        l = left.join(few, F.col(lkey) == F.col("_hk")).withColumn("_ls", F.pmod(F.xxhash64(*left.columns), F.col("_salts"))).drop("_hk", "_salts")
        r = right.join(few, F.col(rkey) == F.col("_hk")).withColumn("_rs", F.explode(F.sequence(F.lit(0).cast("long"), F.col("_salts").cast("long") - 1))).drop("_hk", "_salts")
        # the salts of a key go to partitions of their own
        l = l.withColumn("_lp", F.pmod(F.xxhash64(lkey) + F.col("_ls"), F.lit(f)).cast("int")).repartitionById(f, F.col("_lp"))
        r = r.withColumn("_rp", F.pmod(F.xxhash64(rkey) + F.col("_rs"), F.lit(f)).cast("int")).repartitionById(f, F.col("_rp"))
        on = (F.col("_lp") == F.col("_rp")) & (F.col(lkey) == F.col(rkey)) & (F.col("_ls") == F.col("_rs"))
        return rest.unionByName(l.join(r.hint("merge"), on if condition is None else on & condition).drop("_ls", "_rs", "_lp", "_rp"))
    return _dealt_join(left, right, lkey, rkey, how, model, ls, rs, f, condition)


def _dealt_join(left: DataFrame, right: DataFrame, lkey: str, rkey: str, how: str, model: CdfModel, ls: KeySpec, rs: KeySpec, f: int, condition: Column | None) -> DataFrame:
    l = with_slices(left, ls, model, f).withColumnRenamed(PID, "_lp").repartitionById(f, F.col("_lp"))
    r = with_slices(right, rs, model, f).withColumnRenamed(PID, "_rp").repartitionById(f, F.col("_rp"))
    on = (F.col("_lp") == F.col("_rp")) & (F.col(lkey) == F.col(rkey))
    if condition is not None:
        on = on & condition
    return l.join(r.hint("merge"), on, how).drop("_lp", "_rp")


def broadcast_join(left: DataFrame, right: DataFrame, on, how: str = "inner", *, max_rows: int = 1_000_000) -> DataFrame:
    """Broadcasts the right side where its counted rows keep within max_rows, else leaves the choice to Spark."""
    small = right.limit(max_rows + 1).count() <= max_rows
    return left.join(F.broadcast(right) if small else right, on, how)


def hash_join(left: DataFrame, right: DataFrame, on, how: str = "inner") -> DataFrame:
    return left.join(right.hint("shuffle_hash"), on, how)


def builtin_merge_join(left: DataFrame, right: DataFrame, on, how: str = "inner") -> DataFrame:
    return left.join(right.hint("merge"), on, how)


def theta_join(left: DataFrame, right: DataFrame, condition: Column, *, max_rows: int = 100_000) -> DataFrame:
    """Any condition, by nested loops; the right side must be small (counted)."""
    if right.limit(max_rows + 1).count() > max_rows:
        raise ValueError(f"the right side of a theta join is held to {max_rows} rows")
    return left.crossJoin(F.broadcast(right)).filter(condition)


def range_join(points: DataFrame, point: str, intervals: DataFrame, low: str, high: str, *, f: int = 16, sample: SampleSpec = SampleSpec()) -> DataFrame:
    """Points with the intervals [low, high] that hold them: an interval is copied to the slices that it crosses."""
    ps = resolve(points, Order(point), strip_prefix=False)
    model, _ = train_for(points, ps, sample=sample)
    p = with_slices(points.filter(F.col(point).isNotNull()), ps, model, f)
    a, b = (resolve(intervals, Order(c), strip_prefix=False) for c in (low, high))
    i = intervals.filter(F.col(low).isNotNull() & F.col(high).isNotNull() & (F.col(low) <= F.col(high))).withColumns({"_a": a.code(), "_b": b.code()})
    i = i.withColumn("_ip", F.explode(F.sequence(model.pid(F.col("_a"), f), model.pid(F.col("_b"), f)))).drop("_a", "_b")
    joined = p.join(i, (F.col(PID) == F.col("_ip")) & (F.col(point) >= F.col(low)) & (F.col(point) <= F.col(high)))
    return joined.drop(PID, "_ip")


def band_join(left: DataFrame, lkey: str, right: DataFrame, rkey: str, eps: float, *, f: int = 16) -> DataFrame:
    """Pairs with |lkey - rkey| <= eps."""
    spans = right.withColumns({"_low": F.col(rkey) - eps, "_high": F.col(rkey) + eps})
    return range_join(left, lkey, spans, "_low", "_high", f=f).drop("_low", "_high")


def asof_join(left: DataFrame, right: DataFrame, on: str, by: str, value: str, *, direction: str = "backward", tolerance=None, f: int = 16) -> DataFrame:
    """left with the right side's `value` (and its key, right_on) of the same `by` at the nearest `on` not after (before) it.

    Sides are laid together, sliced by one model and filled inside slices; what a slice lacks comes from the
    last (first) right row of each `by` before (after) it: a row for each slice and key that occur together.
    """
    back = direction == "backward"
    model, ls, rs = shared_model(left, on, right, on)
    names = left.columns
    l = with_slices(left.filter(F.col(on).isNotNull()), ls, model, f).withColumns({"_right": F.lit(False), "_v": F.lit(None).cast(dict(right.dtypes)[value])})
    r = with_slices(right.filter(F.col(on).isNotNull()), rs, model, f).select(F.col(on), F.col(by), F.col(value).alias("_v"), PID, F.lit(True).alias("_right"))
    both = l.unionByName(r, allowMissingColumns=True).repartitionById(f, F.col(PID))
    seen = F.when(F.col("_right"), F.struct(F.col(on).alias("k"), F.col("_v").alias("v")))
    w = Window.partitionBy(PID, by).orderBy(F.col(on).asc() if back else F.col(on).desc(), F.col("_right").desc(), F.col("_v").asc_nulls_first())
    filled = both.withColumn("_m", F.last(seen, ignorenulls=True).over(w.rowsBetween(Window.unboundedPreceding, 0)))
    pick = F.max if back else F.min
    ends = r.groupBy(PID, by).agg(pick(F.struct(F.col(on).alias("k"), F.col("_v").alias("v"))).alias("_e"))
    carry = Window.partitionBy(by).orderBy(F.col(PID) if back else F.col(PID).desc())
    asked = l.select(PID, by).distinct().withColumn("_e", F.lit(None).cast(ends.schema["_e"].dataType))
    cells = ends.unionByName(asked).groupBy(PID, by).agg(F.first("_e", ignorenulls=True).alias("_e"))
    carried = cells.withColumn("_c", F.last("_e", ignorenulls=True).over(carry.rowsBetween(Window.unboundedPreceding, -1))).select(PID, by, "_c")
    found = filled.filter(~F.col("_right")).join(carried, [PID, by], "left").withColumn("_m", F.coalesce("_m", "_c"))
    right_on, got = F.col("_m.k"), F.col("_m.v")
    if tolerance is not None:
        near = (F.col(on) - right_on if back else right_on - F.col(on)) <= tolerance
        right_on, got = F.when(near, right_on), F.when(near, got)
    return found.select(*names, right_on.alias("right_on"), got.alias(f"right_{value}"))
