"""Measures: rates, balance, skew, model error, costs and counters of a run."""

from __future__ import annotations

import math
import time
from contextlib import contextmanager
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.cdf_model import CdfModel


# ---- rates -----------------------------------------------------------------------------------------

def sort_rate(size_bytes: float, seconds: float) -> float:
    """MB a second, start and end included."""
    return size_bytes / 1e6 / seconds if seconds > 0 else math.inf


def relative(a: float, b: float) -> dict[str, float]:
    """a against b: the ratio, how many percent higher, how many percent b is lower."""
    return {"ratio": a / b, "higher_percent": (a / b - 1) * 100, "lower_percent": (1 - b / a) * 100}


def bandwidth_gap(rate: float, copy_rate: float) -> float:
    """Part of the copy rate that the sort does not reach."""
    return 1 - rate / copy_rate


def skew_drop(uniform: float, skewed: float) -> float:
    """Percent by which the rate falls on skewed data (negative: rises)."""
    return (1 - skewed / uniform) * 100


def scale_curve(runs: list[tuple[float, float]]) -> dict:
    """(size, rate) in rising size: the drop of each step, their mean, and the whole drop, in percent."""
    runs = sorted(runs)
    steps = [(1 - b[1] / a[1]) * 100 for a, b in zip(runs, runs[1:], strict=False)]
    return {"steps": steps, "mean_drop": sum(steps) / len(steps) if steps else 0.0, "total_drop": (1 - runs[-1][1] / runs[0][1]) * 100 if runs else 0.0}


def energy(seconds: float, watts: float) -> float:
    """Joules of a run at a given mean power: modelled, nothing is metered."""
    return seconds * watts


def repeat(fn, times: int = 5, spark: SparkSession | None = None) -> list[float]:
    """Seconds of each of `times` runs, caches cleared before each."""
    out = []
    for _ in range(times):
        if spark is not None:
            spark.catalog.clearCache()
        began = time.perf_counter()
        fn()
        out.append(time.perf_counter() - began)
    return out


# ---- balance and skew ------------------------------------------------------------------------------

def slice_stats(df: DataFrame, pid: Column | str, f: int) -> DataFrame:
    """(slices, min, max, mean, var, cv, max_over_mean, empty) of slice sizes; empty slices count."""
    p = F.col(pid) if isinstance(pid, str) else pid
    counts = df.select(p.alias("p")).groupBy("p").agg(F.count("*").alias("n"))
    all_slices = df.sparkSession.range(f).select(F.col("id").cast("int").alias("p")).join(counts, "p", "left").select(F.coalesce("n", F.lit(0)).cast("double").alias("n"))
    return all_slices.agg(
        F.count("*").alias("slices"), F.min("n").cast("long").alias("min"), F.max("n").cast("long").alias("max"), F.avg("n").alias("mean"), F.var_pop("n").alias("var"),
        (F.stddev_pop("n") / F.avg("n")).alias("cv"), (F.max("n") / F.avg("n")).alias("max_over_mean"), F.sum((F.col("n") == 0).cast("long")).alias("empty"),
    )


def variance_reduction(model: float, other: float) -> float:
    """Percent by which the model's variance is below another's."""
    return (1 - model / other) * 100 if other else 0.0


def equi_width_histogram(df: DataFrame, col: str, bins: int = 1000, *, low: float | None = None, high: float | None = None) -> DataFrame:
    """(bin, n, frequency) of the non-empty bins between the least and greatest value."""
    if low is None or high is None:
        r = df.agg(F.min(col), F.max(col)).first()
        low, high = (float(r[0]), float(r[1])) if r[0] is not None else (0.0, 1.0)
    width = (high - low) or 1.0
    at = F.greatest(F.lit(0), F.least(F.lit(bins - 1), F.floor((F.col(col).cast("double") - F.lit(low)) / F.lit(width) * bins))).cast("int")
    counts = df.filter(F.col(col).isNotNull()).groupBy(at.alias("bin")).agg(F.count("*").alias("n"))
    return counts.withColumn("frequency", F.col("n") / F.sum("n").over(Window.partitionBy()))  # at most `bins` rows


def bin_skew(histogram: DataFrame, bins: int = 1000) -> DataFrame:
    """(deviation_percent, max_over_mean, filled): spread of bin sizes in percent of their mean."""
    s, q, m = F.sum("n"), F.sum(F.col("n").cast("double") * F.col("n")), F.max("n")
    mean = s / bins
    return histogram.agg((F.sqrt(F.greatest(F.lit(0.0), q / bins - mean * mean)) / mean * 100).alias("deviation_percent"), (m / mean).alias("max_over_mean"), F.count("*").alias("filled"))


def cdf_error(model: CdfModel, df: DataFrame, code: Column) -> DataFrame:
    """(max, mean, rms) distance of the model from the exact distribution, weighed by rows.

    Exact quantiles come from counts by distinct code, cut into ranges by the model itself: each range's
    running count starts at the count of all ranges before.
    """
    f = 64
    counts = df.select(code.cast("double").alias("c")).filter(F.col("c").isNotNull()).groupBy("c").agg(F.count("*").alias("n"))
    counts = counts.withColumn("p", model.pid(F.col("c"), f))
    totals = counts.groupBy("p").agg(F.sum("n").alias("t"))
    starts = totals.select("p", F.coalesce(F.sum("t").over(Window.orderBy("p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"), F.sum("t").over(Window.partitionBy()).alias("rows"))
    inside = F.sum("n").over(Window.partitionBy("p").orderBy("c"))
    exact = counts.withColumn("k", inside).join(F.broadcast(starts), "p").withColumn("e", F.abs(model.cdf(F.col("c")) - (F.col("before") + F.col("k")) / F.col("rows")))
    n = F.sum("n")
    return exact.agg(F.max("e").alias("max"), (F.sum(F.col("e") * F.col("n")) / n).alias("mean"), F.sqrt(F.sum(F.col("e") ** 2 * F.col("n")) / n).alias("rms"))


def displacement(code_order: DataFrame, key: str, code: Column) -> DataFrame:
    """(rows, mean_displacement, max_displacement, moved): how far rows ordered by code alone lie from full-key order, inside groups of equal code.

    Only rows that share a code can be misplaced, so no window spans more than one code's rows.
    """
    w = code_order.withColumn("_c", code).withColumn("_h", F.xxhash64(key))
    a = F.row_number().over(Window.partitionBy("_c").orderBy("_h"))
    b = F.row_number().over(Window.partitionBy("_c").orderBy(key, "_h"))
    moved = w.withColumns({"_a": a, "_b": b}).withColumn("_d", F.abs(F.col("_a") - F.col("_b")))
    return moved.agg(F.count("*").alias("rows"), F.avg("_d").alias("mean_displacement"), F.max("_d").alias("max_displacement"), F.sum((F.col("_d") > 0).cast("long")).alias("moved"))


# ---- cost formulas ---------------------------------------------------------------------------------

def work_span(n: float, r: int, s: int, f: int = 1, seek: str = "const") -> dict[str, float]:
    """Work n; span n/r + 3n/s. seek "linear" (spinning disks): fragments and flushes add a seek for each of their f pieces."""
    span = n / r + 3 * n / s
    if seek == "linear":
        span += f * (r + 1)
    return {"work": float(n), "span": span, "parallelism": n / span if span else 0.0}


def merge_cost(n: float, runs: int, strategy: str, fan_in: tuple[int, ...] = (200,)) -> dict[str, float]:
    """Passes over the rows, rows read and written, and comparisons of merging `runs` sorted runs; slices need none."""
    if strategy == "slices":
        return {"passes": 0, "moved": 2.0 * n, "comparisons": 0.0}
    left, passes, compared = max(1, runs), 0, 0.0
    widths = {"heap": [left], "binary": [2] * math.ceil(math.log2(left)) if left > 1 else []}.get(strategy)
    if widths is None:
        widths, rest, i = [], left, 0
        while rest > 1:
            k = fan_in[min(i, len(fan_in) - 1)]
            widths.append(k)
            rest, i = math.ceil(rest / k), i + 1
    for k in widths:
        if left <= 1:
            break
        compared += n * max(1.0, math.log2(min(k, left)))
        left, passes = math.ceil(left / k), passes + 1
    return {"passes": passes, "moved": 2.0 * n * (1 + passes), "comparisons": compared}


def pipeline_time(read: float, sort: float, write: float, groups: int = 3) -> float:
    """Seconds when phases of `groups` thread groups overlap: the longest phase, and the ends of the others."""
    phases = [read, sort, write]
    return max(phases) + (sum(phases) - max(phases)) / max(1, groups)


# ---- counters of a run -----------------------------------------------------------------------------

@dataclass
class PhaseTimer:
    """Wall seconds and Spark counters by phase, each phase a job group of its own."""

    spark: SparkSession
    seconds: dict[str, float] = field(default_factory=dict)
    counters: dict[str, dict[str, int]] = field(default_factory=dict)

    @contextmanager
    def phase(self, name: str):
        sc = self.spark.sparkContext
        group = f"equidepth-{name}-{time.time_ns()}"
        last = _last_execution(self.spark)
        sc.setJobGroup(group, name)
        began = time.perf_counter()
        try:
            yield
        finally:
            self.seconds[name] = self.seconds.get(name, 0.0) + time.perf_counter() - began
            found = group_counters(self.spark, group)
            found["scanTime"] = scan_millis(self.spark, last)
            for k, v in found.items():
                own = self.counters.setdefault(name, {})
                own[k] = own.get(k, 0) + v
            sc.setLocalProperty("spark.jobGroup.id", None)
            sc.setLocalProperty("spark.job.description", None)

    def shares(self) -> dict[str, float]:
        total = sum(self.seconds.values()) or 1.0
        return {k: v / total for k, v in self.seconds.items()}


COUNTERS = ("inputBytes", "outputBytes", "shuffleReadBytes", "shuffleWriteBytes", "diskBytesSpilled", "executorRunTime", "shuffleFetchWaitTime", "shuffleWriteTime")


def group_counters(spark: SparkSession, group: str) -> dict[str, int]:
    """Spark's own counters summed over the stages of a job group."""
    sc = spark.sparkContext
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    store, tracker, stages = sc._jsc.sc().statusStore(), sc.statusTracker(), set()
    for job in tracker.getJobIdsForGroup(group):
        info = tracker.getJobInfo(job)
        stages |= set(info.stageIds) if info else set()
    out = dict.fromkeys(COUNTERS, 0)
    for s in stages:
        try:
            data = store.lastStageAttempt(s)
        except Exception:  # a stage that was skipped has no attempt
            continue
        for c in COUNTERS:
            out[c] += int(getattr(data, c)())
    return out


def _last_execution(spark: SparkSession) -> int:
    runs = spark._jsparkSession.sharedState().statusStore().executionsList()
    return runs.last().executionId() if runs.size() else -1


def scan_millis(spark: SparkSession, after: int) -> int:
    """Milliseconds that scans took in the SQL executions after a given one, summed over tasks."""
    store, total = spark._jsparkSession.sharedState().statusStore(), 0.0
    runs = store.executionsList()
    for i in range(runs.size()):
        run = runs.apply(i)
        if run.executionId() <= after:
            continue
        values = store.executionMetrics(run.executionId())
        for j in range(run.metrics().size()):
            m = run.metrics().apply(j)
            if m.name() == "scan time" and values.contains(m.accumulatorId()):
                told = values.apply(m.accumulatorId()).split("\n")[-1].split(" (")[0].split()
                total += float(told[0].replace(",", "")) * {"ms": 1, "s": 1e3, "m": 6e4, "min": 6e4, "h": 3.6e6}.get(told[1], 1) if len(told) > 1 else 0
    return int(total)


def io_bytes(counters: dict[str, int]) -> int:
    """Everything read and written: input, output, shuffle both ways, spill."""
    return sum(counters.get(k, 0) for k in ("inputBytes", "outputBytes", "shuffleReadBytes", "shuffleWriteBytes", "diskBytesSpilled"))


def io_time_share(counters: dict[str, int]) -> float:
    """Part of task time spent on scans, on waiting for shuffle data and on writing it."""
    run = counters.get("executorRunTime", 0) * 1e6
    return (counters.get("shuffleWriteTime", 0) + (counters.get("shuffleFetchWaitTime", 0) + counters.get("scanTime", 0)) * 1e6) / run if run else 0.0
