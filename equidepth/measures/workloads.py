"""Experiment runners: each returns one DataFrame of measures. They time real runs, so they act when called."""

from __future__ import annotations

import os
import time
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans import memsort
from ..plans.cdf_model import train_cdf
from ..plans.extsort import PID, builtin_sort, estimated_bytes, first_shards, fragment_matrix, model_sort, plan_slices, pointer_sorted, radix_sort, sort_late_payload
from ..plans.keys import KeySpec, Order, ascii_code, byte_code, profile, resolve
from ..plans.mergesort import external_merge_sort, make_runs, merge_runs
from ..plans.partitioners import hash_pid, quantile_pid, radix_pid, sketch_pid
from ..plans.sampling import SampleSpec, draw_sample
from ..session import drop, drop_at_exit, made_here, shuffles_freed
from ..sources.io import write_noop
from . import metrics
from .validate import check_sorted


def sorters(run_rows: int = 20_000, f: int = 16) -> dict[str, Callable[[DataFrame, list[str]], DataFrame]]:
    """The sorters compared: name to a function from (df, by) to ordered rows. Merge sorts hold rows as Python objects and end in one task."""
    return {
        "model": lambda df, by: model_sort(df, by, f=f).plain(),
        "radix": lambda df, by: radix_sort(df, by, f).plain(),
        "builtin": builtin_sort,
        "os_merge": lambda df, by: external_merge_sort(df, by, "os", run_rows),
        "binary_merge": lambda df, by: merge_runs(make_runs(df, by, run_rows), by, "binary", (2,)),
        "hier_merge": lambda df, by: external_merge_sort(df, by, "A", run_rows),
    }


def media(spark: SparkSession, shared: str) -> dict[str, str | None]:
    """Where tables can be kept: the shared folder, memory, and (where all tasks run in one machine) a RAM disk."""
    found: dict[str, str | None] = {"disk": shared, "memory": None}
    if spark.sparkContext.master.startswith("local[") and os.path.isdir("/dev/shm"):
        found["ram_disk"] = f"file:///dev/shm/equidepth-{uuid.uuid4().hex}"
    return found


def _timed(fn) -> float:
    began = time.perf_counter()
    fn()
    return time.perf_counter() - began


def run_storage(spark: SparkSession, inputs: dict[str, tuple[DataFrame, str]], where: dict[str, str | None], names: list[str], formats=("parquet",), codecs=("snappy",), f: int = 16) -> DataFrame:
    """(medium, format, codec, input, sorter, seconds, mb_per_s, copy_mb_per_s, gap): read from, sort, write to each medium.

    The first medium gets every format and codec, the others the first of each. A medium without a folder is memory: the input is cached and the
    output goes nowhere. Rates count the stored input's bytes.
    """
    rows, all_sorters = [], sorters(f=f)
    for k, (medium, root) in enumerate(where.items()):
        for fmt in (formats if k == 0 else formats[:1]) if root else ("cache",):
            for codec in (codecs if k == 0 else codecs[:1]) if fmt == "parquet" else ("none",):
                for label, (df, key) in inputs.items():
                    if root:
                        source = f"{root}/in-{label}-{fmt}-{codec}"
                        df.write.mode("overwrite").format(fmt).option("compression", codec).save(source)
                        drop_at_exit(spark, root)
                        stored = spark.read.schema(df.schema).format(fmt).load(source)
                        size = estimated_bytes(stored)

                        def put(out, to=f"{root}/out", fmt=fmt, codec=codec):
                            out.write.mode("overwrite").format(fmt).option("compression", codec).save(to)
                    else:
                        stored, size, put = df.persist(), 0, write_noop
                        stored.count()
                        size = estimated_bytes(stored)
                    copied = metrics.sort_rate(size, _timed(lambda s=stored: put(s)))
                    for name in names:
                        secs = _timed(lambda s=stored, n=name, k=key: put(all_sorters[n](s, [k])))
                        rate = metrics.sort_rate(size, secs)
                        rows.append((medium, fmt, codec, label, name, secs, rate, copied, metrics.bandwidth_gap(rate, copied)))
                    if not root:
                        stored.unpersist()
    return spark.createDataFrame(rows, "medium string, format string, codec string, input string, sorter string, seconds double, mb_per_s double, copy_mb_per_s double, gap double")


def run_skew(storage: DataFrame, uniform: str, skewed: str) -> DataFrame:
    """(medium, sorter, uniform, skewed, drop_percent) of run_storage's result."""
    a = storage.filter(F.col("input") == uniform).select("medium", "format", "codec", "sorter", F.col("mb_per_s").alias("uniform"))
    b = storage.filter(F.col("input") == skewed).select("medium", "format", "codec", "sorter", F.col("mb_per_s").alias("skewed"))
    return a.join(b, ["medium", "format", "codec", "sorter"]).withColumn("drop_percent", (1 - F.col("skewed") / F.col("uniform")) * 100)


def run_histogram(df: DataFrame, col: str, bins: int = 1000) -> DataFrame:
    return metrics.equi_width_histogram(df, col, bins)


def run_scale(spark: SparkSession, inputs: list[tuple[float, DataFrame]], by: list[str], names: list[str], f: int = 16) -> DataFrame:
    """(sorter, size, seconds, mb_per_s, mean_drop, total_drop)."""
    rows, all_sorters = [], sorters(f=f)
    for name in names:
        runs = []
        for size, df in inputs:
            secs = _timed(lambda d=df, n=name: write_noop(all_sorters[n](d, by)))
            runs.append((size, metrics.sort_rate(size, secs), secs))
        curve = metrics.scale_curve([(s, r) for s, r, _ in runs])
        rows += [(name, float(s), t, r, curve["mean_drop"], curve["total_drop"]) for s, r, t in runs]
    return spark.createDataFrame(rows, "sorter string, size double, seconds double, mb_per_s double, mean_drop double, total_drop double")


def run_energy(spark: SparkSession, seconds: dict[str, float], watts: float) -> DataFrame:
    """(sorter, seconds, joules): modelled from a stated power."""
    return spark.createDataFrame([(k, v, metrics.energy(v, watts)) for k, v in seconds.items()], "sorter string, seconds double, joules double")


def run_phases(df: DataFrame, by: list[str], path: str, f: int = 16, sample: SampleSpec = SampleSpec()) -> DataFrame:
    """(phase, seconds, share, io_bytes) of training, partitioning, sorting pointers, coalescing rows in that order and flushing them.

    Each run goes one phase further than the one before; a phase is the difference.
    """
    spark = df.sparkSession
    timer = metrics.PhaseTimer(spark)
    with timer.phase("train"):
        spec = resolve(df, Order(by[0]))
        rows = df.count()
        model = train_cdf(draw_sample(df, spec.code(), sample, rows), 64, "linear")
    sf = model_sort(df, by, f=f, model=model)
    steps = {
        "partition": lambda: write_noop(sf.exchanged), "sort": lambda: write_noop(pointer_sorted(sf, stage="sort")),
        "coalesce": lambda: write_noop(pointer_sorted(sf)), "flush": lambda: pointer_sorted(sf).drop(PID).write.mode("overwrite").parquet(path),
    }
    for name, run in steps.items():
        run()  # once unmeasured: workers are up then
        with timer.phase(name):
            run()
    s, names = timer.seconds, list(steps)
    parts = {"train": s["train"], "partition": s["partition"]} | {b: max(0.0, s[b] - s[a]) for a, b in zip(names, names[1:], strict=False)}
    total = sum(parts.values()) or 1.0
    return spark.createDataFrame([(k, v, v / total, metrics.io_bytes(timer.counters.get(k, {}))) for k, v in parts.items()], "phase string, seconds double, share double, io_bytes long")


def run_coalesce(df: DataFrame, by: list[str], locator: str, path: str, f: int = 16, batches=(1 << 10, 100 << 10, 64 << 20)) -> DataFrame:
    """(payload, batch_bytes, seconds): rows written in order, moved by the built-in in-slice sort, fetched by locator after a sort of keys alone,
    or fetched by pointer in batches of each size."""
    sf = model_sort(df, by, f=f)

    def put(out: DataFrame) -> None:
        out.write.mode("overwrite").parquet(path)

    put(sf.plain())
    rows = [("with_key", 0, _timed(lambda: put(sf.plain()))), ("by_locator", 0, _timed(lambda: put(sort_late_payload(df, by, locator, f=f))))]
    rows += [("by_pointer", b, _timed(lambda b=b: put(pointer_sorted(sf, b).drop(PID)))) for b in batches]
    return df.sparkSession.createDataFrame(rows, "payload string, batch_bytes long, seconds double")


def run_io(df: DataFrame, by: list[str], names: list[str], path: str, f: int = 16) -> DataFrame:
    """(sorter, seconds, read, written, shuffled, spilled, total, ratio, io_share): Spark's own counters; ratio to the model sort.

    Every sorter writes all rows at path; its files go once it is measured, before the next one starts.
    """
    spark, rows, all_sorters = df.sparkSession, [], sorters(f=f)
    for name in names:
        timer = metrics.PhaseTimer(spark)
        drop_at_exit(spark, path)
        with made_here() as made:
            with timer.phase("run"), shuffles_freed(spark):
                all_sorters[name](df, by).write.mode("overwrite").parquet(f"{path}/{name}")
        c = timer.counters["run"]
        for used in (*made, path):
            drop(spark, used)
        rows.append([name, timer.seconds["run"], c["inputBytes"], c["outputBytes"], c["shuffleReadBytes"] + c["shuffleWriteBytes"], c["diskBytesSpilled"], metrics.io_bytes(c), 0.0, metrics.io_time_share(c)])
    base = next((r[6] for r in rows if r[0] == "model"), rows[0][6]) or 1
    for r in rows:
        r[7] = r[6] / base
    return spark.createDataFrame([tuple(r) for r in rows], "sorter string, seconds double, read long, written long, shuffled long, spilled long, total long, ratio double, io_share double")


def run_sample_curve(df: DataFrame, col: str, rates: list[float], methods: list[str], f: int = 16, leaves: int = 64, root: str = "linear", floor: int = 0) -> DataFrame:
    """(method, rate, sampled, cdf_max, cdf_rms, cv) of models trained on samples of each rate and source."""
    spec = resolve(df, Order(col))
    rows = df.count()
    coded = df.select(spec.code().alias("_code")).filter(F.col("_code").isNotNull())
    out = []
    for method in methods:
        for rate in rates:
            s = draw_sample(df, spec.code(), SampleSpec(frac=rate, floor=floor or 1, method=method, batch_rows=max(1, int(rows * max(rate, 0.05)))), rows)
            model = train_cdf(s, leaves, root)
            e = metrics.cdf_error(model, coded, F.col("_code")).first()
            c = metrics.slice_stats(coded, model.pid(F.col("_code"), f), f).first()
            out.append((method, rate, len(s), float(e["max"]), float(e["rms"]), float(c["cv"])))
    return df.sparkSession.createDataFrame(out, "method string, rate double, sampled long, cdf_max double, cdf_rms double, cv double")


def run_code_width(df: DataFrame, col: str, widths: list[int], *, raw: bool = True) -> DataFrame:
    """(width, mean_displacement, max_displacement, moved): the whole-key work that a code of each width leaves."""
    out = None
    for w in widths:
        code = byte_code(F.col(col), w) if raw else ascii_code(F.col(col), w, variable=True)
        one = metrics.displacement(df.select(col).filter(F.col(col).isNotNull()), col, code).select(F.lit(w).alias("width"), "mean_displacement", F.col("max_displacement").cast("long").alias("max_displacement"), "moved")
        out = one if out is None else out.unionByName(one)
    return out


def run_balance(df: DataFrame, col: str, fs: list[int], sample: SampleSpec = SampleSpec(), *, leaves: int = 64, root: str | None = None, strip_prefix: bool = True) -> DataFrame:
    """(f, partitioner, mean, var, cv, max_over_mean, empty, reduction_percent): slice sizes by every partitioner; reduction of variance against equal widths."""
    spec = resolve(df, Order(col), strip_prefix=strip_prefix)
    seen = profile(df, spec)
    codes = draw_sample(df, spec.code(), sample, seen["rows"])
    root = root or ("quantile" if spec.kind == "bytes" else "linear")
    model = train_cdf(codes, leaves, root)
    coded = df.select(spec.code().alias("_code"), F.col(col)).filter(F.col("_code").isNotNull())
    out = []
    for f in fs:
        pids = {
            "model": model.pid(F.col("_code"), f), "radix": radix_pid(F.col("_code"), seen["low"], seen["high"], f), "quantile": quantile_pid(F.col("_code"), codes, f),
            "sketch": sketch_pid(coded, F.col("_code"), f), "hash": hash_pid(F.col(col), f),
        }
        got = {k: metrics.slice_stats(coded, p, f).first() for k, p in pids.items()}
        for k, r in got.items():
            out.append((f, k, float(r["mean"]), float(r["var"]), float(r["cv"]), float(r["max_over_mean"]), int(r["empty"]), metrics.variance_reduction(r["var"], got["radix"]["var"])))
    return df.sparkSession.createDataFrame(out, "f int, partitioner string, mean double, var double, cv double, max_over_mean double, empty long, reduction_percent double")


def run_memory_sorts(df: DataFrame, col: str, routines=memsort.ROUTINES, f: int = 16, run_rows: int = 20_000, insertion_rows: int = 1_000) -> DataFrame:
    """(inside, routine, slices, rows, seconds, equal): each routine over all rows of the column's codes, in the slices' own tasks, and as the
    routine that makes a merge sort's runs (seconds of the whole step there).

    seconds in slices: those of the routine alone, summed over slices. Insertion sort is quadratic: it gets so many slices that one has about
    insertion_rows rows, and makes no runs.
    """
    spark, out = df.sparkSession, None
    for r in routines:
        slim = df.select(col)
        sf = model_sort(slim, [col], f=max(f, -(-slim.count() // insertion_rows)) if r == "insertion" else f)
        codes = sf.exchanged.select(KeySpec(Order(col), sf.spec.kind, sf.spec.skip).code().alias("c")).filter("c IS NOT NULL")
        timed = codes.mapInArrow(lambda it, r=r: _timed_slice(it, r), "rows long, seconds double, equal boolean")
        one = timed.agg(F.count("*").alias("slices"), F.sum("rows").alias("rows"), F.sum("seconds").alias("seconds"), F.bool_and("equal").alias("equal"))
        one = one.select(F.lit("slices").alias("inside"), F.lit(r).alias("routine"), "slices", "rows", "seconds", "equal")
        out = one if out is None else out.unionByName(one)
    runs = []
    for r in (r for r in routines if r != "insertion"):
        made = make_runs(df.select(col), [col], run_rows, routine=r)
        secs = _timed(lambda m=made: write_noop(m))
        rises = made.withColumn("_before", F.lag(col).over(Window.partitionBy("run_id").orderBy("pos")))
        seen = rises.agg(F.countDistinct("run_id"), F.count("*"), F.bool_and(F.coalesce(F.col("_before") <= F.col(col), F.lit(True)))).first()
        runs.append(("runs", r, seen[0], seen[1], secs, bool(seen[2])))
    return out.unionByName(spark.createDataFrame(runs, "inside string, routine string, slices long, rows long, seconds double, equal boolean"))


def _timed_slice(batches: Iterator[pa.RecordBatch], routine: str) -> Iterator[pa.RecordBatch]:
    held = [b.column(0).to_numpy(zero_copy_only=False) for b in batches]
    codes = np.concatenate(held) if held else np.zeros(0)
    if len(codes):
        began = time.perf_counter()
        order = memsort.memory_order(codes, routine)
        secs = time.perf_counter() - began
        yield pa.RecordBatch.from_arrays([pa.array([len(codes)], pa.int64()), pa.array([secs]), pa.array([bool((codes[order] == np.sort(codes)).all())])], names=["rows", "seconds", "equal"])


def run_rounds(df: DataFrame, by: list[str], f: int = 256) -> DataFrame:
    """(rounds, shards, slices, tasks, blocks, slices_a_task, rows, ordered): the last exchange of a sort in one round and in two, carried out."""
    out = []
    for rounds in (1, 2):
        sf = model_sort(df, by, f=f, rounds=rounds)
        before = sf.shards if rounds == 2 else sf.sliced
        blocks = fragment_matrix(before.repartition(64) if rounds == 1 else before, F.col(PID))
        each = blocks.groupBy("reader").agg(F.count("*").alias("n")).agg(F.count("*"), F.sum("n"), F.max("n")).first()
        seen = check_sorted(sf.with_rn(), by).first()
        out.append((rounds, min(f, -(-f // -(-f // first_shards(f)))) if rounds == 2 else 1, f, each[0], each[1], each[2], seen["rows"], seen["unordered"] == 0 and seen["gaps"] == 0))
    return df.sparkSession.createDataFrame(out, "rounds int, shards int, slices int, tasks long, blocks long, slices_a_task long, rows long, ordered boolean")


def run_plan(spark: SparkSession, sizes: list[tuple[float, float]]) -> DataFrame:
    """Plans of sorts of (rows, bytes a row) as a table."""
    rows = [plan_slices(n, b) for n, b in sizes]
    names = list(rows[0])
    return spark.createDataFrame([tuple(float(r[k]) for k in names) for r in rows], ", ".join(f"{k} double" for k in names))
