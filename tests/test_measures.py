"""Measures, sketches and copies that have no SQL to compare with."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from equidepth.measures import metrics
from equidepth.operators import aggregates
from equidepth.plans.extsort import model_sort
from equidepth.plans.keys import code_capacity, widest
from equidepth.session import drop_at_exit, scratch, work_dir, written
from equidepth.sources.io import copy_baseline, write_noop


def test_published_ratios():
    """Arithmetic of the rates that are stated in words."""
    assert round(metrics.relative(380, 230)["lower_percent"]) == 39 and round(metrics.relative(380, 130)["lower_percent"]) == 66
    assert round(metrics.relative(900, 760)["higher_percent"]) == 18
    assert metrics.bandwidth_gap(342, 380) == pytest.approx(0.1) and metrics.skew_drop(100, 97) == pytest.approx(3)
    assert round(code_capacity(9)["bits_by_sum"], 2) == pytest.approx(59.14, abs=0.02) and widest() == 9
    assert metrics.pipeline_time(10, 20, 5, 3) == 25
    assert metrics.work_span(1e6, 10, 4, f=8, seek="linear")["span"] > metrics.work_span(1e6, 10, 4)["span"]


def test_repeat_runs_as_often_as_asked():
    seen = []
    took = metrics.repeat(lambda: seen.append(1), 4)
    assert len(seen) == len(took) == 4 and all(t >= 0 for t in took)


def test_sketches_come_near(spark, data):
    events = spark.read.parquet(data.replace("0.001", "0.01") + "/events.parquet")
    x = np.sort([r[0] for r in events.select("value").collect()])
    for name in ("approx_percentile", "kll_percentile"):
        for r in getattr(aggregates, name)(events, "value", [0.1, 0.5, 0.9]).collect():
            rank = np.searchsorted(x, r["value"]) / len(x)
            assert abs(rank - r["q"]) < 0.03, name
    lines = spark.read.parquet(data.replace("0.001", "0.01") + "/lineitem.parquet")
    n = lines.select("l_partkey").distinct().count()
    assert abs(aggregates.approx_distinct(lines, "l_partkey").first()["n"] / n - 1) < 0.08


def test_a_copy_is_the_same_rows(spark, data):
    df, path = spark.read.parquet(f"{data}/orders.parquet"), scratch(spark, "copy")
    copy_baseline(df, path)
    drop_at_exit(spark, path)
    assert spark.read.parquet(path).exceptAll(df).count() == 0 == df.exceptAll(spark.read.parquet(path)).count()


def test_written_tables_lie_in_the_shared_folder(spark, data):
    out = written(spark.read.parquet(f"{data}/nation.parquet"), "test")
    assert all(work_dir(spark).split("://")[-1].removeprefix("file:") in f for f in out.inputFiles()) and out.count() == 25


def test_scans_and_shuffles_are_counted(spark, data):
    timer = metrics.PhaseTimer(spark)
    df = spark.read.parquet(data.replace("0.001", "0.01") + "/lineitem.parquet")
    with timer.phase("sort"):
        write_noop(model_sort(df, ["l_extendedprice"], f=4).plain())
    c = timer.counters["sort"]
    assert c["inputBytes"] > 0 and c["shuffleWriteBytes"] > 0 and c["scanTime"] >= 0 and metrics.io_bytes(c) > c["inputBytes"] and 0 <= metrics.io_time_share(c)


def test_variance_of_slices_is_counted_with_empty_ones(spark):
    df = spark.createDataFrame([(p,) for p in (0, 0, 0, 2)], "p int")
    r = metrics.slice_stats(df, F.col("p"), 4).first()
    assert (r["slices"], r["empty"], r["max"], r["mean"]) == (4, 2, 3, 1.0) and r["var"] == pytest.approx(1.5)
