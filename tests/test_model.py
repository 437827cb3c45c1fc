import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from equidepth.measures import metrics
from equidepth.plans.cdf_model import train_cdf, train_cdf_sql
from equidepth.plans.extsort import choose_slices, concurrent_slices, makespan, plan_slices

numbers = st.floats(allow_nan=False, allow_infinity=False, width=64)


@settings(max_examples=150, deadline=None)
@given(st.lists(numbers, min_size=1, max_size=80), st.lists(numbers, min_size=2, max_size=80), st.sampled_from(["linear", "quantile", "recursive"]), st.sampled_from([1, 2, 7, 64]))
def test_slices_never_fall_as_keys_rise(sample, keys, root, f):
    m = train_cdf(np.array(sample), 16, root)
    x = np.sort(np.array(keys + sample))
    p = m.pid_np(x, f)
    assert (np.diff(p) >= 0).all() and p.min() >= 0 and p.max() < f


def test_without_bands_the_order_can_break():
    r = np.random.default_rng(1)
    broken = 0
    for k in range(40):
        s = np.sort(r.lognormal(0, 3, 300))
        m = train_cdf(s, 64, "linear", clamp=False)
        broken += int((np.diff(m.cdf_np(s)) < -1e-12).sum() > 0)
        assert (np.diff(train_cdf(s, 64, "linear").cdf_np(s)) >= 0).all()
    assert broken > 0


@pytest.mark.parametrize("root", ["linear", "quantile", "recursive"])
def test_expression_equals_numpy(spark, root):
    r = np.random.default_rng(3)
    x = np.concatenate([r.exponential(1, 500), [0.0, 1e9, -5.0]])
    m = train_cdf(x[:200], 32, root)
    df = spark.createDataFrame([(i, float(v)) for i, v in enumerate(x)], "i int, x double")
    got = [r["p"] for r in df.select("i", m.pid(F.col("x"), 13).alias("p")).orderBy("i").collect()]
    assert got == m.pid_np(x, 13).tolist()
    assert df.select(m.pid(F.lit(None).cast("double"), 13).alias("p")).first()["p"] is None


def test_many_leaves_are_found_by_halving(spark):
    """Beyond a tree of comparisons the expression still is the model's, and slices still rise."""
    r = np.random.default_rng(4)
    x = np.concatenate([r.lognormal(0, 2, 3000), [-1.0, 0.0, 1e12]])
    m = train_cdf(x, 600, "quantile")
    assert m.leaves > 256
    df = spark.createDataFrame([(i, float(v)) for i, v in enumerate(x)], "i int, x double")
    got = [row["p"] for row in df.select("i", m.pid(F.col("x"), 97).alias("p")).orderBy("i").collect()]
    assert got == m.pid_np(x, 97).tolist()


def test_sql_twin_agrees_with_numpy(spark):
    x = np.round(np.random.default_rng(5).gamma(2, 3, 400), 2)
    m = train_cdf(x, 8, "linear")
    rows = {r["leaf"]: r for r in train_cdf_sql(spark.createDataFrame([(float(v),) for v in x], "code double"), 8).collect()}
    for j in range(8):
        if m.count[j]:
            assert rows[j]["n"] == m.count[j]
            assert rows[j]["hi"] == pytest.approx(m.high[j])


def test_model_beats_equal_widths_on_skewed_keys(spark, data):
    from equidepth.measures.workloads import run_balance
    from equidepth.plans.sampling import SampleSpec

    df = spark.read.parquet(data.replace("0.001", "0.01") + "/events.parquet")
    rows = {r["partitioner"]: r for r in run_balance(df, "value", [16], SampleSpec(floor=2000)).collect()}
    assert rows["model"]["var"] < 0.77 * rows["radix"]["var"] and rows["model"]["reduction_percent"] > 23


def test_plans():
    assert concurrent_slices([4, 3, 2, 9], 9) == 3 and concurrent_slices([20, 1], 9) == 1 and concurrent_slices([4, 3, 2, 9, 1], 10, "any_window") == 1
    assert choose_slices(1000, 100, 2.0) == 20 and choose_slices(0) == 1
    assert makespan([5, 4, 3], 2) == 7
    small, large = plan_slices(1e7, 100), plan_slices(1e12, 100)
    assert small["rounds"] == 1 and large["rounds"] == 2 and large["block_bytes"] > 64 << 10


def test_measures():
    assert metrics.sort_rate(380e6, 1) == 380 and round(metrics.relative(380, 230)["ratio"], 2) == 1.65
    assert metrics.energy(10, 65) == 650
    c = metrics.scale_curve([(1, 100), (2, 95), (3, 90.25)])
    assert [round(s, 6) for s in c["steps"]] == [5, 5]
    costs = {k: metrics.merge_cost(1e9, 1200, k, (200, 6)) for k in ("slices", "heap", "binary", "hier")}
    assert costs["slices"]["moved"] < costs["heap"]["moved"] < costs["hier"]["moved"] < costs["binary"]["moved"]
    assert metrics.work_span(100, 10, 5)["span"] == 70
    assert metrics.variance_reduction(77, 100) == pytest.approx(23)
