import numpy as np
import pytest
from pyspark.sql import functions as F

from equidepth.measures.validate import check_sorted, validate_all
from equidepth.operators import aggregates, joins, ranks, sets
from equidepth.plans import memsort
from equidepth.plans.cdf_model import train_cdf, train_cdf_sql
from equidepth.plans.extsort import PID, estimated_bytes, first_shards, leaves_for, model_sort, plan_slices, pointer_sorted
from equidepth.plans.keys import Order, orders
from equidepth.plans.partitioners import exact_pid
from equidepth.plans.sampling import SampleSpec


def exchanges(df) -> int:
    return df._jdf.queryExecution().executedPlan().toString().count("Exchange ") - df._jdf.queryExecution().executedPlan().toString().count("BroadcastExchange ")


@pytest.mark.parametrize("f", [1, 2, 7, 64])
@pytest.mark.parametrize("tab,key,tie", [("lineitem", "l_extendedprice", "l_orderkey"), ("events", "event_type", "event_id"), ("customer", "c_name", "c_custkey"), ("documents", "text", "doc_id"), ("orders", "-o_orderdate", "o_orderkey")])
def test_sorted_same_rows_and_disjoint(spark, data, tab, key, tie, f):
    df = spark.read.parquet(f"{data}/{tab}.parquet")
    r = validate_all(df, model_sort(df, [key, tie], f=f)).first()
    assert r["rows"] == df.count() and r["gaps"] == 0 and r["unordered"] == 0 and r["same_rows"] and r["violations"] == 0


def test_shared_prefix_needs_stripping(spark, data):
    df = spark.read.parquet(f"{data}/customer.parquet")
    stripped, whole = model_sort(df, ["c_name"], f=8), model_sort(df, ["c_name"], f=8, strip_prefix=False)
    assert max(stripped.sizes) < 0.5 * sum(stripped.sizes) and max(whole.sizes) == sum(whole.sizes)


@pytest.mark.parametrize("rows", [[], [(1.0,)], [(1.0,)] * 50, [(None,)] * 5, [(float("nan"),), (float("inf"),), (None,), (-0.0,), (0.0,), (float("-inf"),)]])
def test_edges(spark, rows):
    df = spark.createDataFrame(rows, "v double")
    placed = model_sort(df, ["v"], f=4).with_rn()
    assert sorted(r["rn"] for r in placed.collect()) == list(range(1, len(rows) + 1))
    assert check_sorted(placed, ["v"]).first()["unordered"] == 0


def test_large_longs(spark):
    values = [2**62, 2**62 + 1, 2**62 + 2, -(2**63), 2**63 - 1, 2**53, 2**53 + 1]
    df = spark.createDataFrame([(v,) for v in values], "v long")
    got = [r["v"] for r in sorted(model_sort(df, ["v"], f=4).with_rn().collect(), key=lambda r: r["rn"])]
    assert got == sorted(values)


def test_check_sorted_sees_disorder(spark):
    df = spark.createDataFrame([(3.0, 1), (1.0, 2), (2.0, 4)], "v double, rn long")
    r = check_sorted(df, ["v"]).first()
    assert r["unordered"] == 1 and r["gaps"] == 1


def test_null_order_both_ways(spark):
    df = spark.createDataFrame([(v,) for v in (3.0, None, 1.0, None)], "v double")
    for first in (True, False):
        got = [r["v"] for r in sorted(model_sort(df, [Order("v", nulls_first=first)], f=3).with_rn().collect(), key=lambda r: r["rn"])]
        assert got == ([None, None, 1.0, 3.0] if first else [1.0, 3.0, None, None])


def test_one_exchange_and_slices_are_partitions(spark, data):
    df = spark.read.parquet(f"{data}/lineitem.parquet")
    sf = model_sort(df, ["l_extendedprice"], f=8)
    assert exchanges(sf.df) == 1 and exchanges(sf.with_rn()) == 1
    assert sf.df.filter(F.spark_partition_id() != F.col(PID)).count() == 0
    grouped = sf.exchanged.groupBy(PID, "l_extendedprice").count()
    assert exchanges(grouped) == 1


def test_merge_join_has_one_exchange_a_side(spark, data):
    l = spark.read.parquet(f"{data}/lineitem.parquet").select("l_orderkey", "l_quantity")
    o = spark.read.parquet(f"{data}/orders.parquet").select("o_orderkey", "o_totalprice")
    assert exchanges(joins.model_merge_join(l, o, "l_orderkey", "o_orderkey")) == 2


def test_first_batch_sample_is_right_but_unbalanced(spark, data):
    df = spark.read.parquet(data.replace("0.001", "0.01") + "/events.parquet")
    clustered = model_sort(df, ["ts"], f=8, sample=SampleSpec(method="first_batch", batch_rows=500))
    even = model_sort(df, ["ts"], f=8)
    assert validate_all(df, clustered).first()["unordered"] == 0
    assert np.var(clustered.sizes) > 4 * np.var(even.sizes)


def test_model_reused_on_unseen_keys(spark):
    model = train_cdf(np.arange(100.0), 16)
    df = spark.createDataFrame([(float(v),) for v in range(-50, 300, 7)], "v double")
    r = validate_all(df, model_sort(df, ["v"], f=8, model=model)).first()
    assert r["unordered"] == 0 and r["same_rows"]


def test_top_k_reads_few_slices(spark, data):
    df = spark.read.parquet(f"{data}/events.parquet")
    got = [r["value"] for r in sorted(ranks.top_k(model_sort(df, ["value", "event_id"], f=8), 12).collect(), key=lambda r: r["rn"])]
    assert got == sorted(r["value"] for r in df.select("value").collect())[:12]


@pytest.mark.parametrize("routine", memsort.ROUTINES)
def test_memory_routines_agree(routine):
    r = np.random.default_rng(2)
    for x in (r.random(300), r.integers(0, 5, 300).astype(float), np.arange(200.0)[::-1], np.zeros(50), np.array([]), np.array([-1.5, 2.0, -0.0])):
        order = memsort.memory_order(x, routine)
        assert sorted(order.tolist()) == list(range(len(x))) and (x[order] == np.sort(x)).all()


def test_touch_up_heals_truncated_codes():
    keys = ["aaaaaaa" + c for c in "zyxab"] + ["b"]
    order, moves = memsort.model_order(np.array([0.0] * 5 + [1.0]), keys)
    assert [keys[i] for i in order] == sorted(keys) and moves > 0
    assert memsort.touch_up([1, 2, 3], np.array([0, 1, 2]))[1] == 0


def test_heavy_codes_are_refined(spark, data):
    df = spark.read.parquet(data.replace("0.001", "0.01") + "/pages.parquet").select("page_id", "url")
    plain, fine = model_sort(df, ["url", "page_id"], f=8), model_sort(df, ["url", "page_id"], f=8, refine=True)
    assert max(fine.sizes) < max(plain.sizes) and max(fine.sizes) < 2.0 * sum(fine.sizes) / 8
    got = [r["url"] for r in sorted(fine.with_rn().collect(), key=lambda r: r["rn"])]
    assert got == sorted(got, key=lambda u: u.encode())


@pytest.mark.parametrize("key", ["value", "-value", "ts", "event_type"])
def test_slices_become_key_ranges(spark, data, key):
    df = spark.read.parquet(f"{data}/events.parquet").withColumn("value", F.when(F.col("event_id") % 50 != 0, F.col("value")))
    sf = model_sort(df, [key, "event_id"], f=7)
    for low, high in ((0, 0), (2, 4), (6, 6), (0, 6)):
        got = {r["event_id"] for r in sf.slice_range(low, high).sliced.select("event_id").collect()}
        want = {r["event_id"] for r in sf.sliced.filter(F.col(PID).between(low, high)).select("event_id").collect()}
        assert got == want
    if key == "value":
        plan = model_sort(spark.read.parquet(f"{data}/events.parquet"), ["value"], f=7).slice_range(1, 2).sliced._jdf.queryExecution().executedPlan().toString()
        assert "GreaterThanOrEqual(value" in plan and "LessThan(value" in plan


def shuffles(spark, run) -> list[int]:
    """Shuffle bytes written of each stage of what `run` does, the stages without any left out."""
    store = spark.sparkContext._jsc.sc().statusStore()
    group = f"count-{id(run)}"
    spark.sparkContext.setJobGroup(group, group)
    run()
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
    tracker = spark.sparkContext.statusTracker()
    stages = {s for j in tracker.getJobIdsForGroup(group) for s in tracker.getJobInfo(j).stageIds}
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    sizes = []
    for s in sorted(stages):
        try:
            sizes.append(int(store.lastStageAttempt(s).shuffleWriteBytes()))
        except Exception:  # skipped
            continue
    return [n for n in sizes if n]


def test_two_rounds_are_two_shuffles(spark, data):
    df = spark.read.parquet(f"{data}/lineitem.parquet")
    for rounds, want in ((1, 1), (2, 2)):
        sf = model_sort(df, ["l_extendedprice", "l_orderkey"], f=64, rounds=rounds)
        assert len(shuffles(spark, lambda sf=sf: sf.plain().write.format("noop").mode("overwrite").save())) == want
        r = validate_all(df, sf).first()
        assert r["unordered"] == 0 and r["gaps"] == 0 and r["same_rows"] and r["violations"] == 0


def test_a_task_of_the_second_round_makes_blocks_for_one_shard(spark, data):
    """What plan_slices says of two rounds: shards of consecutive slices, each file one shard."""
    sf = model_sort(spark.read.parquet(f"{data}/lineitem.parquet"), ["l_extendedprice"], f=64, rounds=2)
    each = -(-64 // first_shards(64))
    files = sf.shards.groupBy(F.input_file_name().alias("file")).agg(F.min(PID).alias("low"), F.max(PID).alias("high"), F.countDistinct(PID).alias("n")).collect()
    assert len(files) <= first_shards(64) and all(r["low"] // each == r["high"] // each and r["n"] <= each for r in files)


def test_rounds_slices_and_leaves_come_from_the_plan(spark, data):
    df = spark.read.parquet(f"{data}/lineitem.parquet")
    assert model_sort(df, ["l_extendedprice"], f=8).rounds == 1
    fine = model_sort(df, ["l_extendedprice"], slice_bytes=500)
    plan = plan_slices(fine.rows, estimated_bytes(df) / fine.rows, slice_bytes=500)
    assert plan["rounds"] == 2 == fine.rounds and fine.model.leaves == leaves_for(fine.f) and leaves_for(8000) == 1000
    r = validate_all(df, fine).first()
    assert r["unordered"] == 0 and r["same_rows"] and r["violations"] == 0


@pytest.mark.parametrize("by", [["event_type", "event_id"], ["event_type", "-value", "event_id"], ["-user_id", "event_type", "ts"], ["flag", "text", "big"]])
def test_ties_are_cut_by_the_further_columns(spark, data, by):
    """A leading key of few values fills all slices, and the order is the one asked for."""
    df = spark.read.parquet(data.replace("0.001", "0.01") + "/events.parquet").withColumn("user_id", F.col("user_id") % 3)
    df = df.withColumns({
        "flag": F.when(F.col("event_id") % 11 != 0, F.col("event_id") % 2 == 0), "text": F.when(F.col("event_id") % 7 != 0, F.repeat(F.col("event_type"), (F.col("event_id") % 15).cast("int"))),
        "big": F.lit(2**60) + F.col("event_id") % 500,
    })
    sf, whole = model_sort(df, by, f=16, split_ties=True), model_sort(df, by, f=16)
    assert sum(n > 0 for n in sf.sizes) > sum(n > 0 for n in whole.sizes) and max(sf.sizes) < max(whole.sizes)
    placed = sf.with_rn().cache()
    assert check_sorted(placed, by).first()["unordered"] == 0 and placed.count() == df.count()
    if by[0] == "event_type":
        assert max(sf.sizes) < 2 * np.mean(sf.sizes)


def test_a_third_of_the_rows_on_one_key(spark):
    """The largest task stays near the others', and results stay whole."""
    df = spark.createDataFrame([(7 if i % 3 == 0 else i, i) for i in range(30_000)], "k long, v long")
    few = spark.createDataFrame([(7, i) for i in range(20)] + [(i, 0) for i in range(1000, 3000)], "rk long, rv long")
    sizes = model_sort(df, ["k", "v"], f=16, split_ties=True).sizes
    assert max(sizes) < 2 * np.median(sizes)
    got = joins.model_merge_join(df, few, "k", "rk", f=16)
    want = df.join(few, df["k"] == few["rk"])
    assert got.count() == want.count() and got.exceptAll(want).count() == 0
    for how in ("left", "right", "full", "left_semi", "left_anti"):
        got, want = joins.model_merge_join(df, few, "k", "rk", how, f=16), df.join(few, df["k"] == few["rk"], how)
        assert got.count() == want.count() and got.exceptAll(want).count() == 0, how
    sizes = [r["count"] for r in joins.model_merge_join(df, few, "k", "rk", f=16).filter("k = 7").groupBy(F.spark_partition_id()).count().collect()]
    assert len(sizes) >= 5 and max(sizes) < 2 * np.median(sizes)  # a third of the rows and more: five or six of sixteen slices
    groups = aggregates.model_group_by(df, ["k"], [F.count("*").alias("n")])
    assert {(r["k"], r["n"]) for r in groups.filter("n > 1").collect()} == {(7, 10_001)}
    assert sets.model_distinct(df.select("k")).count() == df.select("k").distinct().count()
    assert ranks.global_rank(model_sort(df, ["k"], f=16)).filter("k = 7").select("rnk").distinct().collect()[0][0] == 5
    assert ranks.exact_percentile(model_sort(df, ["k"], f=16), [0.2]).first()["value"] == 7


@pytest.mark.parametrize("by", [["value", "event_id"], ["-value", "event_id"], [Order("value", nulls_first=False), "event_id"], ["event_type", "-ts", "event_id"]])
def test_pointers_give_the_same_order(spark, data, by):
    df = spark.read.parquet(f"{data}/events.parquet").withColumn("value", F.when(F.col("event_id") % 9 == 0, F.lit(float("nan"))).when(F.col("event_id") % 10 != 0, F.col("value")))
    sf = model_sort(df, by, f=5)
    a = [r["event_id"] for r in sf.plain().collect()]
    assert a == [r["event_id"] for r in pointer_sorted(sf, 500).collect()] == [r["event_id"] for r in df.orderBy(*[o.column() for o in orders(by)]).collect()]


def test_no_window_or_cross_join_over_everything(spark, data):
    ev = spark.read.parquet(f"{data}/events.parquet")
    left, right = ev.select(F.col("event_id").alias("left_id"), "ts", "event_type"), ev.select("ts", "event_type", "event_id")
    plans = [joins.asof_join(left, right, "ts", "event_type", "event_id", f=8), exact_pid(ev.select("value"), F.col("value"), 8), train_cdf_sql(ev.select(F.col("value").alias("code")), 8).select("leaf", "n", "slope", "hi")]
    assert "Join Cross" not in plans[0]._jdf.queryExecution().optimizedPlan().toString()  # the model's root is a row joined to all
    for df in plans:
        assert "CartesianProduct" not in df._jdf.queryExecution().executedPlan().toString()
        single = [n for n in df._jdf.queryExecution().executedPlan().toString().splitlines() if "Exchange SinglePartition" in n]
        assert len(single) <= 2  # sums of one row each, and the leaves' bands
