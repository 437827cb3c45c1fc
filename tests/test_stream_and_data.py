import math

import pytest
from pyspark.sql import functions as F

from equidepth.functions import udf
from equidepth.measures import metrics, workloads
from equidepth.measures.metrics import PhaseTimer, io_bytes
from equidepth.plans.cdf_model import train_cdf
from equidepth.plans.extsort import model_sort
from equidepth.plans.keys import ascii_code
from equidepth.sources import io
from equidepth.sources.datagen import SkewSpec, calibrate_share, generate_records
from equidepth.streaming import fragments as ST


def test_fragments_survive_a_restart(spark, data, tmp_path):
    df = spark.read.parquet(f"{data}/events.parquet").select("event_id", "value")
    sf = model_sort(df, ["value", "event_id"], f=4)
    df.repartition(3).write.parquet(f"{tmp_path}/in/events.parquet")
    stream = lambda: spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/events.parquet")
    for _ in range(2):  # the second start finds nothing new
        ST.stream_fragments(stream(), sf.spec, sf.model, 4, f"{tmp_path}/out", f"{tmp_path}/cp").awaitTermination()
    got = ST.finalize_fragments(spark, f"{tmp_path}/out", ["value", "event_id"], df.schema, 4)
    want = [(r["event_id"], i + 1) for i, r in enumerate(df.orderBy("value", "event_id").collect())]
    assert sorted((r["event_id"], r["rn"]) for r in got.collect()) == sorted(want)


def test_late_rows_go_aside(spark, data):
    df = spark.read.parquet(f"{data}/events.parquet")
    cut = df.selectExpr("max(ts) - interval 5 days AS c").first()["c"]
    kept, late = ST.late_rows(df, "ts", F.lit(cut))
    assert kept.count() + late.count() == df.count() and late.filter(F.col("ts") >= F.lit(cut)).count() == 0


def test_drift_is_seen(spark, tmp_path):
    model = train_cdf([float(v) for v in range(1000)], 16)
    from equidepth.plans.keys import KeySpec, Order

    df = spark.createDataFrame([(float(v % 100),) for v in range(400)], "v double")
    df.write.parquet(f"{tmp_path}/in/drift.parquet")
    s = spark.readStream.schema(df.schema).parquet(f"{tmp_path}/in/drift.parquet")
    got = ST.run_to_table(ST.drift_monitor(s, KeySpec(Order("v"), "double"), model, 4), "drift_seen", "update", f"{tmp_path}/cp").collect()
    assert max(r["drift"] for r in got) == pytest.approx(3.0) and sum(r["rows"] for r in got) == 400


def code_frame(df):
    return df.select(ascii_code(F.col("key")).cast("double").alias("c"))


def test_generated_keys(spark):
    n = 100_000
    df = generate_records(spark, n)
    r = df.agg(F.min(F.length("key")), F.max(F.length("key")), F.min(F.length("payload")), F.max(F.length("payload")), F.countDistinct("key")).first()
    assert tuple(r)[:4] == (10, 10, 90, 90) and r[4] == n
    even = metrics.bin_skew(metrics.equi_width_histogram(code_frame(df), "c")).first()["deviation_percent"]
    assert even == pytest.approx(100 * math.sqrt(1000 / n), rel=0.15)  # sampling noise alone
    skewed = metrics.bin_skew(metrics.equi_width_histogram(code_frame(generate_records(spark, n, skew=SkewSpec())), "c")).first()
    assert skewed["deviation_percent"] > 10 * even and skewed["max_over_mean"] > 6  # half of all rows share one prefix under the literal rule


def test_share_can_be_calibrated(spark):
    share = calibrate_share(spark, 50_000, 65.65, rule="uniform", steps=6)
    df = generate_records(spark, 50_000, skew=SkewSpec(share=share, rule="uniform"))
    got = metrics.bin_skew(metrics.equi_width_histogram(code_frame(df), "c", low=0.0, high=float(95**9))).first()
    assert got["deviation_percent"] == pytest.approx(65.65, rel=0.12)


def test_written_order_and_counters(spark, data, tmp_path):
    df = spark.read.parquet(f"{data}/orders.parquet")
    sf = model_sort(df, ["o_totalprice", "o_orderkey"], f=4)
    timer = PhaseTimer(spark)
    with timer.phase("write"):
        manifest = io.write_sorted(sf, f"{tmp_path}/s")
    m = manifest.orderBy("pid").collect()
    assert [r["row_offset"] for r in m] == [sum(x["rows"] for x in m[:i]) for i in range(len(m))] and sum(r["rows"] for r in m) == df.count()
    part = io.read_sorted(spark, f"{tmp_path}/s", low=10, high=20)
    assert sorted(r["rn"] for r in part.collect()) == list(range(10, 21))
    assert timer.seconds["write"] > 0 and io_bytes(timer.counters["write"]) > 0


def test_io_of_merging_is_more(spark, data, tmp_path):
    df = spark.read.parquet(data.replace("0.001", "0.01") + "/orders.parquet")
    rows = {r["sorter"]: r for r in workloads.run_io(df, ["o_totalprice"], ["model", "hier_merge"], str(tmp_path)).collect()}
    assert rows["model"]["ratio"] == 1.0 and rows["hier_merge"]["ratio"] > 1.0


def test_registered_functions(spark):
    model = train_cdf([float(v) for v in range(100)], 8)
    names = udf.register_all(spark, model, 4)
    assert {"model_pid", "quantile_slices"} <= set(names)
    assert [r[0] for r in spark.sql("SELECT model_pid(cast(x AS double)) FROM VALUES (0), (60), (99), (NULL) t(x)").collect()] == [0, 2, 3, None]
    assert spark.sql("SELECT * FROM split_fixed('abcde', 2)").first() == ("ab", "cde")
