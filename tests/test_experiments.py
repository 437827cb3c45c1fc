"""Every experiment runs, and its measures move the way they are said to."""

import pytest
from pyspark.sql import functions as F

from equidepth import queries_more as Q
from equidepth.measures import workloads
from equidepth.plans.extsort import model_sort
from equidepth.sources.datagen import SkewSpec, calibrate_share, generate_records


def rows(spark, data, name):
    return [r.asDict() for r in Q.QUERIES[name](spark, data).collect()]


def test_uniform_records_fill_bins_evenly_and_skewed_ones_do_not(spark, data):
    path = data.replace("0.001", "0.01")
    even, n = rows(spark, path, "w01_uniform_records")[0]["deviation_percent"], spark.read.parquet(f"{path}/lineitem.parquet").count()
    assert even < 100 * (3 * 1000 / n) ** 0.5
    assert all(r["deviation_percent"] > 10 * even for r in rows(spark, path, "w02_skewed_records"))


def test_deviation_of_the_published_file_by_calibrated_share(spark):
    share = calibrate_share(spark, 50_000, 65.65, rule="uniform")
    assert 0.0 < share < 1.0


def test_storage_covers_media_formats_and_sorters(spark, data):
    got = rows(spark, data, "w03_storage")
    assert {"disk", "memory"} <= {r["medium"] for r in got} and {r["sorter"] for r in got} == {"model", "os_merge", "builtin"}
    assert {(r["format"], r["codec"]) for r in got if r["medium"] == "disk"} == {("parquet", "none"), ("parquet", "snappy"), ("parquet", "zstd"), ("csv", "none"), ("orc", "none")}
    assert all(r["mb_per_s"] > 0 and r["copy_mb_per_s"] > 0 for r in got)


def test_skew_is_measured_on_like_files(spark, data):
    got = rows(spark, data, "w05_skew_effect")
    assert {r["sorter"] for r in got} == {"model", "radix", "builtin", "os_merge"} and all(r["uniform"] > 0 and r["skewed"] > 0 for r in got)
    files = Q._records(spark)
    sizes = [f.agg(F.count("*"), F.sum(F.length("key") + F.length("payload"))).first() for f, _ in files.values()]
    assert sizes[0] == sizes[1]


def test_eight_sizes(spark, data):
    got = rows(spark, data, "w06_scale")
    assert {r["sorter"] for r in got} == {"model", "builtin", "os_merge"} and all(len({r["size"] for r in got if r["sorter"] == s}) == 8 for s in ("model", "builtin", "os_merge"))


def test_merging_costs_more_energy(spark, data):
    got = {r["sorter"]: r for r in rows(spark, data, "w07_energy")}
    assert got["os_merge"]["joules"] == pytest.approx(65.0 * got["os_merge"]["seconds"]) and got.keys() == {"model", "builtin", "radix", "os_merge"}


def test_phases_are_all_there_and_sum_to_one(spark, data):
    got = rows(spark, data, "w08_phases")
    assert [r["phase"] for r in got] == ["train", "partition", "sort", "coalesce", "flush"] and sum(r["share"] for r in got) == pytest.approx(1)


def test_merging_moves_more_bytes_than_slicing(spark, data):
    got = {r["sorter"]: r for r in rows(spark, data.replace("0.001", "0.01"), "w09_io")}
    assert got["model"]["ratio"] == 1 and all(got[k]["ratio"] > 1 for k in ("os_merge", "binary_merge", "hier_merge"))
    assert got["binary_merge"]["shuffled"] > got["os_merge"]["shuffled"]


def test_error_falls_with_the_sample_and_the_first_batch_misleads(spark, data):
    got = rows(spark, data.replace("0.001", "0.01"), "w10_sample_curve")
    assert {r["rate"] for r in got} == {0.001, 0.005, 0.01, 0.05, 0.2, 1.0} and {r["key"] for r in got} == {"ts", "value", "l_extendedprice"}
    for key in ("ts", "value", "l_extendedprice"):
        own = {r["rate"]: r["cdf_rms"] for r in got if r["key"] == key and r["method"] == "bernoulli"}
        assert own[1.0] <= own[0.2] * 1.2 and own[0.2] < own[0.001]
    clustered = {r["method"]: r["cdf_rms"] for r in got if r["key"] == "ts" and r["rate"] == 0.05}
    assert clustered["first_batch"] > 3 * clustered["bernoulli"]


def test_model_slices_vary_less_than_equal_widths_on_skewed_records(spark, data):
    got = rows(spark, data, "w11_balance_records")
    for f in (8, 16, 64):
        own = {r["partitioner"]: r for r in got if r["f"] == f}
        assert own["model"]["reduction_percent"] > 23 and own["model"]["cv"] < own["radix"]["cv"]


@pytest.mark.parametrize("name", ["w11_balance_events", "w11_balance_text", "w11_balance_price"])
def test_balance_of_the_given_tables(spark, data, name):
    got = rows(spark, data.replace("0.001", "0.01"), name)
    for f in {r["f"] for r in got}:
        own = {r["partitioner"]: r for r in got if r["f"] == f}
        assert own.keys() == {"model", "radix", "quantile", "sketch", "hash"}
        if name != "w11_balance_price":
            assert own["model"]["var"] < own["radix"]["var"]


def test_payloads_every_way(spark, data):
    for name in ("w12_coalesce", "w12_coalesce_documents"):
        got = rows(spark, data, name)
        assert [(r["payload"], r["batch_bytes"]) for r in got] == [("with_key", 0), ("by_locator", 0), ("by_pointer", 1 << 10), ("by_pointer", 100 << 10), ("by_pointer", 64 << 20)]


def test_memory_routines_over_all_rows(spark, data):
    n = spark.read.parquet(f"{data}/lineitem.parquet").count()
    got = rows(spark, data, "w13_memory_sorts")
    assert all(r["rows"] == n and r["equal"] for r in got)
    assert {r["routine"] for r in got if r["inside"] == "slices"} == set(workloads.memsort.ROUTINES) and len([r for r in got if r["inside"] == "runs"]) == 6


def test_plans_and_rounds(spark, data):
    plans = rows(spark, data, "w15_plans")
    assert plans[-1]["rounds"] == 2 and plans[0]["rounds"] == 1 and plans[-1]["block_bytes"] > 64 << 10
    one, two = rows(spark, data, "w15_two_rounds")
    assert one["ordered"] and two["ordered"] and one["rows"] == two["rows"] and two["shards"] > 1
    assert two["slices_a_task"] < one["slices_a_task"] and two["blocks"] < one["blocks"]


def test_touch_up_work_falls_with_width(spark, data):
    got = rows(spark, data, "w17_code_width")
    for key, widest in (("url", 9), ("text", 7), ("records", 9)):
        own = {r["width"]: r for r in got if r["key"] == key}
        assert sorted(own) == list(range(1, widest + 1)) and own[1]["moved"] >= own[widest]["moved"]
        assert all(own[w + 1]["mean_displacement"] <= 1.1 * own[w]["mean_displacement"] for w in range(1, widest))


def test_skewed_records_sort_whole(spark):
    df = generate_records(spark, 20_000, skew=SkewSpec(share=1.0))
    sf = model_sort(df, ["key", "rec_idx"], f=16, refine=True)
    got = [r["key"] for r in sorted(sf.with_rn().select("key", "rn").collect(), key=lambda r: r["rn"])]
    assert got == sorted(got)
