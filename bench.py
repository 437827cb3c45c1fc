"""Times the headline queries and prints one JSON line.

BENCH_SF_DIR: folder of tables (default /root/testdata/sf0.1). BENCH_CPUS: local cores (default 8).
Each query runs once to warm up and then BENCH_RUNS times (default 3); its figure is the mean. Results go
to a sink that keeps nothing, so that writing is not what is measured. Beside them, outside the sum ("frame"): every sorter
writing Parquet as the copy does, over lineitem and over generated records (uniform, and skewed ones of the same number and
width), its ratio to the built-in sort, to the merge baseline and to the copy, phases, and bytes moved. Merge sorts run once.
"""

from __future__ import annotations

import json
import os
import time

from equidepth import queries_more as core
from equidepth.measures import metrics
from equidepth.measures.workloads import run_io, run_phases, sorters
from equidepth.plans.extsort import estimated_bytes, model_sort
from equidepth.session import drop_at_exit, local_session, scratch
from equidepth.sources.datagen import SkewSpec, generate_records
from equidepth.sources.io import copy_baseline, read_table, write_noop

HEADLINE = [
    "sort_lineitem_price", "sort_events_value", "sort_documents_text", "sort_orders_multi", "global_cume_dist", "global_ntile", "top_k_price", "exact_percentiles",
    "merge_join_lineitem", "builtin_merge_join", "range_join", "asof_join", "group_by_orderkey", "pricing_summary", "distinct_pairs", "dedup_keep_first", "model_intersect", "inverted_index", "lookup_keys",
]


def seconds(fn, runs: int) -> float:
    fn()
    took = metrics.repeat(fn, runs)
    return sum(took) / len(took)


def written(spark, base: str, label: str, df, by: list[str], runs: int, merges: tuple[str, ...]) -> dict:
    """MB a second of each sorter that reads Parquet, sorts and writes Parquet, and of the copy; ratios of the model sort."""
    source = f"{base}/in-{label}"
    df.write.mode("overwrite").parquet(source)
    stored = spark.read.parquet(source)
    size, every = estimated_bytes(stored), sorters(run_rows=50_000)
    rate = {"copy": metrics.sort_rate(size, seconds(lambda: copy_baseline(stored, f"{base}/copy"), runs))}
    for name in ("model", "radix", "builtin"):
        rate[name] = metrics.sort_rate(size, seconds(lambda n=name: every[n](stored, by).write.mode("overwrite").parquet(f"{base}/out"), runs))
    model = model_sort(stored, by, f=16).model
    rate["model_trained"] = metrics.sort_rate(size, seconds(lambda: model_sort(stored, by, f=16, model=model).plain().write.mode("overwrite").parquet(f"{base}/out"), runs))
    for name in merges:
        began = time.perf_counter()
        every[name](stored, by).write.mode("overwrite").parquet(f"{base}/out")
        rate[name] = metrics.sort_rate(size, time.perf_counter() - began)
    ratios = {f"model_over_{k}": round(rate["model"] / rate[k], 3) for k in ("builtin", "radix", *merges)}
    return {"mb": round(size / 1e6, 1), "mb_per_s": {k: round(v, 2) for k, v in rate.items()}, **ratios, "gap_to_copy": round(metrics.bandwidth_gap(rate["model"], rate["copy"]), 3)}


def main() -> None:
    folder = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1").rstrip("/")
    runs = int(os.environ.get("BENCH_RUNS", "3"))
    spark = local_session()
    found = {n: round(seconds(lambda n=n: write_noop(core.QUERIES[n](spark, folder)), runs), 4) for n in HEADLINE}
    line = read_table(spark, folder, "lineitem")
    size = estimated_bytes(line)
    by, every = ["l_extendedprice"], sorters(run_rows=50_000)
    for name in ("model", "radix", "builtin"):
        found[f"sorter_{name}"] = round(seconds(lambda n=name: write_noop(every[n](line, by)), runs), 4)
    model = model_sort(line, by, f=16).model
    found["sorter_model_trained"] = round(seconds(lambda: write_noop(model_sort(line, by, f=16, model=model).plain()), runs), 4)
    rates = {k: round(metrics.sort_rate(size, v), 2) for k, v in found.items() if k.startswith("sorter_")}
    base = scratch(spark, "bench")
    n = max(20_000, line.count() // 3)
    skewed = generate_records(spark, n, skew=SkewSpec(share=0.5, rule="uniform"))
    frame = {
        "lineitem": written(spark, base, "lineitem", line, by, runs, ("os_merge",)),
        "records_uniform": written(spark, base, "uniform", generate_records(spark, n), ["key"], runs, ("os_merge", "hier_merge")),
        "records_skewed": written(spark, base, "skewed", skewed, ["key"], runs, ("os_merge", "hier_merge")),
    }
    frame["skew_drop_percent"] = {k: round(metrics.skew_drop(v, frame["records_skewed"]["mb_per_s"][k]), 1) for k, v in frame["records_uniform"]["mb_per_s"].items()}
    frame["phases"] = {r["phase"]: round(r["share"], 3) for r in run_phases(line, by, f"{base}/phases").collect()}
    frame["io"] = {r["sorter"]: {"bytes_to_model": round(r["ratio"], 3), "io_share": round(r["io_share"], 3)} for r in run_io(skewed, ["key"], ["model", "radix", "builtin", "os_merge"], f"{base}/io").collect()}
    drop_at_exit(spark, base)
    print(json.dumps({
        "metric": "sum of mean seconds of the headline queries", "value": round(sum(found.values()), 4), "unit": "sec", "queries": found, "sf": os.path.basename(folder),
        "mb_per_s": rates, "model_over_builtin": round(found["sorter_builtin"] / found["sorter_model"], 3), "frame": frame, "runs": runs,
    }))


if __name__ == "__main__":
    main()
