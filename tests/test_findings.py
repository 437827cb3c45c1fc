"""What failed on larger tables, seen on small ones."""

import os
import time

import pytest
from pyspark.sql import functions as F

from equidepth import queries_more as Q
from equidepth.measures import workloads
from equidepth.plans import mergesort as M
from equidepth.plans.keys import orders
from equidepth.session import scratch, work_dir
from equidepth.streaming import fragments as ST


def test_streams_leave_files_and_not_rows_on_the_driver(spark, data):
    for name in ("stream_session", "stream_static_join"):
        assert Q.QUERIES[name](spark, data).inputFiles()


def test_a_streamed_table_has_all_batches_or_the_last_complete_one(spark, data, tmp_path):
    df = spark.read.parquet(f"{data}/events.parquet").select("event_id", "user_id")
    df.repartition(3).write.parquet(f"{tmp_path}/in")
    stream = lambda: spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    every = ST.run_to_table(stream(), "every", "append", f"{tmp_path}/a")
    users = ST.run_to_table(stream().groupBy("user_id").agg(F.count("*").alias("n")), "users", "complete", f"{tmp_path}/b")
    assert every.inputFiles() and sorted(every.collect()) == sorted(df.collect())
    assert sorted(users.collect()) == sorted(df.groupBy("user_id").agg(F.count("*").alias("n")).collect())
    again = ST.run_to_table(stream(), "again", "append", f"{tmp_path}/a")  # nothing is new
    assert again.count() == 0 and again.schema == every.schema


def _made(spark, n):
    """Keys with nulls, NaN, ties and one heavy value, in chunks."""
    v = F.when(F.col("id") % 11 == 0, F.lit(None)).when(F.col("id") % 13 == 0, F.lit(float("nan"))).when(F.col("id") % 3 == 0, F.lit(5.0)).otherwise((F.hash("id") % 97).cast("double"))
    return spark.range(0, n, 1, 3).select("id", v.alias("v"), F.when(F.col("id") % 7 == 0, F.lit(None)).otherwise(F.md5((F.col("id") % 50).cast("string"))).alias("s"))


_CASES = [("heap", (200,), None, ["v", "id"]), ("heap", (200,), "model", ["-s", "v", "id"]), ("binary", (2,), None, ["-v", "-id"]), ("hier", (4, 6), None, ["s", "id"])]


@pytest.mark.parametrize("strategy,fan_in,routine,by", _CASES)
def test_merges_in_pieces(spark, monkeypatch, strategy, fan_in, routine, by):
    monkeypatch.setattr(M, "PIECE_ROWS", 400)
    df = _made(spark, 3000)
    got = M.merge_runs(M.make_runs(df, by, 100, routine=routine), by, strategy, fan_in).collect()
    want = df.orderBy(*[o.column() for o in orders(by)]).select("id").collect()
    assert [r["id"] for r in sorted(got, key=lambda r: r["rn"])] == [r["id"] for r in want] and sorted(r["rn"] for r in got) == list(range(1, 3001))


def test_no_task_of_a_merge_holds_everything(spark, monkeypatch):
    """Many pieces though a third of all rows has one key; none is far above its share."""
    monkeypatch.setattr(M, "PIECE_ROWS", 400)
    runs, _, _, rows = M.numbered(M.make_runs(_made(spark, 6000), "v", 100))
    sizes = [r["count"] for r in M.merge_level(runs, "v", 1000, rows, True).groupBy(F.shiftright("pos", M.PIECE_BITS)).count().collect()]
    assert sum(sizes) == 6000 and len(sizes) >= 10 and max(sizes) <= 1200


def test_plans_of_pairwise_merges_do_not_double(spark, data):
    """Thirteen levels of pairs: each level was in the plan of the next one twice."""
    df = spark.range(0, 3000, 1, 2).withColumn("v", F.hash("id"))
    out = M.merge_runs(M.make_runs(df, ["v", "id"], 1), ["v", "id"], "binary")
    assert out._jdf.queryExecution().optimizedPlan().toString().count("MapInArrow") <= 12 and out.count() == 3000


def test_insertion_sort_gets_short_slices(spark, data):
    path = data.replace("0.001", "0.01")
    n = spark.read.parquet(f"{path}/events.parquet").count()
    assert n == 10_000
    before = spark.conf.get("spark.sql.shuffle.partitions")
    got = Q.QUERIES["memory_sort_insertion"](spark, path)
    assert sorted(r["rn"] for r in got.collect()) == list(range(1, n + 1)) and spark.conf.get("spark.sql.shuffle.partitions") == before
    from equidepth import queries

    fine = queries._memory(spark, path, "insertion", 100)
    assert sorted(fine.collect()) == sorted(got.collect())


def test_padding_breaks_keys_of_documents(spark, data):
    got = {r["pad"]: r["broken"] for r in Q.QUERIES["pad_violation"](spark, data).collect()}
    assert got["paper"] > 0 and got["low"] == 0


def _left(spark):
    """Folders of intermediate tables, and shuffle files, that lie on disk."""
    own = {x for x in os.listdir(work_dir(spark).removeprefix("file:")) if x.startswith("equidepth-")}
    dirs = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirs()
    return own, {x for d in dirs for _, _, names in os.walk(str(d)) for x in names if x.startswith("shuffle_") and x.endswith(".data")}


def _shuffles_since(spark, before, most):
    for _ in range(50):  # they go a little later
        if len(new := _left(spark)[1] - before) <= most:
            break
        time.sleep(0.2)
    return new


@pytest.mark.parametrize("strategy,fan_in", [("binary", (2,)), ("hier", (4, 6)), ("heap", (200,))])
def test_a_merge_keeps_its_last_level_alone(spark, monkeypatch, strategy, fan_in):
    monkeypatch.setattr(M, "PIECE_ROWS", 400)
    folders, shuffles = _left(spark)
    got = M.merge_runs(M.make_runs(_made(spark, 3000), ["v", "id"], 100), ["v", "id"], strategy, fan_in)
    assert len(_left(spark)[0] - folders) == 1 and not _shuffles_since(spark, shuffles, 0)
    assert sorted(r["rn"] for r in got.collect()) == list(range(1, 3001))


def test_measured_sorts_leave_nothing_on_disk(spark, data, monkeypatch):
    monkeypatch.setattr(M, "PIECE_ROWS", 1000)
    df, names = spark.read.parquet(f"{data}/lineitem.parquet"), ["model", "radix", "builtin", "os_merge", "binary_merge", "hier_merge"]
    folders, shuffles = _left(spark)
    monkeypatch.setattr(workloads, "sorters", lambda f, every=workloads.sorters: every(500, f))
    got = workloads.run_io(df, ["l_extendedprice"], names, scratch(spark, "io"))
    assert [r["sorter"] for r in got.collect()] == names and all(r["written"] > 0 and r["shuffled"] > 0 for r in got.collect())
    assert _left(spark)[0] == folders and len(_shuffles_since(spark, shuffles, 8)) <= 8  # of small counts


@pytest.mark.parametrize("strategy,fan_in,routine,by", [*_CASES, ("binary", (2,), None, ["s", "-v", "id"]), ("hier", (12, 2), "model", ["-v", "id"])])
def test_merges_in_parts(spark, monkeypatch, strategy, fan_in, routine, by):
    monkeypatch.setattr(M, "PIECE_ROWS", 400)
    monkeypatch.setattr(M, "PART_ROWS", 1000)
    levels, merge = [], M.merge_level
    monkeypatch.setattr(M, "merge_level", lambda runs, by, k, n, pieces, before: levels.append((pieces, n)) or merge(runs, by, k, n, pieces, before))
    df = _made(spark, 3000)
    got = M.merge_runs(M.make_runs(df, by, 100, routine=routine), by, strategy, fan_in).collect()
    want = df.orderBy(*[o.column() for o in orders(by)]).select("id").collect()
    assert [r["id"] for r in sorted(got, key=lambda r: r["rn"])] == [r["id"] for r in want] and sorted(r["rn"] for r in got) == list(range(1, 3001))
    assert sum(n for _, n in levels) % 3000 == 0 and max(n for _, n in levels) <= 2000


def test_parts_of_a_level_hold_each_row_once(spark):
    runs, by = M.make_runs(_made(spark, 6000), "v", 100), orders("v")
    runs, left, _, rows = M.numbered(runs)
    for order in (by, orders("-v"), orders("-s")):
        code, cuts = M.key_cuts(runs, order, rows)
        for k in (left, 31, 21, 2):
            parts = M.level_parts(order, k, left, code, cuts)
            hits = sum((F.when(c, 1).otherwise(0) for c in parts), F.lit(0))
            assert len(parts) > 1 and runs.agg(F.min(hits), F.max(hits)).first() == (1, 1)
