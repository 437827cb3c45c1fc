"""Micro-batches appended to slices by a frozen model, and the usual windowed forms over streams."""

from __future__ import annotations

import json
from collections.abc import Iterator
from typing import Any

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import StructType

from ..plans.cdf_model import CdfModel
from ..plans.extsort import PID, with_slices
from ..plans.keys import KeySpec, orders
from ..session import drop_at_exit, scratch


def stream_table(spark: SparkSession, folder: str, name: str, *, files_per_batch: int | None = None, schema: StructType | None = None) -> DataFrame:
    """One table of a folder as a file stream."""
    schema = schema or spark.read.parquet(f"{folder}/{name}.parquet").schema
    reader = spark.readStream.schema(schema).option("pathGlobFilter", f"{name}*.parquet")
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    return reader.parquet(folder)


def stream_fragments(stream: DataFrame, spec: KeySpec, model: CdfModel, f: int, path: str, checkpoint: str):
    """Appends every micro-batch's rows to their slices' folders under path, by the batch's number.

    A batch that is run again replaces what it wrote before, so restarts leave no row twice.
    """

    def append(batch: DataFrame, batch_id: int) -> None:
        placed = with_slices(batch, spec, model, f).withColumnRenamed(PID, "pid")
        placed.write.mode("overwrite").partitionBy("pid").parquet(f"{path}/batch={batch_id}")

    return stream.writeStream.foreachBatch(append).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def finalize_fragments(spark: SparkSession, path: str, by, schema: str | StructType, f: int) -> DataFrame:
    """The sealed whole with rn: each slice's fragments are gathered and sorted; slices follow each other."""
    base = schema if isinstance(schema, str) else ", ".join(f"`{x.name}` {x.dataType.simpleString()}" for x in schema)
    rows = spark.read.schema(f"{base}, batch bigint, pid int").parquet(path)
    names = [c for c in rows.columns if c not in ("batch", "pid")]
    sizes = rows.groupBy("pid").agg(F.count("*").alias("n"))
    offsets = sizes.select("pid", F.coalesce(F.sum("n").over(Window.orderBy("pid").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("row_offset"))  # f rows
    w = Window.partitionBy("pid").orderBy(*[o.column() for o in orders(by)])
    placed = rows.repartitionById(f, F.col("pid")).withColumn("_k", F.row_number().over(w))
    return placed.join(F.broadcast(offsets), "pid").select(*names, (F.col("row_offset") + F.col("_k")).cast("long").alias("rn"))


def with_lateness(stream: DataFrame, ts: str, delay: str) -> DataFrame:
    """Watermarks need a timestamp with a zone: files without one are read as the session's."""
    return stream.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, delay)


def late_rows(batch: DataFrame, ts: str, watermark: Column) -> tuple[DataFrame, DataFrame]:
    """(in time, late) rows of a batch by a given watermark."""
    late = F.col(ts) < watermark
    return batch.filter(~late | F.col(ts).isNull()), batch.filter(late)


def tumbling(df: DataFrame, ts: str, width: str, keys: list[str], aggs: list[Column]) -> DataFrame:
    """Works on streams and tables alike."""
    g = df.groupBy(F.window(ts, width), *keys).agg(*aggs)
    return g.select(F.col("window.start").alias("start"), F.col("window.end").alias("end"), *[c for c in g.columns if c != "window"])


def sliding(df: DataFrame, ts: str, width: str, slide: str, keys: list[str], aggs: list[Column]) -> DataFrame:
    g = df.groupBy(F.window(ts, width, slide), *keys).agg(*aggs)
    return g.select(F.col("window.start").alias("start"), F.col("window.end").alias("end"), *[c for c in g.columns if c != "window"])


def session(df: DataFrame, ts: str, gap: str, keys: list[str], aggs: list[Column]) -> DataFrame:
    g = df.groupBy(F.session_window(ts, gap).alias("window"), *keys).agg(*aggs)
    return g.select(F.col("window.start").alias("start"), F.col("window.end").alias("end"), *[c for c in g.columns if c != "window"])


def stream_dedup(stream: DataFrame, keys: list[str], ts: str, delay: str) -> DataFrame:
    return stream.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, delay).dropDuplicatesWithinWatermark(keys)


def stream_static_join(stream: DataFrame, table: DataFrame, on, how: str = "inner") -> DataFrame:
    return stream.join(table, on, how)


def stream_interval_join(left: DataFrame, right: DataFrame, lkey: str, rkey: str, lts: str, rts: str, within: str, delay: str) -> DataFrame:
    """Pairs of equal key whose right time lies within `within` after the left one's."""
    l, r = left.withWatermark(lts, delay), right.withWatermark(rts, delay)
    return l.join(r, (F.col(lkey) == F.col(rkey)) & (F.col(rts) >= F.col(lts)) & (F.col(rts) <= F.col(lts) + F.expr(f"interval {within}")))


def _counted(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for b in batches:
        yield b.groupby(["lane", "pid"]).size().reset_index(name="n")


DRIFT = "slice int, rows bigint, share double, drift double"


def _drift(f: int):
    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        counts = json.loads(state.get[0]) if state.exists else [0] * f
        for b in batches:
            for p, n in zip(b["pid"], b["n"], strict=True):
                counts[int(p)] += int(n)
        state.update((json.dumps(counts),))
        total = sum(counts) or 1
        yield pd.DataFrame({"slice": range(f), "rows": counts, "share": [c / total for c in counts], "drift": [c / total * f - 1 for c in counts]})

    return update


def drift_monitor(stream: DataFrame, spec: KeySpec, model: CdfModel, f: int, lanes: int = 1) -> DataFrame:
    """Shares of slices against 1 / f so far, kept as f counters a lane; far from 0: time to train anew.

    Rows are counted by slice where they are read; a lane receives at most f numbers from each task of a batch.
    """
    placed = with_slices(stream, spec, model, f).select((F.pmod(F.xxhash64(F.col(PID)), F.lit(lanes))).alias("lane"), F.col(PID).alias("pid"))
    placed = placed.mapInPandas(_counted, "lane bigint, pid int, n bigint")
    return placed.groupBy("lane").applyInPandasWithState(_drift(f), DRIFT, "counts string", "update", GroupStateTimeout.NoTimeout)


def run_to_table(stream: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Runs a stream over what is there now into files of the shared folder: the last batch's rows in mode complete, else those of all batches.

    A batch that is run again replaces what it wrote before. Nothing passes through the driver.
    """
    spark, path = stream.sparkSession, scratch(stream.sparkSession, "streamed")
    done: list[int] = []

    def put(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{batch_id}")
        done.append(batch_id)

    writer = stream.writeStream.foreachBatch(put).queryName(name).outputMode(mode).trigger(availableNow=True)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    q: Any = writer.start()
    q.awaitTermination()
    if not done:
        return spark.createDataFrame([], stream.schema)
    drop_at_exit(spark, path)
    kept = done[-1:] if mode == "complete" else dict.fromkeys(done)
    return spark.read.schema(stream.schema).parquet(*[f"{path}/{k}" for k in kept])
