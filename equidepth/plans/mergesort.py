"""Sorting by runs and merges: the way without a model, for comparison.

Runs are chunks of the input as it lies, sorted each on its own and written. A level of merging exchanges all rows. Groups of
runs that a task can hold are merged there whole; longer ones are cut into pieces of consecutive keys, and a task merges the
parts of the group's runs that fall into its piece. That each level moves every row is the cost being compared.

On disk lie two levels at most, the one read and the one being written, and the exchange of a part of the rows: levels of large
tables are merged part after part, and the level before goes once all parts are written.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import drop, drop_at_exit, made_here, scratch, shuffles_freed, written
from .keys import Order, orders, resolve
from .memsort import memory_order, touch_up
from .sampling import SampleSpec, draw_sample

#: Rows that a task merges at once, about; and the bits of pos below the number of a piece.
PIECE_ROWS = 100_000
PIECE_BITS = 33
#: Parts of a level that are exchanged one after the other, and the rows above which a level has parts.
PARTS = 4
PART_ROWS = 10_000_000

PRESETS = {
    # run routine, merge strategy, fan-in of each level
    "os": ("merge", "heap", (16,)),
    "A": ("intro", "hier", (200, 6)),
    "B": ("quick", "heap", (200,)),
    "C": ("merge", "hier", (64, 8)),
}


def make_runs(df: DataFrame, by, run_rows: int = 10_000, *, payload: bool = True, locator: str | None = None, routine: str | None = None) -> DataFrame:
    """df with run_id and pos: consecutive chunks of about run_rows, each sorted in its task.

    payload=False keeps the keys and a locator; fetch_payload() brings the rest at the end.
    routine: one of memsort's, on the leading key's codes, touched up by whole keys; without it Spark's own sort.
    """
    by = orders(by)
    if not payload:
        if locator is None:
            raise ValueError("runs without payload need a locator")
        df = df.select(*dict.fromkeys([*(o.name for o in by), locator]))
    if routine is not None:
        spec = resolve(df, by[0])
        schema = ", ".join(f"`{n}` {t}" for n, t in df.dtypes) + ", run_id long, pos long"
        end = -np.inf if by[0].nulls_lead else np.inf
        return df.withColumn("_code", spec.code()).withColumn("_part", F.spark_partition_id()).mapInArrow(lambda it: _runs(it, by, run_rows, routine, end), schema)
    low = (1 << 33) - 1
    placed = df.withColumn("_row", F.monotonically_increasing_id())
    placed = placed.withColumn("_run", F.floor(F.col("_row").bitwiseAND(low) / run_rows).cast("long"))
    placed = placed.sortWithinPartitions("_run", *[o.column() for o in by], "_row")
    at = F.monotonically_increasing_id().bitwiseAND(low) - F.col("_run") * run_rows + 1  # a partition's runs before this one are full
    return placed.withColumns({"run_id": F.shiftright("_row", 33) * 1_000_000 + F.col("_run"), "pos": at}).drop("_row", "_run")


def _runs(batches: Iterator[pa.RecordBatch], by: list[Order], run_rows: int, routine: str, end: float) -> Iterator[pa.RecordBatch]:
    """Runs of a partition: codes ordered by the routine, then an insertion pass by whole keys."""
    held, rows, number = [], 0, 0

    def run() -> pa.Table:
        table = pa.Table.from_batches(held)
        codes = pc.fill_null(table.column("_code"), end).to_numpy()
        order, _ = touch_up(_keys(table, by), memory_order(codes, routine))
        name = (table.column("_part")[0].as_py() << 33) + number
        out = table.drop_columns(["_code", "_part"]).take(pa.array(order))
        return out.append_column("run_id", pa.array([name] * len(order), pa.int64())).append_column("pos", pa.array(range(1, len(order) + 1), pa.int64()))

    for batch in batches:
        while batch.num_rows:
            take = min(batch.num_rows, run_rows - rows)
            held.append(batch.slice(0, take))
            rows, batch = rows + take, batch.slice(take)
            if rows == run_rows:
                yield from run().combine_chunks().to_batches()
                held, rows, number = [], 0, number + 1
    if held:
        yield from run().combine_chunks().to_batches()


def fetch_payload(sorted_keys: DataFrame, df: DataFrame, locator: str) -> DataFrame:
    return sorted_keys.select(locator, "rn").join(df, locator)


class _Turned:
    """A value whose order is turned round."""

    __slots__ = ("v",)

    def __init__(self, v):
        self.v = v

    def __lt__(self, other):
        return other.v < self.v

    def __eq__(self, other):
        return other.v == self.v


def _keys(table: pa.Table, by: list[Order]) -> list:
    """What rises with the order asked for, a value or a tuple a row: of each column whether it is null or NaN, where some are, and its value."""
    parts = []
    for o in by:
        c = table.column(o.name)
        if c.null_count:
            parts.append((pc.is_null(c).to_numpy() != o.nulls_lead).tolist())
        if pa.types.is_date32(c.type):
            c = c.cast(pa.int32())
        elif pa.types.is_timestamp(c.type):
            c = c.cast(pa.int64())
        elif pa.types.is_boolean(c.type):
            c = c.cast(pa.int8())
        if pa.types.is_floating(c.type):
            v = pc.fill_null(c, 0.0).to_numpy()
            nan = np.isnan(v)
            if nan.any():
                parts.append((nan != o.descending).tolist())
                v = np.where(nan, 0.0, v)
            parts.append((-v if o.descending else v).tolist())
        elif pa.types.is_integer(c.type):
            v = pc.fill_null(c, 0).to_numpy()
            parts.append((~v if o.descending else v).tolist())
        else:
            v = c.to_pylist()
            if c.null_count:
                some = next((x for x in v if x is not None), 0)
                v = [some if x is None else x for x in v]
            parts.append([_Turned(x) for x in v] if o.descending else v)
    return parts[0] if len(parts) == 1 else list(zip(*parts, strict=True))


def _kway(table: pa.Table, by: list[Order]) -> np.ndarray:
    """Order of the rows of some runs, which lie one after the other, by a heap of the runs' heads; two runs by one plain merge."""
    run = table.column("run_id").to_numpy()
    ends = [0, *(np.flatnonzero(run[1:] != run[:-1]) + 1).tolist(), len(run)]
    if len(ends) == 2:
        return np.arange(len(run))
    keys = _keys(table, by)
    if len(ends) == 3:
        return np.array(sorted(range(len(run)), key=keys.__getitem__), np.int64)  # this sort finds the two rising runs and merges them
    return np.fromiter(heapq.merge(*[range(a, b) for a, b in zip(ends, ends[1:], strict=False)], key=keys.__getitem__), np.int64, len(run))


def _groups(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """The rows of each group; a group's rows follow each other."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        group = batch.column(batch.schema.get_field_index("_group")).to_numpy()
        if held and len(group) and held[-1].column("_group")[-1].as_py() != group[0]:
            yield pa.Table.from_batches(held)
            held = []
        ends = [0, *(np.flatnonzero(group[1:] != group[:-1]) + 1).tolist(), len(group)]
        for a, b in zip(ends, ends[1:], strict=False):
            if a:
                yield pa.Table.from_batches(held)
                held = []
            if b > a:
                held.append(batch.slice(a, b - a))
    if held:
        yield pa.Table.from_batches(held)


def _merged(batches: Iterator[pa.RecordBatch], by: list[Order], names: list[str], pieces: bool, before: int) -> Iterator[pa.RecordBatch]:
    first = (before + TaskContext.get().partitionId() << PIECE_BITS) + 1 if pieces else 1
    for table in _groups(batches):
        n = len(table)
        out = table.take(pa.array(_kway(table, by))).drop_columns(["run_id", "pos"]).rename_columns({"_group": "run_id"})
        yield from out.append_column("pos", pa.array(np.arange(first, first + n))).select(names).combine_chunks().to_batches()


def numbered(runs: DataFrame) -> tuple[DataFrame, int, int, int]:
    """(the runs written, their run_id counted from 0; runs; rows of the longest; rows)."""
    kept = written(runs, "runs")
    sizes = kept.groupBy("run_id").agg(F.count("*").alias("n"))
    left, longest, rows = sizes.agg(F.count("*"), F.max("n"), F.sum("n")).first()
    ranks = sizes.select("run_id", (F.row_number().over(Window.orderBy("run_id")) - 1).cast("long").alias("_rank"))  # one row a run
    names = [F.col("_rank").alias("run_id") if c == "run_id" else F.col(c) for c in runs.columns]
    return kept.join(F.broadcast(ranks), "run_id").select(*names), left, longest or 0, rows or 0


def merge_level(runs: DataFrame, by, fan_in: int, rows: int, pieces: bool, before: int = 0) -> DataFrame:
    """Runs, numbered from 0 and of so many rows together, merged `fan_in` at a time: one exchange of all rows.

    pieces: the groups are too long for a task. Rows are dealt by group, key, run and place, so equal keys can be cut too, and
    pos is the number of the piece, from `before` on, and the place in it; else it is the place in the group. runs are then read twice.
    """
    by = orders(by)
    grouped = runs.withColumn("_group", F.floor(F.col("run_id") / fan_in).cast("long"))
    parts = max(1, -(-rows // PIECE_ROWS))
    if pieces:
        dealt = grouped.repartitionByRange(parts, "_group", *[o.column() for o in by], "run_id", "pos")
    else:
        dealt = grouped.repartition(parts, "_group")
    names = runs.columns
    schema = ", ".join(f"`{n}` {t}" for n, t in runs.dtypes)
    return dealt.sortWithinPartitions("_group", "run_id", "pos").mapInArrow(lambda it: _merged(it, by, names, pieces, before), schema)


def key_cuts(runs: DataFrame, by: list[Order], rows: int) -> tuple[Column | None, list[float]]:
    """(code of the leading key, codes that cut all rows into PARTS of about one size); none for a key without a code. Equal keys are not cut."""
    if dict(runs.dtypes)[by[0].name] == "binary":
        return None, []
    try:
        code = resolve(runs, by[0]).code()
    except TypeError:
        return None, []
    sample = np.sort(draw_sample(runs, code, SampleSpec(cap=100_000), rows))
    return code, np.unique(sample[[len(sample) * i // PARTS for i in range(1, PARTS)]]).tolist() if len(sample) else []


def level_parts(by: list[Order], fan_in: int, left: int, code: Column | None, cuts: list[float]) -> list[Column]:
    """Conditions that deal a level's rows out, each row to one: whole groups where there are enough, else ranges of the leading key inside groups.

    Parts follow each other as the groups do and, inside a group, as the order asked for does.
    """
    groups = max(1, -(-left // fan_in))
    n = min(groups, PARTS)
    ends = [groups * i // n * fan_in for i in range(n + 1)]
    own = [F.col("run_id").between(a, b - 1) for a, b in zip(ends, ends[1:], strict=False)]
    each = -(-PARTS // n)
    step = PARTS // each
    cuts = cuts[step - 1 :: step] if each > 1 else []
    if code is None or not cuts:
        return own
    ranges = [code < cuts[0], *((code >= a) & (code < b) for a, b in zip(cuts, cuts[1:], strict=False)), code >= cuts[-1]]
    with_null = 0 if by[0].nulls_lead else len(cuts)
    return [g & F.coalesce(r, F.lit(i == with_null)) for g in own for i, r in enumerate(ranges)]


def merged_files(runs: DataFrame, by: list[Order], fan_in: int, left: int, rows: int, pieces: bool, code: Column | None, cuts: list[float]) -> DataFrame:
    """A level, merged part after part and written, so that no more than a part lies in an exchange."""
    spark = runs.sparkSession
    parts = level_parts(by, fan_in, left, code, cuts if pieces else []) if rows > PART_ROWS else [F.lit(True)]
    sizes = runs.agg(*[F.count_if(c) for c in parts]).first() if len(parts) > 1 else [rows]
    path, before = scratch(spark, "merged"), 0
    drop_at_exit(spark, path)
    for part, n in zip(parts, sizes, strict=True):
        if n:
            with shuffles_freed(spark):
                merge_level(runs.filter(part), by, fan_in, n, pieces, before).write.mode("append").parquet(path)
            before += -(-n // PIECE_ROWS)
    return spark.read.schema(runs.schema).parquet(path)


def merge_runs(runs: DataFrame, by, strategy: str = "heap", fan_in: tuple[int, ...] = (200, 6)) -> DataFrame:
    """Sorted rows with rn. "heap": all runs at once; "binary": pairs; "hier": fan_in by level.

    Levels are written if the rows are too many for a task; a level's files go when the next one is written.
    """
    by, spark = orders(by), runs.sparkSession
    with made_here() as kept, shuffles_freed(spark):
        runs, left, longest, rows = numbered(runs)
    level, pieces, code, cuts = 0, rows > PIECE_ROWS, None, []
    if rows > PART_ROWS:
        code, cuts = key_cuts(runs, by, rows)
    while left > 1 or level == 0:
        k = max(2, left) if strategy == "heap" else 2 if strategy == "binary" else fan_in[min(level, len(fan_in) - 1)]
        longest = min(rows, longest * min(k, max(1, left)))
        if pieces:
            with made_here() as made:
                runs = merged_files(runs, by, k, left, rows, longest > PIECE_ROWS, code, cuts)
            for path in kept:
                drop(spark, path)
            kept = made
        else:
            runs = merge_level(runs, by, k, rows, False)
        left, level = math.ceil(left / k), level + 1
    if not pieces:
        return runs.withColumnRenamed("pos", "rn").drop("run_id")
    runs = runs.withColumn("_piece", F.shiftright("pos", PIECE_BITS))
    sizes = runs.groupBy("_piece").agg(F.count("*").alias("n"))
    starts = sizes.select("_piece", F.coalesce(F.sum("n").over(Window.orderBy("_piece").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_start"))  # one row a piece
    place = (F.col("_start") + F.col("pos").bitwiseAND((1 << PIECE_BITS) - 1)).cast("long")
    return runs.join(F.broadcast(starts), "_piece").withColumn("pos", place).withColumnRenamed("pos", "rn").drop("run_id", "_piece", "_start")


def external_merge_sort(df: DataFrame, by, preset: str = "os", run_rows: int = 10_000) -> DataFrame:
    """A preset of run creation and merging: "os" (heap of all runs), "A", "B", "C"."""
    routine, strategy, fan_in = PRESETS[preset]
    return merge_runs(make_runs(df, by, run_rows, routine=routine), by, strategy, fan_in)
