"""Model-partitioned sort: sample, train, one exchange by slice id, sort inside slices; no merge.

A SortedFrame is the lazy result. Rows of slice i all come before those of slice i + 1, a slice is the
shuffle partition of its number, and a slice's place in the whole is the sum of the sizes before it.
Sizes come from a scan of the key column alone, so the sorted rows are made once, when they are used.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field, replace
from functools import cached_property

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window, WindowSpec
from pyspark.sql import functions as F

from ..session import drop_at_exit, scratch
from .cdf_model import FAR, CdfModel, RefinedModel, refine_heavy, train_cdf
from .keys import KeySpec, Order, orders, profile, resolve
from .sampling import SampleSpec, draw_sample

PID = "_pid"
#: Codes of seven bytes each that a refined model looks at, and codes of all columns together that split_ties looks at.
LEVELS = 8
MOST_LEVELS = 16
#: Rows by the plan's size, and bytes of a value, below which a sample is drawn without counting first.
FEW = 50_000_000
WIDTH = 8


def choose_slices(total_bytes: int, slice_bytes: int = 256 << 20, headroom: float = 2.0, least: int = 1) -> int:
    """So many slices that one takes at most slice_bytes in memory; headroom: memory bytes for a stored byte."""
    return max(least, int(-(-total_bytes * headroom // max(1, slice_bytes))))


def concurrent_slices(sizes: list[int], memory: int, mode: str = "prefix") -> int:
    """Most consecutive slices that fit together: the first ones, or (any_window) any run of that many; at least 1."""
    if mode == "prefix":
        held = np.cumsum(sizes) if len(sizes) else np.zeros(0)
        return max(1, int((held <= memory).sum()))
    sums = np.concatenate([[0], np.cumsum(sizes)])
    best = 1
    for s in range(1, len(sizes) + 1):
        if (sums[s:] - sums[:-s] <= memory).all():
            best = s
    return best


def first_shards(f: int) -> int:
    """Shards of the first of two rounds: four times the square root of the slices."""
    return max(1, min(f, int(np.ceil(np.sqrt(f))) * 4))


def leaves_for(f: int) -> int:
    """Leaves of a model for f slices."""
    return int(min(4096, max(64, f // 8)))


def plan_slices(rows: float, row_bytes: float, *, slice_bytes: int = 512 << 20, map_bytes: int = 512 << 20, sample: SampleSpec = SampleSpec(), block_bytes: int = 64 << 10) -> dict:
    """Arithmetic for a sort of any size: slices, rounds, blocks of an exchange, sample, leaves, expected imbalance.

    Two rounds where one would make blocks below block_bytes: first shards of consecutive slices, then slices
    inside each. model_sort takes slices, rounds and leaves from here where it is not told them.
    """
    total = rows * row_bytes
    f = max(1, int(np.ceil(total / slice_bytes)))
    maps = max(1, int(np.ceil(total / map_bytes)))
    one = total / (maps * f)
    rounds = 1 if one >= block_bytes or f < 64 else 2
    coarse = f if rounds == 1 else first_shards(f)
    drawn = float(rows) * sample.rate(int(rows))
    return {
        "rows": float(rows), "bytes": total, "slices": f, "maps": maps, "rounds": rounds, "first_round": coarse, "blocks": float(maps) * coarse,
        "block_bytes": total / (maps * coarse), "sample": drawn, "leaves": leaves_for(f), "imbalance": float(np.sqrt(f / drawn)) if drawn else 0.0,
    }


@dataclass
class SortedFrame:
    """Rows with their slice id, the order asked for, and the model that made the slices."""

    sliced: DataFrame  # before the exchange, with _pid
    by: list[Order]
    f: int
    spec: KeySpec | None
    model: CdfModel | None
    columns: list[str] = field(default_factory=list)
    rows: int | None = None
    rounds: int = 1

    @property
    def spark(self) -> SparkSession:
        return self.sliced.sparkSession

    @cached_property
    def exchanged(self) -> DataFrame:
        """The exchange: a row goes to the shuffle partition of its slice; in two rounds, from the shards of the first."""
        return (self.shards if self.rounds == 2 else self.sliced).repartitionById(self.f, F.col(PID))

    @cached_property
    def shards(self) -> DataFrame:
        """The first of two rounds, carried out: rows are exchanged to shards of consecutive slices and written, a file for each shard.

        A task of the second round reads a part of one shard, so it makes blocks for that shard's slices alone.
        """
        each = -(-self.f // first_shards(self.f))
        path = scratch(self.spark, "shards")
        self.sliced.repartitionById(-(-self.f // each), F.floor(F.col(PID) / each).cast("int")).write.parquet(path)
        drop_at_exit(self.spark, path)
        return self.spark.read.schema(self.sliced.schema).parquet(path)

    @cached_property
    def df(self) -> DataFrame:
        """Ordered inside slices, slices in order: the sorted whole, with _pid."""
        return self.exchanged.sortWithinPartitions(*[o.column() for o in self.by])

    def plain(self) -> DataFrame:
        return self.df.select(*self.columns)

    def window(self, by: list[Order] | None = None) -> WindowSpec:
        return Window.partitionBy(PID).orderBy(*[o.column() for o in (by or self.by)])

    @cached_property
    def sizes(self) -> list[int]:
        """Rows of each slice, empty ones too; at most f numbers."""
        found = {r[0]: r[1] for r in self.sliced.groupBy(PID).count().collect()}
        return [found.get(i, 0) for i in range(self.f)]

    def offsets_frame(self) -> DataFrame:
        """(_pid, rows, row_offset): f rows, the offset excluding the slice itself."""
        starts = np.concatenate([[0], np.cumsum(self.sizes)[:-1]]).astype(int).tolist()
        return self.spark.createDataFrame(list(zip(range(self.f), self.sizes, starts, strict=True)), f"{PID} int, rows long, row_offset long")

    def with_rn(self, name: str = "rn") -> DataFrame:
        """Rows with their 1-based place in the whole, without a global window."""
        numbered = self.exchanged.withColumn("_k", F.row_number().over(self.window()))
        placed = numbered.join(F.broadcast(self.offsets_frame().select(PID, "row_offset")), PID)  # f rows
        return placed.select(*self.columns, (F.col("row_offset") + F.col("_k")).cast("long").alias(name))

    def slice_range(self, low: int, high: int) -> SortedFrame:
        """Only slices low..high. The model turns them into a range of keys, which the scan can use, so the
        others' rows are not read on; sizes already known are kept."""
        part = replace(self, sliced=self.sliced.filter(self._slices(low, high)))
        if "sizes" in self.__dict__:
            part.__dict__["sizes"] = [n if low <= i <= high else 0 for i, n in enumerate(self.sizes)]
        return part

    def _slices(self, low: int, high: int) -> Column:
        if not isinstance(self.model, CdfModel):
            return F.col(PID).between(low, high)
        start, end = self.model.slice_start(low, self.f), self.model.slice_start(high + 1, self.f)
        key, falling = F.col(self.spec.order.name), self.spec.order.descending
        plain = self.spec.kind in ("double", "number")
        code = key if plain else self.spec.code()
        inside = F.lit(True)
        if start > float("-inf"):
            inside = inside & ((code <= F.lit(-start)) if plain and falling else (code >= F.lit(start)))
        if end < float("inf"):
            inside = inside & ((code > F.lit(-end)) if plain and falling else (code < F.lit(end)))
        null_slice = 0 if self.spec.order.nulls_lead else self.f - 1
        return (inside | key.isNull()) if low <= null_slice <= high else (inside & key.isNotNull())


def tie_levels(df: DataFrame, by: list[Order], spec: KeySpec) -> list[Column]:
    """Codes that tell rows apart by column after column: of each column's value, then of the next column's.

    A code speaks for the next column only where it says all of its own column: text of at most LEVELS codes' bytes, whole
    numbers below 2^53. Elsewhere the next code is null, which stands behind all others. A null value is a code of its own.
    """
    levels, whole = [], None
    for k, o in enumerate(by):
        own = spec if k == 0 else resolve(df, o, strip_prefix=False)
        longest = df.agg(F.max(F.octet_length(o.name))).first()[0] or 0 if own.kind == "bytes" else 0
        parts = [own.level(i).code() for i in range(max(1, min(LEVELS, -(-(longest - own.skip) // own.width))) if own.kind == "bytes" and not o.descending else 1)]
        none = F.lit(-FAR if o.nulls_lead else FAR)
        for i, code in enumerate(parts):
            if k:  # a null of the leading column has a slice of its own
                code = F.when(F.col(o.name).isNull(), none if i == 0 else F.lit(0.0)).otherwise(code)
            levels.append(code if whole is None else F.when(whole, code))
        if own.kind == "bytes" and o.descending or len(levels) >= MOST_LEVELS:
            break
        if own.kind == "bytes":
            fits = F.coalesce(F.octet_length(o.name) <= own.skip + LEVELS * own.width, F.lit(True))
        elif own.kind == "number":
            fits = F.coalesce(F.abs(F.col(o.name)) < F.lit(1 << 53), F.lit(True))
        else:
            fits = F.lit(True)
        whole = fits if whole is None else whole & fits
    return levels[:MOST_LEVELS]


def with_slices(df: DataFrame, spec: KeySpec, model: CdfModel, f: int, levels: list[Column] | None = None) -> DataFrame:
    """df with _pid. The code is a column of its own first, so the model's expression does not repeat it."""
    null_slice = 0 if spec.order.nulls_lead else f - 1
    if isinstance(model, RefinedModel):
        made = levels or [spec.level(k).code() for k in range(LEVELS)]
        levels = [f"_code{k}" for k in range(min(model.depth, len(made)))]
        coded = df.withColumns(dict(zip(levels, made, strict=False)))
        return coded.withColumn(PID, F.coalesce(model.pid(f, *[F.col(c) for c in levels]), F.lit(null_slice))).drop(*levels)
    coded = df.withColumn("_code", spec.code())
    return coded.withColumn(PID, F.coalesce(model.pid(F.col("_code"), f), F.lit(null_slice))).drop("_code")


def train_for(df: DataFrame, spec: KeySpec, *, sample: SampleSpec = SampleSpec(), leaves: int | None = None, root: str | None = None, rows: int | None = None) -> tuple[CdfModel, int | None]:
    """(model, rows) of a frame's leading key. Strings get a quantile root, numbers a linear one.

    Where the plan's size says that there are fewer than FEW rows, the sample's rate comes from that size and rows are not counted
    (None), unless the sample turns out smaller than its floor.
    """
    root = root or ("quantile" if spec.kind == "bytes" else "linear")
    if rows is None and sample.method == "bernoulli":
        guess = estimated_bytes(df) // (WIDTH * max(1, len(df.columns)))
        if 0 < guess < FEW:
            codes = draw_sample(df, spec.code(), sample, guess)
            if len(codes) >= sample.floor or sample.rate(guess) >= 1:
                return train_cdf(codes, leaves or 64, root), None
    rows = df.count() if rows is None else rows
    return train_cdf(draw_sample(df, spec.code(), sample, rows), leaves or 64, root), rows


def _level_sample(df: DataFrame, levels: list[Column], sample: SampleSpec, rows: int) -> np.ndarray:
    """Sampled codes, a column for each level; nulls of later levels are infinite, rows without a first code are left out."""
    codes = df.select(*[c.alias(f"c{k}") for k, c in enumerate(levels)])
    part = codes if sample.rate(rows) >= 1 else codes.sample(False, sample.rate(rows), sample.seed)
    table = part.filter(F.col("c0").isNotNull()).toArrow()
    if not table.num_rows:
        return np.zeros((0, len(levels)))
    points = np.stack([table.column(k).to_numpy() for k in range(len(levels))], axis=1)
    return np.where(np.isnan(points), np.inf, points)


def model_sort(
    df: DataFrame, by, *, f: int | None = None, sample: SampleSpec = SampleSpec(), leaves: int | None = None, root: str | None = None,
    model: CdfModel | None = None, ties=None, strip_prefix: bool = True, slice_bytes: int = 256 << 20, rounds: int | None = None, refine: bool = False, split_ties: bool = False,
) -> SortedFrame:
    """Sort by columns ("-name" falls). ties: further columns that settle equal keys.

    f, rounds: slices and rounds of exchange; without them, from the plan for the optimizer's size estimate (plan_slices), at least
    the shuffle partitions. model: a model trained before, for frames that must be sliced alike.
    refine: for rising text keys, give codes heavier than a slice models of their keys' next bytes.
    split_ties: also cut a key heavier than a slice by the further columns. Equal keys then lie in several slices: for sorting and
    numbering, not for joins, groups or ranks by the leading key.
    """
    by = orders(by) + (orders(ties) if ties else [])
    spec = resolve(df, by[0], strip_prefix=strip_prefix)
    rows = df.count() if model is None and (f is None or split_ties or refine) else None
    if f is None or rounds is None:
        size = estimated_bytes(df)
        least = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        plan = plan_slices(max(1, rows or size // 100), size / max(1, rows or size // 100), slice_bytes=slice_bytes)
        if f is None:
            f = choose_slices(size, slice_bytes, least=least)
            f = min(f, max(1, rows)) if rows is not None else f
        rounds = rounds or plan["rounds"]
    leaves = leaves or leaves_for(f)
    levels = None
    if model is None and split_ties and len(by) > 1:
        levels = tie_levels(df, by, spec)
        model = refine_heavy(_level_sample(df, levels, sample, rows), f, leaves)
    elif model is None and refine and spec.kind == "bytes" and not spec.order.descending:
        model = refine_heavy(_level_sample(df, [spec.level(k).code() for k in range(LEVELS)], sample, rows), f, leaves)
    if model is None:
        model, rows = train_for(df, spec, sample=sample, leaves=leaves, root=root, rows=rows)
    return SortedFrame(with_slices(df, spec, model, f, levels), by, f, spec, model, df.columns, rows, rounds)


def estimated_bytes(df: DataFrame) -> int:
    """The optimizer's size of a frame."""
    return min(int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())), 1 << 62)


def presliced_sort(df: DataFrame, by, pid: Column, f: int) -> SortedFrame:
    """Sort by slices of another partitioner; pid must rise with the leading key."""
    by = orders(by)
    return SortedFrame(df.withColumn(PID, pid.cast("int")), by, f, None, None, df.columns)


def radix_sort(df: DataFrame, by, f: int = 16) -> SortedFrame:
    """Equal-width slices, then the same in-slice sort."""
    from .partitioners import radix_pid

    spec = resolve(df, orders(by)[0])
    seen = profile(df, spec)
    pid = radix_pid(spec.code(), seen["low"] or 0.0, seen["high"] or 0.0, f)
    return presliced_sort(df, by, F.coalesce(pid, F.lit(0 if spec.order.nulls_lead else f - 1)), f)


def builtin_sort(df: DataFrame, by) -> DataFrame:
    """Spark's own range sort."""
    return df.orderBy(*[o.column() for o in orders(by)])


def sort_late_payload(df: DataFrame, by, locator: str, **options) -> DataFrame:
    """Sort keys and a unique locator, then fetch the payload by it. `rn` keeps the order.

    Worth it only where the payload is far wider than the key; the payload moves once, by locator.
    """
    names = [o.name for o in orders(by)]
    slim = df.select(*dict.fromkeys([*names, locator]))
    placed = model_sort(slim, by, **options).with_rn()
    return placed.select(locator, "rn").join(df, locator)


def _pointer_keys(table: pa.Table, by: list[Order]) -> tuple[pa.Table, list[tuple[str, str]]]:
    """Columns whose plain order is the one asked for: of each key whether it is null, whether it is NaN, and its value."""
    columns, sorts = {}, []
    for i, o in enumerate(by):
        c, way = table.column(o.name), "descending" if o.descending else "ascending"
        columns[f"n{i}"] = pc.cast(pc.is_null(c), pa.int8())
        sorts.append((f"n{i}", "descending" if o.nulls_lead else "ascending"))
        if pa.types.is_floating(c.type):
            nan = pc.fill_null(pc.is_nan(c), False)
            columns[f"a{i}"] = pc.cast(nan, pa.int8())
            sorts.append((f"a{i}", way))
            c = pc.if_else(nan, 0.0, c)
        columns[f"v{i}"] = c
        sorts.append((f"v{i}", way))
    return pa.table(columns), sorts


def _flushed(batches: Iterator[pa.RecordBatch], by: list[Order], batch_bytes: int, stage: str) -> Iterator[pa.RecordBatch]:
    """A slice's rows in order, `batch_bytes` at a time; stage "sort" stops once the pointers are in order."""
    held = list(batches)
    if not held:
        return
    table = pa.Table.from_batches(held).combine_chunks()
    keys, sorts = _pointer_keys(table, by)
    order = pc.sort_indices(keys, sort_keys=sorts)
    if stage == "sort":
        yield from table.slice(0, 1).to_batches()
        return
    step = max(1, int(batch_bytes * len(table) // max(1, table.nbytes)))
    for at in range(0, len(table), step):
        yield from table.take(order.slice(at, step)).combine_chunks().to_batches()


def pointer_sorted(sf: SortedFrame, batch_bytes: int = 100 << 10, *, stage: str = "flush") -> DataFrame:
    """Slices in order by sorting pointers and fetching rows in that order, batch_bytes at a time, so that what is written leaves in
    one sequence. A slice is held by its task; columns that are no keys are touched once, when they leave.
    """
    by = sf.by
    kinds = ", ".join(f"`{n}` {t}" for n, t in sf.exchanged.dtypes)
    return sf.exchanged.mapInArrow(lambda it: _flushed(it, by, batch_bytes, stage), kinds)


def fragment_matrix(df: DataFrame, pid: Column) -> DataFrame:
    """(reader, pid, rows): how each input split's rows fall into slices."""
    return df.groupBy(F.spark_partition_id().alias("reader"), pid.alias("pid")).agg(F.count("*").alias("rows"))


def makespan(sizes: list[int], workers: int, policy: str = "largest_first") -> int:
    """Finishing time of `workers` taking slices from a queue, in units of size."""
    busy = [0] * max(1, workers)
    for s in sorted(sizes, reverse=True) if policy == "largest_first" else sizes:
        i = busy.index(min(busy))
        busy[i] += s
    return max(busy)
