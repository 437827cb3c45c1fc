"""Indexes on sorted slices: sparse entries, zone maps, lookups, learned positions, shards, inverted files."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.cdf_model import CdfModel
from ..plans.extsort import PID, SortedFrame, model_sort, with_slices
from ..plans.keys import KeySpec, Order
from ..session import written


def build_index(sf: SortedFrame, key: str, every: int = 100) -> DataFrame:
    """(key, pid, pos): every `every`-th row of each slice, its first row always; pos is 0-based inside the slice."""
    numbered = sf.exchanged.withColumn("pos", (F.row_number().over(sf.window()) - 1).cast("long"))
    return numbered.filter(F.col("pos") % every == 0).select(F.col(key).alias("key"), F.col(PID).alias("pid"), "pos")


def zone_map(df: DataFrame, cols: list[str], by: str | Column = PID) -> DataFrame:
    """Rows, least and greatest value of cols for each slice (or other part)."""
    aggs = [F.count("*").alias("rows")]
    for c in cols:
        aggs += [F.min(c).alias(f"min_{c}"), F.max(c).alias(f"max_{c}")]
    return df.groupBy(F.col(by).alias("pid") if isinstance(by, str) else by.alias("pid")).agg(*aggs)


def range_scan(sf: SortedFrame, low, high) -> DataFrame:
    """Rows with low <= key <= high; the bounds reach the scan."""
    key = sf.by[0].name
    return sf.sliced.filter(F.col(key).between(F.lit(low), F.lit(high))).select(*sf.columns)


def lookup(sf: SortedFrame, keys: DataFrame, name: str, *, max_keys: int = 1_000_000) -> DataFrame:
    """Rows whose key is among keys.name, read between the least and the greatest of them.

    keys of more than max_keys rows are joined slice by slice instead of being broadcast.
    """
    key = sf.by[0].name
    wanted = keys.select(F.col(name).alias("_key")).filter(F.col("_key").isNotNull()).distinct()
    seen = wanted.agg(F.min("_key"), F.max("_key"), F.count("*")).first()
    near = sf.sliced.filter(F.col(key).between(F.lit(seen[0]), F.lit(seen[1])))
    if seen[2] <= max_keys:
        return near.join(F.broadcast(wanted), F.col(key) == F.col("_key")).select(*sf.columns)
    placed = with_slices(wanted.withColumnRenamed("_key", key), sf.spec, sf.model, sf.f).withColumnRenamed(key, "_key").withColumnRenamed(PID, "_kp")
    return sf.exchanged.join(placed.repartitionById(sf.f, F.col("_kp")), (F.col(PID) == F.col("_kp")) & (F.col(key) == F.col("_key"))).select(*sf.columns)


@dataclass(frozen=True)
class LearnedIndex:
    """A model of a sorted column and the largest distance between predicted and true place."""

    model: CdfModel
    spec: KeySpec
    rows: int
    error: int

    def span(self, key: Column) -> tuple[Column, Column]:
        """0-based places between which a stored key lies."""
        at = self.model.position(key, self.rows)
        return F.greatest(F.lit(0), at - self.error), F.least(F.lit(self.rows - 1), at + self.error)


def learned_index(sf: SortedFrame) -> LearnedIndex:
    """Measures the model's error on all rows of the frame."""
    placed = sf.with_rn("_rn").withColumn("_code", sf.spec.code())
    n = sum(sf.sizes)
    far = placed.agg(F.max(F.abs(sf.model.position(F.col("_code"), n) - (F.col("_rn") - 1)))).first()[0]
    return LearnedIndex(sf.model, sf.spec, n, int(far or 0))


def learned_locate(index: LearnedIndex, keys: DataFrame, name: str) -> DataFrame:
    """keys with the place predicted and the span that holds it."""
    spec = KeySpec(Order(name), index.spec.kind, index.spec.skip, index.spec.width)
    coded = keys.withColumn("_code", spec.code())
    low, high = index.span(F.col("_code"))
    return coded.select(*keys.columns, index.model.position(F.col("_code"), index.rows).alias("place"), low.alias("low"), high.alias("high"))


def shard(df: DataFrame, key: str, f: int, **options) -> DataFrame:
    """df with `shard`, disjoint ranges of key of about equal size."""
    sf = model_sort(df, [key], f=f, **options)
    return sf.sliced.withColumnRenamed(PID, "shard")


def cluster_by(df: DataFrame, keys: list[str], *, f: int = 16, bits: int = 4, **options) -> DataFrame:
    """Rows near in one or two keys near each other: two keys are laid on a curve of interleaved slice bits."""
    if len(keys) == 1:
        return model_sort(df, keys, f=f, **options).plain()
    side = 1 << bits
    a, b = (model_sort(df, [k], f=side, **options) for k in keys)
    both = df.withColumn("_ca", a.spec.code()).withColumn("_cb", b.spec.code())
    both = both.withColumns({"_a": F.coalesce(a.model.pid(F.col("_ca"), side), F.lit(0)), "_b": F.coalesce(b.model.pid(F.col("_cb"), side), F.lit(0))})
    z = F.lit(0)
    for i in range(bits):
        z = z + F.shiftleft(F.shiftright(F.col("_a"), i).bitwiseAND(1), 2 * i + 1) + F.shiftleft(F.shiftright(F.col("_b"), i).bitwiseAND(1), 2 * i)
    cells = side * side
    return both.withColumn("cell", z).drop("_ca", "_cb", "_a", "_b").repartitionById(f, F.floor(F.col("cell") * f / cells).cast("int")).sortWithinPartitions("cell", *keys)


def tokens(text: Column) -> Column:
    """Lower-case words between white space."""
    return F.filter(F.split(F.lower(text), r"\s+"), lambda x: x != "")


def _postings(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(term, doc, positions) of each document's words, by sorting (document, term, position) of a batch at once."""
    for batch in batches:
        words = batch.column(1)
        sizes = np.diff(words.offsets.to_numpy())
        if not sizes.sum():
            continue
        coded = words.flatten().dictionary_encode()
        row = np.repeat(np.arange(len(sizes)), sizes)
        place = np.arange(len(row)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        cell = row.astype(np.int64) * len(coded.dictionary) + coded.indices.to_numpy()
        order = np.argsort(cell, kind="stable")  # positions rise inside a cell
        first = np.flatnonzero(np.concatenate([[True], np.diff(cell[order]) != 0]))
        offsets = pa.array(np.append(first, len(order)), pa.int32())
        yield pa.RecordBatch.from_arrays(
            [coded.dictionary.take(coded.indices.take(pa.array(order[first]))), batch.column(0).take(pa.array(row[order[first]])), pa.ListArray.from_arrays(offsets, pa.array(place[order], pa.int32()))],
            names=["term", "doc", "positions"],
        )


def _gathered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row for each run of equal (term, part), its postings as they come; a run that a batch cuts is held until its end."""

    def runs(table: pa.Table, last: bool) -> tuple[pa.RecordBatch | None, pa.Table]:
        table = table.combine_chunks()
        term, part = table.column("term"), table.column("part").to_numpy()
        ids = term.combine_chunks().dictionary_encode().indices.to_numpy() if len(table) else np.zeros(0, np.int32)
        first = np.flatnonzero(np.concatenate([[True], (ids[1:] != ids[:-1]) | (part[1:] != part[:-1])]))
        bounds = np.append(first, len(table)) if last else first
        if len(bounds) < 2:
            return None, table
        done = table.slice(0, int(bounds[-1])).combine_chunks()
        postings = pa.StructArray.from_arrays([done.column("doc").combine_chunks(), done.column("positions").combine_chunks()], names=["doc", "positions"])
        at = pa.array(bounds[:-1])
        out = pa.RecordBatch.from_arrays([done.column("term").take(at).combine_chunks(), done.column("part").take(at).combine_chunks(), pa.ListArray.from_arrays(pa.array(bounds, pa.int32()), postings)], names=["term", "part", "postings"])
        return out, table.slice(int(bounds[-1]))

    held: pa.Table | None = None
    for batch in batches:
        table = pa.Table.from_batches([batch])
        done, held = runs(table if held is None or not len(held) else pa.concat_tables([held, table]), False)
        if done is not None:
            yield done
    if held is not None and len(held):
        done, _ = runs(held, True)
        if done is not None:
            yield done


def inverted_index(docs: DataFrame, *, key: str = "doc_id", text: str = "text", posting_cap: int = 4096, max_frequent: int = 1_000_000) -> DataFrame:
    """(term, part, postings): postings (doc, positions) by doc; terms of more than posting_cap documents are cut into parts.

    A document's positions are gathered by term where it is read (_postings), so texts are split once and one exchange by (term, part)
    is left. A document is in a frequent term's part by its hash, so no task gathers more than about posting_cap documents of
    one term. Frequent terms are few (all postings / posting_cap at most); they are counted before they are broadcast.
    """
    slim = docs.select(F.col(key).alias("doc"), tokens(F.col(text)).alias("words")).filter(F.size("words") > 0)
    kind = dict(slim.dtypes)["doc"]
    each = written(slim.mapInArrow(_postings, f"term string, doc {kind}, positions array<int>"), "postings")
    held = each.groupBy("term").agg(F.count("*").alias("df"))
    frequent = held.filter(F.col("df") > posting_cap).select("term", F.ceil(F.col("df") / posting_cap).cast("int").alias("parts"))
    few = frequent.limit(max_frequent + 1).count() <= max_frequent
    cut = each.join(F.broadcast(frequent) if few else frequent, "term", "left")
    cut = cut.withColumn("part", F.when(F.col("parts").isNotNull(), F.pmod(F.xxhash64("doc"), F.col("parts")).cast("int")).otherwise(0))
    rows = cut.select("term", "part", "doc", "positions").repartition("term", "part").sortWithinPartitions("term", "part", "doc")
    return rows.mapInArrow(_gathered, f"term string, part int, postings array<struct<doc:{kind},positions:array<int>>>")


def search(index: DataFrame, terms: list[str], mode: str = "and") -> DataFrame:
    """(doc, hits): documents with all (and) or any (or) of the terms; hits: occurrences of all terms."""
    wanted = sorted({t.lower() for t in terms})
    hits = index.filter(F.col("term").isin(wanted)).select("term", F.explode("postings").alias("p"))
    each = hits.groupBy(F.col("p.doc").alias("doc")).agg(F.countDistinct("term").alias("n"), F.sum(F.size("p.positions")).alias("hits"))
    return each.filter(F.col("n") >= (len(wanted) if mode == "and" else 1)).select("doc", F.col("hits").cast("long").alias("hits"))
