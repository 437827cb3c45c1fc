"""Benchmark decontamination by SimHash windows, a multi-index over Hamming blocks, and exact verification.

A benchmark item and every window of a document that is as long as the item (counted in shingles) get a
64-bit SimHash of their shingles, weighed by occurrence. Eight 8-bit blocks index the items: fingerprints
within 8 * (r + 1) - 1 bits of each other agree within r bits in some block, so looking up each block's
neighbours within r bits finds every item within that radius. Candidates are verified by the weighted
Jaccard similarity of their shingle bags (sum of least counts over sum of greatest).

Windows that share no shingle with an item have similarity 0 to it, so windows are fingerprinted at
every position where they hold at least one shingle of an item of their length; no document, position
or candidate is passed over otherwise.

Scale: documents are read once per block of items (`block_items` of them and `block_chars` characters at most, but for an item
that has more) and never shuffled; a block's index, bounded so, travels with the tasks. Larger benchmarks run in more
blocks. without_leaks tells each row by itself while it is scanned: no join, no digest.

Nulls: null and empty texts and items match nothing; items without an id are left out. Items of fewer words than a shingle match
only a document of the same few words. Very long texts are searched whole, a span of windows at a time. Ties: of equally similar
windows the first span's counts, in a span the one nearest in bits, then the first. Repeated rows each report; repeated items count once. Columns cannot clash:
find_leaks reads key and text alone, without_leaks renames the input's columns while it works. Empty tables give empty results.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import U64, WordHashes, mix64, shield, shingles_of, word_hashes

SPAN = 50_000  # positions whose windows are fingerprinted at once
CELLS = 2_000_000  # windows times items compared at once
_POP8 = np.array([bin(i).count("1") for i in range(256)], np.uint8)
MATCHES = "row bigint, item_id bigint, start_word int, n_words int, distance int, similarity double"
ARROW = pa.schema([("row", pa.int64()), ("item_id", pa.int64()), ("start_word", pa.int32()), ("n_words", pa.int32()), ("distance", pa.int32()), ("similarity", pa.float64())])


@dataclass(frozen=True)
class LeakSpec:
    """Shingle width, least similarity, and bits by which a block may differ (radius 8 * (bits + 1) - 1)."""

    width: int = 5
    threshold: float = 0.8
    block_bits: int = 2

    @property
    def radius(self) -> int:
        return 8 * (self.block_bits + 1) - 1


def simhash_windows(shingles: np.ndarray, starts: np.ndarray, length: int) -> np.ndarray:
    """SimHash of shingles[s : s + length] for each s of starts."""
    low, high = int(starts.min()), int(starts.max()) + length
    bits = np.unpackbits(mix64(shingles[low:high]).astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
    sums = np.zeros((len(bits) + 1, 64), np.int32)
    np.cumsum(bits, axis=0, out=sums[1:])
    ones = sums[starts - low + length] - sums[starts - low]
    return np.packbits(2 * ones > length, axis=1).view(">u8").ravel().astype(U64)


def weighted_jaccard(a: np.ndarray, b: np.ndarray) -> float:
    """Of two bags of shingles."""
    values, inverse = np.unique(np.concatenate([a, b]), return_inverse=True)
    x = np.bincount(inverse[: len(a)], minlength=len(values))
    y = np.bincount(inverse[len(a) :], minlength=len(values))
    most = np.maximum(x, y).sum()
    return float(np.minimum(x, y).sum() / most) if most else 0.0


@dataclass
class ItemIndex:
    """Items by their number of shingles; their fingerprints in blocks; the items that hold a shingle."""

    ids: list[int]
    bags: list[np.ndarray]
    spec: LeakSpec
    by_length: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = field(default_factory=dict)
    holders: dict[int, list[int]] = field(default_factory=dict)
    members: np.ndarray = field(default_factory=lambda: np.empty(0, U64))
    gate: np.ndarray = field(default_factory=lambda: np.zeros(1 << 20, bool))

    def __post_init__(self):
        near = _POP8[np.arange(256)[:, None] ^ np.arange(256)[None, :]] <= self.spec.block_bits  # value x item byte
        lengths = np.array([len(b) for b in self.bags])
        for n in np.unique(lengths):
            own = np.flatnonzero(lengths == n)
            prints = np.array([simhash_windows(self.bags[i], np.array([0]), int(n))[0] for i in own], U64)
            blocks = prints.astype(">u8").view(np.uint8).reshape(-1, 8)
            self.by_length[int(n)] = (own, prints, np.stack([near[:, blocks[:, b]] for b in range(8)]))  # block, value, item
        for i, bag in enumerate(self.bags):
            for x in np.unique(bag).tolist():
                self.holders.setdefault(x, []).append(i)
        self.members = np.array(sorted(self.holders), U64)
        self.gate[(self.members & U64((1 << 20) - 1)).astype(np.int64)] = True

    def matches(self, shingles: np.ndarray) -> list[tuple[int, int, int, float]]:
        """(item, start, distance, similarity): the best window of each item that reaches the threshold."""
        at = np.flatnonzero(self.gate[(shingles & U64((1 << 20) - 1)).astype(np.int64)])
        if not len(at):
            return []
        where = np.searchsorted(self.members, shingles[at])
        at = at[self.members[np.minimum(where, len(self.members) - 1)] == shingles[at]]
        positions: dict[int, list[int]] = {}
        for p in at.tolist():
            for i in self.holders[int(shingles[p])]:
                positions.setdefault(i, []).append(p)
        lengths: dict[int, list[int]] = {}
        for i in positions:
            lengths.setdefault(len(self.bags[i]), []).append(i)
        found = []
        for n, items in lengths.items():
            size = min(n, len(shingles))
            held = np.unique(np.concatenate([positions[i] for i in items]))
            mark = np.zeros(len(shingles) - size + 2, np.int32)
            np.add.at(mark, np.clip(held - size + 1, 0, len(shingles) - size), 1)
            np.add.at(mark, np.minimum(held, len(shingles) - size) + 1, -1)
            starts = np.flatnonzero(np.cumsum(mark)[:-1] > 0)
            own, fixed, near = self.by_length[n]
            wanted = np.isin(own, items)
            own, fixed, near = own[wanted], fixed[wanted], near[:, :, wanted]
            best = [(0.0, 0, 0)] * len(own)
            for part in _spans(starts, max(1, CELLS // len(own))):
                prints = simhash_windows(shingles, part, size)
                bytes_ = prints.astype(">u8").view(np.uint8).reshape(-1, 8)
                hit = np.zeros((len(part), len(own)), bool)
                for b in range(8):
                    hit |= near[b][bytes_[:, b]]
                distance = np.bitwise_count(prints[:, None] ^ fixed[None, :])
                hit &= distance <= self.spec.radius
                for j in np.flatnonzero(hit.any(axis=0)):
                    rows = np.flatnonzero(hit[:, j])
                    for r in rows[np.argsort(distance[rows, j], kind="stable")]:
                        if best[j][0] == 1.0:
                            break
                        s = int(part[r])
                        similar = weighted_jaccard(shingles[s : s + size], self.bags[own[j]])
                        if similar > best[j][0]:
                            best[j] = (similar, s, int(distance[r, j]))
            found += [(int(own[j]), s, d, x) for j, (x, s, d) in enumerate(best) if x >= self.spec.threshold]
        return found


def _spans(starts: np.ndarray, most: int) -> Iterator[np.ndarray]:
    """Rising starts in runs of at most `most` that lie within SPAN positions."""
    at = 0
    while at < len(starts):
        end = min(at + most, int(np.searchsorted(starts, starts[at] + SPAN)))
        yield starts[at:end]
        at = end


def build_index(items: list[tuple[int, str | None]], spec: LeakSpec) -> ItemIndex:
    memo = WordHashes()
    pairs = [(i, shingles_of(word_hashes(t, memo), spec.width)) for i, t in items]
    pairs = [(i, s) for i, s in pairs if len(s)]
    return ItemIndex([i for i, _ in pairs], [s for _, s in pairs], spec)


def _scan(batches: Iterator[pa.RecordBatch], index: ItemIndex) -> Iterator[pa.RecordBatch]:
    memo, spec = WordHashes(), index.spec
    for batch in batches:
        rows = []
        for row, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            shingles = shingles_of(word_hashes(text.as_py(), memo), spec.width)
            for item, start, distance, similar in index.matches(shingles) if len(shingles) else ():
                rows.append((row, index.ids[item], start, min(len(index.bags[item]), len(shingles)) + spec.width - 1, distance, similar))
        columns = list(zip(*rows, strict=True)) or [()] * len(ARROW)
        yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, ARROW, strict=True)], schema=ARROW)


def indexes(items: DataFrame, spec: LeakSpec, block_items: int = 5000, block_chars: int = 8_000_000) -> Iterator[ItemIndex]:
    """Indexes of the distinct items, block by block."""
    block, chars = [], 0
    for item in items.select(F.col("item_id").cast("long"), "text").filter(F.col("item_id").isNotNull() & F.col("text").isNotNull()).distinct().toLocalIterator():
        if block and (len(block) == block_items or chars + len(item[1]) > block_chars):
            yield build_index(block, spec)
            block, chars = [], 0
        block.append((item[0], item[1]))
        chars += len(item[1])
    if block:
        yield build_index(block, spec)


def find_leaks(docs: DataFrame, items: DataFrame, spec: LeakSpec = LeakSpec(), *, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(row, item_id, start_word, n_words, distance, similarity): row is the document's key."""
    slim = docs.select(F.col(key).cast("long").alias("row"), F.col(text).alias("text")).filter(F.col("text").isNotNull() & (F.col("text") != ""))
    results = [slim.mapInArrow(lambda it, index=index: _scan(it, index), MATCHES) for index in indexes(items, spec) if index.ids]
    return reduce(DataFrame.unionByName, results) if results else docs.sparkSession.createDataFrame([], MATCHES)


def _clean(batches: Iterator[pa.RecordBatch], index: ItemIndex, at: int) -> Iterator[pa.RecordBatch]:
    memo, spec = WordHashes(), index.spec
    for batch in batches:
        kept = [not (len(s := shingles_of(word_hashes(text.as_py(), memo), spec.width)) and index.matches(s)) for text in batch.column(at)]
        yield batch.filter(pa.array(kept, pa.bool_()))


def without_leaks(docs: DataFrame, items: DataFrame, spec: LeakSpec = LeakSpec(), *, text: str = "text") -> DataFrame:
    """docs without the rows whose text has a leak."""
    inner, names, restore = shield(docs)
    at = inner.columns.index(names[text])
    for index in indexes(items, spec):
        if index.ids:
            inner = inner.mapInArrow(lambda it, index=index: _clean(it, index, at), inner.schema)
    return restore(inner)


def op6_query(spark, sf_dir: str) -> DataFrame:
    """Every benchmark item found in every document."""
    docs, items = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "benchmark"))
    return find_leaks(docs, items).select(F.col("row").alias("doc_id"), "item_id", "start_word", "n_words", "distance", "similarity")
