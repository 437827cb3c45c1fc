"""What several operators of this subpackage need: a shared work folder, word hashes, size checks.

Intermediate tables go to the folder that the cluster names in ``spark.checkpoint.dir``; only
where the master is local and the session names none (tests on one machine) a folder of our own is made and set.
"""

from __future__ import annotations

import contextlib
import re

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import work_dir, written  # noqa: F401  (work_dir for those who name a path themselves)

WORD = re.compile(r"\w+")
U64 = np.uint64
_MUL = U64(0x9E3779B97F4A7C15)
_MIX1 = U64(0xBF58476D1CE4E5B9)
_MIX2 = U64(0x94D049BB133111EB)


def materialize(df: DataFrame, tag: str) -> DataFrame:
    """Write df to the shared folder and return a frame that reads it: cuts lineage, survives lost executors; removed when the driver ends."""
    return written(df, tag)


@contextlib.contextmanager
def arrow_rows(spark: SparkSession, rows: int):
    """Arrow batches of at most `rows` rows for what runs inside, where rows are wide."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, rows)
    try:
        yield
    finally:
        spark.conf.set(name, before)


def shield(docs: DataFrame):
    """(docs with columns c0, c1, ..., old name to new, a function that gives a result its old names back).

    An input may hold any column names; ours cannot meet them then.
    """
    names = {n: f"c{i}" for i, n in enumerate(docs.columns)}

    def restore(df: DataFrame, *more: str, without: tuple[str, ...] = ()) -> DataFrame:
        return df.select(*[F.col(c).alias(n) for n, c in names.items() if n not in without], *more)

    return docs.toDF(*names.values()), names, restore


def text_or_empty(col: str | Column = "text") -> Column:
    return F.coalesce(F.col(col) if isinstance(col, str) else col, F.lit(""))


def broadcast_if_small(df: DataFrame, max_rows: int) -> tuple[DataFrame, bool]:
    """df (already materialized) with a broadcast hint when its counted rows keep within max_rows."""
    small = df.limit(max_rows + 1).count() <= max_rows
    return (F.broadcast(df) if small else df), small


class WordHashes(dict):
    """64-bit hash of each word, remembered; emptied when it holds `most` words, so memory is bounded."""

    def __init__(self, most: int = 250_000):
        super().__init__()
        self.most = most

    def __missing__(self, word: str) -> int:
        if len(self) >= self.most:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word.encode("utf-8", "surrogatepass"))
        return value


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values."""
    x = (x ^ (x >> U64(30))) * _MIX1
    x = (x ^ (x >> U64(27))) * _MIX2
    return x ^ (x >> U64(31))


def words_of(text: str | None) -> list[str]:
    """Lower-case runs of word characters."""
    return WORD.findall(text.lower()) if text else []


def shingles_of(hashes: np.ndarray, width: int) -> np.ndarray:
    """64-bit hashes of all runs of `width` words; fewer words than that make one shingle, no word none."""
    n = len(hashes)
    if n == 0:
        return np.empty(0, U64)
    take = min(n, width)
    out = np.zeros(n - take + 1, U64)
    for k in range(take):
        out = out * _MUL + hashes[k : n - take + 1 + k]
    return mix64(out)


def word_hashes(text: str | None, memo: WordHashes) -> np.ndarray:
    words = words_of(text)
    return np.fromiter(map(memo.__getitem__, words), U64, len(words))


def chunks_by_length(lengths, budget: int):
    """Slices (from, to) of consecutive rows whose lengths together keep within budget (one row at least)."""
    start, total = 0, 0
    for i, n in enumerate(lengths):
        if i > start and total + n > budget:
            yield start, i
            start, total = i, 0
        total += n
    if start < len(lengths):
        yield start, len(lengths)
