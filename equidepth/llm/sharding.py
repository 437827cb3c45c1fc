"""Consistent-hash ring with virtual nodes and bounded loads.

Every row hashes to a point of the ring and belongs to the shard of the next virtual node
clockwise. A shard takes no more than its capacity; what overflows goes on clockwise to the next
virtual node whose shard has room. With ``load="rows"`` and ``slack=0`` the capacities are the
whole-number shares of the row count, so shards differ by one row at most; with a slack, or with
``load="bytes"``, a shard holds at most (1 + slack) times its share and fewer rows move when the
ring grows.

How it is spread: the ring is cut into a fixed number of cells. One aggregation counts the rows of each cell, and a cell with many
is cut by a hash of the text into sub-cells, in proportion (at most 200,000 of them in all), so a key that repeats is spread. Another counts
the load of each sub-cell, the driver walks the ring over those counts and cuts them into pieces, and rows find their piece
by their rank inside the sub-cell. No window spans more than a sub-cell.

Nulls: a null key hashes like any other value, a null text counts no bytes. Very long texts count their bytes and travel only if the
caller keeps them in the frame. Ties in rank go by key, text hash and load; rows alike in all are interchangeable, and so are
repeated rows. An empty table gives an empty result. Columns of the input named like ours (``shard``, ``slot``) are replaced; others
cannot clash, as the input's columns are renamed while it works.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import shield, text_or_empty


@dataclass(frozen=True)
class Ring:
    """`vnodes` virtual nodes for each shard on a ring of `cells` equal cells."""

    shards: int
    vnodes: int = 64
    cells: int = 1 << 14
    seed: int = 17

    def owners(self) -> np.ndarray:
        """(position, shard) of all virtual nodes, clockwise. Adding a shard adds nodes and moves none."""
        taken: dict[int, int] = {}
        for shard in range(self.shards):
            for v in range(self.vnodes):
                probe = 0
                while True:
                    digest = hashlib.blake2b(f"{self.seed}:{shard}:{v}:{probe}".encode(), digest_size=8).digest()
                    at = int.from_bytes(digest, "big") % self.cells
                    if at not in taken:
                        taken[at] = shard
                        break
                    probe += 1
        return np.array(sorted(taken.items()), dtype=np.int64).reshape(-1, 2)


def capacities(total: int, shards: int, slack: float, exact: bool) -> list[int]:
    """Most load of each shard: the whole-number shares when exact, else (1 + slack) times the mean."""
    if exact:
        return [total // shards + (s < total % shards) for s in range(shards)]
    return [int(np.ceil((1 + slack) * total / shards))] * shards


def walk(ring: Ring, loads: dict[tuple[int, int], int], caps: list[int]) -> list[tuple[int, int, int, int, int]]:
    """Pieces (cell, sub, from, to, shard): home shards first, then overflow clockwise to the next with room."""
    nodes = ring.owners()
    at, owner = nodes[:, 0], nodes[:, 1]
    room, pieces, late = list(caps), [], []
    for (cell, sub), load in sorted(loads.items()):
        node = int(np.searchsorted(at, cell)) % len(at)
        take = min(load, room[owner[node]])
        if take:
            pieces.append((cell, sub, 0, take, int(owner[node])))
            room[owner[node]] -= take
        if load > take:
            late.append((cell, sub, take, load, node))
    for cell, sub, start, end, node in late:
        steps = 0
        while start < end:
            node = (node + 1) % len(at)
            steps += 1
            if steps > len(at):  # only rounding of capacities in bytes can bring us here
                pieces.append((cell, sub, start, end, int(np.argmax(room))))
                break
            if room[owner[node]] > 0:
                take = min(end - start, room[owner[node]])
                pieces.append((cell, sub, start, start + take, int(owner[node])))
                room[owner[node]] -= take
                start, steps = start + take, 0
    return pieces


def _pieces_frame(spark, pieces: list[tuple]) -> DataFrame:
    names = ["_cell", "_sub", "_from", "_to", "shard", "_slot0"]
    columns = list(zip(*pieces, strict=True)) if pieces else [[]] * 6
    kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int64()]
    return spark.createDataFrame(pa.table({n: pa.array(list(c), k) for n, c, k in zip(names, columns, kinds, strict=True)}))


def assign_shards(
    df: DataFrame, shards: int, *, key: str = "doc_id", text: str = "text", load: str = "rows", slack: float = 0.0,
    vnodes: int = 64, rows_per_sub: int = 50_000, most_subs: int = 200_000, seed: int = 17,
) -> DataFrame:
    """df with `shard` int and `slot` long (gapless from 0 inside each shard).

    load: "rows" or "bytes" (UTF-8 bytes of `text` plus 8). slack 0 with "rows" fills shards exactly.
    """
    if load not in ("rows", "bytes"):
        raise ValueError("load is 'rows' or 'bytes'")
    df = df.drop("shard", "slot")
    df, names, restore = shield(df)
    key, text = names[key], names[text]
    ring = Ring(shards, vnodes, seed=seed)
    spread = F.xxhash64(text_or_empty(text))
    point = F.xxhash64(F.lit(seed), F.col(key))
    weight: Column = F.lit(1).cast("long") if load == "rows" else F.octet_length(text_or_empty(text)).cast("long") + 8
    laid = df.withColumns({
        "_point": point, "_spread": spread, "_weight": weight,
        "_cell": F.shiftrightunsigned(point, 64 - (ring.cells - 1).bit_length()).cast("int"),
    })
    spark = df.sparkSession
    counts = {r[0]: r[1] for r in laid.groupBy("_cell").count().collect()}  # a row for each cell
    each = max(rows_per_sub, -(-sum(counts.values()) // most_subs))
    large = [(c, -(-n // each)) for c, n in sorted(counts.items()) if n > each]
    if large:
        laid = laid.join(F.broadcast(spark.createDataFrame(large, "_cell int, _subs int")), "_cell", "left")  # at most a row for each cell
        laid = laid.withColumn("_sub", F.pmod("_spread", F.coalesce("_subs", F.lit(1))).cast("int")).drop("_subs")
    else:
        laid = laid.withColumn("_sub", F.lit(0))
    loads = {(r[0], r[1]): r[2] for r in laid.groupBy("_cell", "_sub").agg(F.sum("_weight")).collect()}
    total = sum(loads.values())
    pieces = walk(ring, loads, capacities(total, shards, slack, exact=load == "rows" and slack == 0))
    inside = Window.partitionBy("_cell", "_sub").orderBy("_point", F.col(key).asc_nulls_last(), "_spread", "_weight")
    rank = (F.row_number().over(inside) - 1).cast("long") if load == "rows" else F.sum("_weight").over(inside.rowsBetween(Window.unboundedPreceding, 0)) - F.col("_weight")
    filled, numbered = [0] * shards, []
    for cell, sub, start, end, shard in pieces:
        numbered.append((cell, sub, start, end, shard, filled[shard]))
        filled[shard] += end - start
    cut = F.broadcast(_pieces_frame(spark, numbered))  # at most cells + most_subs + overflow pieces
    found = laid.withColumn("_rank", rank).join(cut, ["_cell", "_sub"])
    found = found.filter((F.col("_rank") >= F.col("_from")) & (F.col("_rank") < F.col("_to")))
    if load == "rows":
        return restore(found.withColumn("slot", F.col("_slot0") + F.col("_rank") - F.col("_from")), "shard", "slot")
    counts = sorted(tuple(r) for r in found.groupBy("_cell", "_sub", "shard").count().collect())
    base, offset = [0] * shards, []
    for cell, sub, shard, n in counts:
        offset.append((cell, sub, 0, 0, shard, base[shard]))
        base[shard] += n
    start = F.broadcast(_pieces_frame(spark, offset).select("_cell", "_sub", "shard", F.col("_slot0").alias("_base")))
    order = Window.partitionBy("_cell", "_sub", "shard").orderBy("_rank", "_point", "_spread")
    numbered_rows = found.withColumn("_n", F.row_number().over(order)).join(start, ["_cell", "_sub", "shard"])
    return restore(numbered_rows.withColumn("slot", (F.col("_base") + F.col("_n") - 1).cast("long")), "shard", "slot")


def op1_query(spark, sf_dir: str) -> DataFrame:
    """All documents on 24 shards whose row counts differ by one at most."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    body = text_or_empty("text")
    digest = docs.select(
        "doc_id", (F.octet_length(body).cast("long") + 8).alias("size"), F.crc32(F.encode(body, "UTF-8")).cast("long").alias("text_crc32"), "text",
    )
    # only the digest columns travel: the text is needed for its hash alone
    slim = digest.withColumn("text_key", F.xxhash64(text_or_empty("text")).cast("string")).drop("text")
    placed = assign_shards(slim, 24, text="text_key")
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
