"""MinHash near-dedup by probability Jaccard (ProbMinHash), banding, exact verification and components.

A text's word shingles are weighed by how often they occur. Each shingle is a Poisson process of its
share of the weight: its arrivals come after exponential waits and each falls on one of the
signature's components, which keeps the shingle of its earliest arrival. Shingles whose next arrival
comes after the latest component is filled stop early. Two texts agree on a component with
probability equal to their probability Jaccard similarity. Bands of components propose candidates;
candidates whose exact probability Jaccard reaches `threshold` are linked, and components of links
are the classes, named by their least doc_id.

Scale. Equal texts are one text from the first step on (by digest). Each band bucket with two texts or
more compares its members with one hub, the member that shares most buckets with others: exactly, hub by hub, as
a stream, in pieces that a task can hold, so a bucket of m texts makes m comparisons. Components of these links
tell which buckets are settled: those whose members other than the hub are all of one component. In any other
bucket every pair of members of different components is compared exactly, in blocks of bounded bytes: the members outside
the bucket's largest component with each other and with those inside it. A block's comparison looks shingles up among
those of the block (postings), and only links that join two components leave it, so what a bucket emits is less than
its members. Every pair that shares a bucket is thus settled: the one way to lose a link is that its texts
share no band, with a chance of (1 - 0.8^5)^28, 2 * 10^-5, at the threshold.
Texts in shared buckets are fetched once and travel as sorted shingle hashes. Nothing but an edge count comes to the
driver. Components are found by large-star and small-star steps over links, checkpointed each round.

Nulls: null texts and texts without a word are near nothing and each row keeps its own doc_id as its
class (null stays null). A text of fewer words than a shingle is one shingle. Very long texts are signed and compared
whole, alone in their piece. Ties: of rows with the least key the one with the least text digest is kept. Repeated rows
share their text's class. Columns of the input cannot clash (keep_one renames them while it works). Empty tables give
empty results.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import U64, WordHashes, arrow_rows, broadcast_if_small, chunks_by_length, materialize, mix64, shield, shingles_of, text_or_empty, word_hashes

_STEP = U64(0xA0761D6478BD642F)
CHARS = 2_000_000  # of text signed at once
BLOCK = 512  # texts of a block
BLOCK_BYTES = 4_000_000  # of a block's shingle hashes, but for a text that has more


@dataclass(frozen=True)
class NearSpec:
    """Shingle width, least similarity, and bands x rows components of a signature."""

    width: int = 5
    threshold: float = 0.8
    bands: int = 28
    rows: int = 5
    seed: int = 29

    @property
    def components(self) -> int:
        return self.bands * self.rows


def signatures(sets: list[tuple[np.ndarray, np.ndarray]], k: int, seed: int) -> np.ndarray:
    """(n, k) signatures of n weighted sets (hashes, weights); a row of an empty set is 0."""
    n = len(sets)
    best = np.full(n * k, np.inf)
    sig = np.zeros(n * k, U64)
    sizes = np.array([len(h) for h, _ in sets])
    owner = np.repeat(np.arange(n), sizes)
    if not len(owner):
        return sig.reshape(n, k)
    item = np.concatenate([h for h, _ in sets])
    rate = np.concatenate([w / w.sum() for _, w in sets if len(w)])
    state = mix64(item ^ U64(seed * 0x9E3779B97F4A7C15 & (2**64 - 1)))
    clock = np.zeros(len(item))
    while len(item):
        state = mix64(state + _STEP)
        # 40 bits make the wait, 24 bits the component: both from one draw of the element's own stream
        wait = -np.log(((state >> U64(24)).astype(np.float64) + 0.5) / float(1 << 40))
        clock = clock + wait / rate
        cell = owner * k + ((state & U64(0xFFFFFF)) * U64(k) >> U64(24)).astype(np.int64)
        early = clock < best[cell]
        c, t, x = cell[early], clock[early], item[early]
        np.minimum.at(best, c, t)
        won = best[c] == t
        sig[c[won]] = x[won]
        stop = best.reshape(n, k).max(axis=1)  # until every component is filled nothing stops
        go = clock < stop[owner]
        owner, item, rate, state, clock = owner[go], item[go], rate[go], state[go], clock[go]
    return mix64(sig).reshape(n, k) * (sizes > 0)[:, None].astype(U64)


def weighted_shingles(text: str | None, memo: WordHashes, width: int) -> tuple[np.ndarray, np.ndarray]:
    hashes, counts = np.unique(shingles_of(word_hashes(text, memo), width), return_counts=True)
    return hashes, counts.astype(np.float64)


def probability_jaccard(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray], least: float = 0.0) -> float:
    """Exact: the sum over shared elements d of 1 / sum of max(x'/x_d, y'/y_d) over all elements.

    It is at most what the shared elements weigh on either side; where that is below `least`, 0 is returned.
    """
    if not len(a[0]) or not len(b[0]):
        return 0.0
    common, ia, ib = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    if not len(common):
        return 0.0
    x, y = a[1] / a[1].sum(), b[1] / b[1].sum()
    xs, ys = x[ia], y[ib]
    if min(xs.sum(), ys.sum()) < least - 1e-9:
        return 0.0
    # shared elements in order of x/y: those at or above d's ratio count by x, the others by y
    order = np.argsort(xs / ys, kind="stable")
    xs, ys = xs[order], ys[order]
    ratio = xs / ys
    above = np.concatenate([np.cumsum(xs[::-1])[::-1], [0.0]])
    below = np.concatenate([[0.0], np.cumsum(ys)])
    first = np.searchsorted(ratio, ratio, side="left")
    only_x, only_y = max(0.0, 1.0 - x[ia].sum()), max(0.0, 1.0 - y[ib].sum())
    return float((1.0 / ((above[first] + only_x) / xs + (below[first] + only_y) / ys)).sum())


def _band_rows(batches: Iterator[pd.DataFrame], spec: NearSpec) -> Iterator[pd.DataFrame]:
    memo = WordHashes()
    seen: dict[bytes, int] = {}
    for batch in batches:
        batch = batch[~batch["uid"].isin(seen)].drop_duplicates("uid")
        if len(seen) > 200_000:
            seen.clear()
        seen.update(dict.fromkeys(batch["uid"], 1))
        texts = batch["text"].tolist()
        uids = batch["uid"].to_numpy()
        for start, end in chunks_by_length([max(len(t), 2 * spec.components) for t in texts], CHARS):
            sig = signatures([weighted_shingles(t, memo, spec.width) for t in texts[start:end]], spec.components, spec.seed)
            parts = sig.reshape(end - start, spec.bands, spec.rows)
            key = np.zeros(parts.shape[:2], U64)
            for r in range(spec.rows):
                key = mix64(key * U64(31) + parts[:, :, r])
            key = mix64(key + np.arange(spec.bands, dtype=U64)[None, :])
            filled = sig.any(axis=1)
            rows = np.flatnonzero(filled)
            yield pd.DataFrame({"uid": uids[start:end][rows], "keys": list(key[rows].view(np.int64))})


def _bags(batches: Iterator[pa.RecordBatch], spec: NearSpec) -> Iterator[pa.RecordBatch]:
    """Of each text its sorted distinct shingles, and how often each occurs where any occurs more than once."""
    memo = WordHashes()
    for batch in batches:
        bags, counts = [], []
        for text in batch.column("text"):
            hashes, n = weighted_shingles(text.as_py(), memo, spec.width)
            bags.append(hashes.tobytes())
            counts.append(n.astype(np.uint32).tobytes() if n.size and n.max() > 1 else b"")
        yield pa.RecordBatch.from_arrays([batch.column("uid"), pa.array(bags, pa.binary()), pa.array(counts, pa.binary())], names=["uid", "bag", "counts"])


Bag = tuple[np.ndarray, np.ndarray]


def _bag(bag: bytes, counts: bytes) -> Bag:
    hashes = np.frombuffer(bag, U64)
    return hashes, np.frombuffer(counts, np.uint32).astype(np.float64) if counts else np.ones(len(hashes))


def is_near(a: Bag, b: Bag, spec: NearSpec) -> bool:
    """Exactly, by the shared shingles' weight first: the similarity is at most what they weigh on either side."""
    if len(a[0]) > len(b[0]):
        a, b = b, a
    at = np.searchsorted(b[0], a[0])
    hit = b[0][np.minimum(at, len(b[0]) - 1)] == a[0]
    if min(a[1][hit].sum() / a[1].sum(), b[1][at[hit]].sum() / b[1].sum()) < spec.threshold - 1e-9:
        return False
    return probability_jaccard(a, b, spec.threshold) >= spec.threshold


def _hub_links(batches: Iterator[pa.RecordBatch], spec: NearSpec) -> Iterator[pa.RecordBatch]:
    """Links of hubs with their members; rows come sorted by hub and piece, the hub's own row first."""
    hub, own = None, None
    for batch in batches:
        left, right = [], []
        for name, uid, bag, counts in zip(*(batch.column(c).to_pylist() for c in ("hub", "uid", "bag", "counts")), strict=True):
            if uid == name:
                hub, own = name, _bag(bag, counts)
            elif name == hub and is_near(own, _bag(bag, counts), spec):
                left.append(name)
                right.append(uid)
        yield pa.RecordBatch.from_arrays([pa.array(left, pa.binary()), pa.array(right, pa.binary())], names=["a", "b"])


def joins(roots: list[bytes], bags: list[Bag], split: int, spec: NearSpec) -> list[tuple[int, int]]:
    """Near pairs (i, j) that join different roots, one for each join: rows below `split` with those from it on, or, where it takes in all rows, with each other."""
    label = {r: r for r in roots}
    within = split == len(bags)

    def find(x: bytes) -> bytes:
        while label[x] != x:
            label[x] = x = label[label[x]]
        return x

    found = []
    if len(bags) <= 4:
        for i in range(split):
            for j in range(i + 1 if within else split, len(bags)):
                if find(roots[i]) != find(roots[j]) and is_near(bags[i], bags[j], spec):
                    found.append((i, j))
                    label[find(roots[i])] = find(roots[j])
        return found
    sizes = np.array([len(h) for h, _ in bags])
    owner = np.repeat(np.arange(len(bags)), sizes)
    items, first = np.concatenate([h for h, _ in bags]), np.concatenate([[0], np.cumsum(sizes)])
    weight = np.concatenate([w / w.sum() for _, w in bags])
    order = np.argsort(items, kind="stable")  # of one shingle the owners rise
    owner, by_item = owner[order], weight[order]
    distinct, start, place = np.unique(items[order], return_index=True, return_inverse=True)
    end = np.append(start[1:], len(items))
    where = np.empty(len(items), np.int64)
    where[order] = place
    for i in range(split):
        mine = where[first[i] : first[i + 1]]
        low, count = start[mine], end[mine] - start[mine]
        run = np.repeat(low - np.concatenate([[0], np.cumsum(count)[:-1]]), count) + np.arange(count.sum())
        who = owner[run]
        theirs = np.bincount(who, by_item[run], len(bags))
        ours = np.bincount(who, np.repeat(weight[first[i] : first[i + 1]], count), len(bags))
        bound = np.minimum(theirs, ours)
        bound[: i + 1 if within else split] = 0.0
        likely = np.flatnonzero(bound >= spec.threshold - 1e-9)
        for j in likely[np.argsort(-bound[likely], kind="stable")].tolist():
            if find(roots[i]) != find(roots[j]) and probability_jaccard(bags[i], bags[j], spec.threshold) >= spec.threshold:
                found.append((i, j))
                label[find(roots[i])] = find(roots[j])
    return found


def _block_links(batches: Iterator[pa.RecordBatch], spec: NearSpec) -> Iterator[pa.RecordBatch]:
    """Joins of each cell (key, lo, hi); rows come sorted by cell and own block, and a cell is held at a time."""
    held: list[tuple] = []
    cell = None

    def settle() -> Iterator[pa.RecordBatch]:
        _, low, high = cell
        split = len(held) if low == high else sum(r[0] == low for r in held)
        pairs = joins([r[2] for r in held], [_bag(r[3], r[4]) for r in held], split, spec)
        if pairs:
            columns = [[held[i][1] for i, _ in pairs], [held[j][1] for _, j in pairs], [held[i][2] for i, _ in pairs], [held[j][2] for _, j in pairs]]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.binary()) for c in columns], names=["a", "b", "a_root", "b_root"])

    for batch in batches:
        for key, low, high, *row in zip(*(batch.column(c).to_pylist() for c in ("key", "lo", "hi", "own", "uid", "root", "bag", "counts")), strict=True):
            if (key, low, high) != cell:
                if len(held) > 1:
                    yield from settle()
                cell, held = (key, low, high), []
            held.append(tuple(row))
    if len(held) > 1:
        yield from settle()


def with_uid(docs: DataFrame, text: str = "text") -> DataFrame:
    """uid: a digest of the text with its words' case and spacing as they are; equal texts share it."""
    body = text_or_empty(text)
    return docs.withColumn("uid", F.unhex(F.md5(body)))


def near_links(docs: DataFrame, spec: NearSpec = NearSpec(), text: str = "text") -> tuple[DataFrame, DataFrame]:
    """(roots, joins): (uid, root) of components of verified links with hubs, and (a, b, a_root, b_root) of verified links that join them."""
    spark = docs.sparkSession
    texts = with_uid(docs.select(text_or_empty(text).alias("text"))).select("uid", "text").filter(F.col("text") != "")
    banded = texts.mapInPandas(lambda it: _band_rows(it, spec), "uid binary, keys array<bigint>")
    with arrow_rows(spark, 1000):
        signed = materialize(banded.groupBy("uid").agg(F.first("keys").alias("keys")), "near-signed")  # equal texts of other partitions
    exploded = signed.select("uid", F.explode("keys").alias("key"))
    # tables that meet their rows by bucket are written first, so that both sides of each join can be split where a bucket is large
    shared = materialize(exploded.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1"), "near-shared")
    members = materialize(exploded.join(shared, "key"), "near-members")
    central = materialize(members.groupBy("uid").agg(F.sum("n").alias("central")), "near-named")
    named, _ = broadcast_if_small(central.select("uid"), 1_000_000)  # 16 bytes a row
    once = texts.join(named, "uid", "left_semi").groupBy("uid").agg(F.first("text").alias("text"))
    with arrow_rows(spark, 256):
        bags = materialize(once.mapInArrow(lambda it: _bags(it, spec), "uid binary, bag binary, counts binary"), "near-bags")
    hubs = materialize(members.join(central, "uid").groupBy("key").agg(F.max(F.struct("central", "uid")).alias("hub")).select("key", F.col("hub.uid").alias("hub")), "near-hubs")
    spokes = materialize(members.select("key", "uid").join(hubs, "key").filter(F.col("uid") != F.col("hub")), "near-spokes")
    with arrow_rows(spark, 512):
        links = materialize(_with_hubs(spokes, bags, spec), "near-links")
        roots = materialize(components(links), "near-roots")
        joined = materialize(_in_blocks(spokes, roots, bags, spec), "near-joins")
    return roots, joined


def _with_hubs(spokes: DataFrame, bags: DataFrame, spec: NearSpec) -> DataFrame:
    """(a, b): members near their hub; a hub's members are cut into pieces and its own bag goes to each."""
    pairs = spokes.select("hub", "uid").distinct()
    pieces = pairs.groupBy("hub").agg(F.ceil(F.count("*") / BLOCK).alias("pieces"))
    own = pieces.select("hub", F.explode(F.expr("sequence(0, cast(pieces - 1 as int))")).alias("piece"), F.col("hub").alias("uid"))
    large = pieces.filter("pieces > 1")
    dealt = pairs.join(large, "hub", "left").select("hub", F.pmod(F.xxhash64("uid"), F.coalesce("pieces", F.lit(1))).cast("int").alias("piece"), "uid")
    rows = dealt.unionByName(own).join(bags, "uid").withColumn("later", F.col("uid") != F.col("hub"))
    return rows.repartition("hub", "piece").sortWithinPartitions("hub", "piece", "later").mapInArrow(lambda it: _hub_links(it, spec), "a binary, b binary")


def _in_blocks(spokes: DataFrame, roots: DataFrame, bags: DataFrame, spec: NearSpec) -> DataFrame:
    """(a, b, a_root, b_root): links between components inside buckets that hold more than one besides their hub."""
    rooted = spokes.select("key", "uid").join(roots, "uid", "left").withColumn("root", F.coalesce("root", "uid"))
    rooted = rooted.join(bags.select("uid", F.octet_length("bag").alias("bytes")), "uid")
    groups = rooted.groupBy("key", "root").agg(F.count("*").alias("n"), F.sum("bytes").alias("bytes"))
    buckets = groups.groupBy("key").agg(F.max(F.struct("n", "bytes", "root")).alias("major"), F.sum("n").alias("n"), F.sum("bytes").alias("bytes")).filter(F.col("n") > F.col("major.n"))

    def blocks(n, size):
        return F.greatest(F.ceil(n / BLOCK), F.ceil(size / BLOCK_BYTES)).cast("int")

    plan = materialize(buckets.select("key", F.col("major.root").alias("major"), blocks(F.col("n") - F.col("major.n"), F.col("bytes") - F.col("major.bytes")).alias("minor_blocks"), blocks(F.col("major.n"), F.col("major.bytes")).alias("major_blocks")), "near-open")
    met = rooted.join(plan, "key")
    inside = F.col("root") == F.col("major")
    # blocks of the minor components come first; members of the largest one meet those only
    own = F.when(inside, F.col("minor_blocks") + F.pmod(F.xxhash64("uid"), F.col("major_blocks"))).otherwise(F.pmod(F.xxhash64("uid"), F.col("minor_blocks"))).cast("int")
    last = F.when(inside, F.col("minor_blocks")).otherwise(F.col("minor_blocks") + F.col("major_blocks")) - 1
    cells = met.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), last)))
    cells = cells.select("key", F.least("own", "other").alias("lo"), F.greatest("own", "other").alias("hi"), "own", "uid", "root").join(bags, "uid")
    sorted_cells = cells.repartition("key", "lo", "hi").sortWithinPartitions("key", "lo", "hi", "own")
    return sorted_cells.mapInArrow(lambda it: _block_links(it, spec), "a binary, b binary, a_root binary, b_root binary")


def components(links: DataFrame, few: int = 100_000) -> DataFrame:
    """(uid, root): the least uid of each linked uid's component, by large-star and small-star steps.

    Each node's least neighbour meets its edges by broadcast where there are at most `few` edges (counted), else from a checkpoint,
    so that both sides of the join can be split where a node has many edges.
    """
    edges = links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u <> v").distinct().checkpoint()
    n, before = edges.count(), None

    def meet(rows: DataFrame, lows: DataFrame) -> DataFrame:
        return rows.join(F.broadcast(lows) if n <= few else lows.checkpoint(), "u")  # at most two rows for each of n edges

    while n:
        both = edges.select("u", "v").union(edges.select(F.col("v"), F.col("u")))
        lows = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("m", "u"))
        large = meet(both, lows).filter(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = meet(large, low).select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").union(low.select("u", F.col("m").alias("v"))).distinct()
        edges = small.checkpoint()
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.bit_xor(F.xxhash64("v", "u"))).first()
        if now == before:  # the same edges twice: stars
            break
        before, n = now, now[0]
    return edges.select(F.col("u").alias("uid"), F.col("v").alias("root"))


def near_roots(docs: DataFrame, spec: NearSpec = NearSpec(), text: str = "text") -> DataFrame:
    """(uid, root) of every text that is linked to one with a lesser uid; root is the least of its component."""
    roots, joined = near_links(docs, spec, text)
    merged = materialize(components(joined.select(F.col("a_root").alias("a"), F.col("b_root").alias("b"))), "near-merged")
    moved = roots.join(merged.select(F.col("uid").alias("root"), F.col("root").alias("final")), "root", "left").select("uid", F.coalesce("final", "root").alias("root"))
    return materialize(moved.unionByName(merged), "near-final")


def near_classes(docs: DataFrame, spec: NearSpec = NearSpec(), *, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, uid, root, bare, class_id, class_rows): every row with its class: root tells classes apart, class_id is the least doc_id.

    Classes whose rows have null keys only, or share their least key, have one class_id but different roots.
    """
    roots = near_roots(docs, spec, text)
    rows = with_uid(docs.select(F.col(key).alias(key), F.col(text).alias("text"))).withColumn("bare", ~text_or_empty().rlike(r"(?U)\w")).drop("text")
    joined = rows.join(roots, "uid", "left").withColumn("root", F.coalesce("root", "uid"))
    # written first, so that a class with many rows can be split where it meets its name
    names = materialize(joined.filter("not bare").groupBy("root").agg(F.min(key).alias("class_id"), F.count("*").alias("class_rows")), "near-classes")
    named = joined.join(names, "root", "left")
    return named.select(key, "uid", "root", "bare", F.when(F.col("bare"), F.col(key)).otherwise(F.col("class_id")).alias("class_id"), F.when(F.col("bare"), F.lit(1)).otherwise(F.col("class_rows")).cast("long").alias("class_rows"))


def keep_one(docs: DataFrame, spec: NearSpec = NearSpec(), *, key: str = "doc_id", text: str = "text") -> DataFrame:
    """docs with one row of each class: that of the least key, ties by the text's digest; texts without words all stay."""
    inner, names, restore = shield(docs)
    key, text = names[key], names[text]
    classes = near_classes(inner, spec, key=key, text=text)
    marked = classes.filter("not bare").groupBy("root").agg(F.min(F.struct(F.col(key).isNull().alias("none"), F.col(key).alias("k"), "uid")).alias("first"))
    keep = materialize(marked.select(_named(F.col("first.k")).alias("_k"), F.col("first.uid").alias("uid")), "near-keep")
    rows = with_uid(inner, text).withColumns({"_bare": ~text_or_empty(text).rlike(r"(?U)\w"), "_k": _named(F.col(key))})
    kept = rows.filter("not _bare").join(keep, ["_k", "uid"], "left_semi").dropDuplicates(["_k", "uid"])
    return restore(kept).unionByName(restore(rows.filter("_bare")))


def _named(key):
    """A key that equals itself where it is null."""
    return F.coalesce(F.concat(F.lit("1"), key.cast("string")), F.lit("0"))


def op4_query(spark, sf_dir: str) -> DataFrame:
    """The near-duplicate class of every document; class_key tells classes of one class_id apart (null or repeated doc_ids)."""
    classes = near_classes(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return classes.select("doc_id", "class_id", "class_rows", F.hex("root").alias("class_key"))
