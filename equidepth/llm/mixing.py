"""Mixing sources to target weights, in DataFrame operations only.

The words of each source, its documents in digest order, are packed end to end into blocks of a
fixed length. A source gets as many slots of the mix as its target needs; each slot draws one of
the output shards, so the counts of a source over the shards are a multinomial draw (and a shard's
counts over the sources are one too, with the sources' totals held at their targets). Slot j of a
source is block perm(j mod N) of its N blocks, with another permutation each time the source is gone
through, so no block is taken more often than ceil(slots / N). A permutation is a swap-or-not shuffle: in each round an
index and its partner (a round's key less the index, modulo N) change places where a digest of the greater of both says so.
Joining slots and blocks by (source, block index) gives what the mix takes of each document and which shards hold it.

Targets: sources in code point order, null last, take the given weights in turn and share
`multiple` times all sizes; a target stops at `most` times its source's size and the excess is
shared again by weight. That fixed point is min(most * size, level * weight), and the level comes
from one pass over the sources in order of size / weight.

Scale: a source is cut into lanes by a digest of id and text before any window, the more lanes the more rows there are, so a
source or an id with a third of all rows is spread; windows over everything run over one row for each source and,
beyond 200,000 sources, give way to slices. Slots of a source are made in runs of 65,536 dealt over the cluster.

Nulls: a null text has size 0; null sources form one source, the last; null ids are packed by their texts' digests. Documents of size
0 keep their row and take nothing. Very long texts span many blocks. Ties in the packing go by digest, id and size; rows alike in all
three are interchangeable. Repeated rows each hold their own place in the packing. mix() reads three columns, mixed_documents
renames the input's while it works, so none can clash. Empty tables give empty results. Permutations are exact below 2**59
blocks a source.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.extsort import PID, model_sort
from .shared import materialize, shield, text_or_empty

WORD_RUN = r"[^\x20\x09-\x0D]+"
RUN = 65_536
ROUNDS = 6  # of a block permutation
LANES = (256, 65_536, 50_000)  # least, most, and the rows that call for one more doubling


def _digest_number(text: Column) -> Column:
    """The first 32 bits of an MD5 digest as a long."""
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def _digest_long(text: Column) -> Column:
    """The first 60 bits of an MD5 digest as a long."""
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def lanes_for(rows: int) -> int:
    least, most, each = LANES
    return max(least, min(most, 1 << (rows // each).bit_length()))


def _source_key(col: str) -> Column:
    """Sorts like the source by code point, null last."""
    return F.coalesce(F.concat(F.lit("1"), F.col(col)), F.lit("2"))


def source_targets(sized: DataFrame, weights=(5, 2, 1), multiple: float = 1.5, most: float = 2.0, one_task: int = 200_000) -> DataFrame:
    """(src, source_size, target) of each source of a frame with columns src and size.

    Up to `one_task` sources (counted) their order and running sums are windows over one row for each; more are sliced and summed
    slice by slice.
    """
    totals = materialize(sized.groupBy("src").agg(F.sum("size").alias("source_size")), "mix-sources")
    few = totals.count() <= one_task
    placed = totals.withColumn("rn", F.row_number().over(Window.orderBy("src"))) if few else model_sort(totals, ["src"]).with_rn()
    turn = F.pmod(F.col("rn").cast("int") - 1, F.lit(len(weights)))
    weighed = placed.withColumn("w", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), turn + 1)).drop("rn")
    weighed = weighed.withColumns({"bound": F.lit(most) * F.col("source_size"), "ratio": F.lit(most) * F.col("source_size") / F.col("w")})
    weighed = weighed if few else materialize(weighed, "mix-weighed")
    all_size, all_w = weighed.agg(F.coalesce(F.sum("source_size"), F.lit(0)), F.sum("w")).first()
    if few:
        before = Window.orderBy("ratio", "src").rowsBetween(Window.unboundedPreceding, -1)
        start = rows = None
    else:
        slices = model_sort(weighed, ["ratio", "src"])
        before = slices.window().rowsBetween(Window.unboundedPreceding, -1)
        sums = {r[0]: (r[1], r[2]) for r in slices.sliced.groupBy(PID).agg(F.sum("bound"), F.sum("w")).collect()}  # a row for each slice
        held, starts = (0.0, 0.0), []
        for p in range(slices.f):
            starts.append((p, *held))
            held = tuple(x + y for x, y in zip(held, sums.get(p, (0.0, 0.0)), strict=True))
        start = F.broadcast(totals.sparkSession.createDataFrame(starts, f"{PID} int, _b double, _w double"))
        rows = slices.exchanged
    b, w = (F.coalesce(F.sum(c).over(before), F.lit(0.0)) for c in ("bound", "w"))
    tried = weighed.withColumns({"_sb": b, "_sw": w}) if few else rows.withColumns({"_sb": b, "_sw": w}).join(start, PID).withColumns({"_sb": F.col("_sb") + F.col("_b"), "_sw": F.col("_sw") + F.col("_w")})
    tried = tried.withColumn("level", (F.lit(multiple) * F.lit(all_size) - F.col("_sb")) / (F.lit(all_w) - F.col("_sw")))
    first = tried.filter(F.col("level") <= F.col("ratio")).agg(F.min(F.struct("ratio", "src", "level"))["level"]).first()[0]
    return weighed.withColumn("target", F.least("bound", F.col("w") * F.lit(first or 0.0))).select("src", "source_size", "target")


def pack(sized: DataFrame, lanes: int) -> DataFrame:
    """sized with `at`, the first word's position in its source; documents in order of lane and digest."""
    laned = sized.withColumn("lane", F.pmod(F.conv(F.substring("digest", 1, 4), 16, 10).cast("int"), F.lit(lanes)))
    lane_sizes = laned.groupBy("src", "lane").agg(F.sum("size").alias("lane_size"))
    over = Window.partitionBy("src").orderBy("lane").rowsBetween(Window.unboundedPreceding, -1)
    bases = lane_sizes.withColumn("base", F.coalesce(F.sum("lane_size").over(over), F.lit(0))).drop("lane_size")
    inside = Window.partitionBy("src", "lane").orderBy("digest", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    placed = laned.withColumn("inside", F.coalesce(F.sum("size").over(inside), F.lit(0)))
    return placed.join(bases, ["src", "lane"]).withColumn("at", F.col("base") + F.col("inside")).drop("lane", "digest", "base", "inside")


def draw_slots(plan: DataFrame, shard_slots: int) -> DataFrame:
    """(src, shard, j, block): every slot of the mix. plan: src, blocks, slots."""
    total = plan.agg(F.coalesce(F.sum("slots"), F.lit(0)).alias("all_slots"))
    dealt = plan.filter("slots > 0").crossJoin(F.broadcast(total))  # one row
    dealt = dealt.withColumn("shards", F.greatest(F.lit(1), F.ceil(F.col("all_slots") / shard_slots)))
    runs = dealt.select("src", "slots", "shards", F.explode(F.sequence(F.lit(0).cast("long"), F.expr(f"(slots - 1) div {RUN}"))).alias("run"))
    parts = plan.sparkSession.conf.get("spark.sql.shuffle.partitions")
    runs = runs.repartition(int(parts), "src", "run")
    last = F.least(F.col("slots"), (F.col("run") + 1) * RUN) - 1
    drawn = runs.select("src", "shards", F.explode(F.sequence(F.col("run") * RUN, last)).alias("slot"))
    drawn = drawn.withColumn("shard", F.pmod(_digest_number(F.concat_ws("/", F.lit("shard"), "src", F.col("slot").cast("string"))), F.col("shards")))
    counts = drawn.groupBy("src", "shard").agg(F.count("*").alias("n"))
    before = Window.partitionBy("src").orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.withColumn("first", F.coalesce(F.sum("n").over(before), F.lit(0)))
    counts = counts.repartition(int(parts), "src", "shard")  # each row becomes up to shard_slots
    slots = counts.select("src", "shard", F.explode(F.sequence(F.col("first"), F.col("first") + F.col("n") - 1)).alias("j"))
    return slots.join(plan.select("src", "blocks"), "src").withColumn("block", block_of("j", "blocks", "src")).select("src", "shard", "j", "block")


def block_of(slot: str, blocks: str, src: str) -> Column:
    """The block that a slot takes: a permutation of the source's blocks, another one in each turn through them."""
    n = F.col(blocks)
    name = F.concat_ws("/", F.col(src), F.expr(f"cast({slot} div {blocks} as string)"))

    def swap(x: Column, r: Column) -> Column:
        key = _digest_long(F.concat_ws("/", F.lit("key"), name, r.cast("string"))) % n
        other = (key - x + n) % n
        drawn = F.conv(F.substring(F.md5(F.concat_ws("/", F.lit("swap"), name, r.cast("string"), F.greatest(x, other).cast("string"))), 1, 1), 16, 10).cast("int")
        return F.when(drawn < 8, other).otherwise(x)

    return F.aggregate(F.sequence(F.lit(1), F.lit(ROUNDS)), F.col(slot) % n, swap)


def mix(
    docs: DataFrame, *, source: str = "source", text: str = "text", weights=(5, 2, 1), multiple: float = 1.5, most: float = 2.0,
    block_words: int = 128, shard_slots: int = 4096, lanes: int | None = None,
) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(documents, slots, pieces) of the mix.

    documents: doc_id, source, size, source_size, target, taken, first_shard, last_shard (of the output shards that hold any of it;
    null where none), at. slots: src, shard, j, block. pieces: the parts of blocks (src, block, doc_id, at, words) that slots take.
    """
    body = text_or_empty(text)
    digest = F.md5(F.concat_ws("/", F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.md5(body)))
    sized = materialize(docs.select(F.col("doc_id"), F.col(source).alias("source"), _source_key(source).alias("src"), F.regexp_count(body, F.lit(WORD_RUN)).cast("long").alias("size"), digest.alias("digest")), "mix-sizes")
    targets = source_targets(sized, weights, multiple, most)
    blocks = F.expr(f"(source_size + {block_words - 1}) div {block_words}")
    plan = targets.withColumn("blocks", blocks).withColumn("slots", F.when(F.col("source_size") > 0, F.least((F.lit(most) * F.col("blocks")).cast("long"), F.round(F.col("target") * F.col("blocks") / F.col("source_size")).cast("long"))).otherwise(F.lit(0).cast("long")))
    plan = materialize(plan, "mix-plan")
    placed = materialize(pack(sized, lanes or lanes_for(sized.count())), "mix-packed")
    pieces = placed.filter("size > 0").select("src", "doc_id", "at", "size", F.explode(F.expr(f"sequence(at div {block_words}, (at + size - 1) div {block_words})")).alias("block"))
    pieces = pieces.withColumn("words", F.least(F.col("at") + F.col("size"), (F.col("block") + 1) * block_words) - F.greatest(F.col("at"), F.col("block") * block_words))
    slots = draw_slots(plan, shard_slots)
    taken = pieces.join(slots, ["src", "block"]).groupBy("src", "at").agg(F.sum("words").alias("taken"), F.min("shard").alias("first_shard"), F.max("shard").alias("last_shard"))
    rows = placed.join(taken, (placed["src"] == taken["src"]) & (placed["at"] == taken["at"]) & (placed["size"] > 0), "left").select(placed["*"], "taken", "first_shard", "last_shard")
    known = plan.select(F.col("src").alias("_s"), "source_size", "target")
    rows = rows.join(known, rows["src"] == known["_s"]).select("doc_id", "source", "src", "at", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"), "first_shard", "last_shard")
    return rows, slots, pieces


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """The rows of docs as often as the mix takes their words: taken / size, rounded by the document's digest.

    Documents without a word are in no mix and do not come back.
    """
    inner, names, restore = shield(docs)
    source, text, key = names[options.pop("source", "source")], names[options.pop("text", "text")], names["doc_id"]
    rows, _, _ = mix(inner.withColumn("doc_id", F.col(key)), source=source, text=text, **options)
    part = _digest_number(F.concat(F.lit("round/"), F.coalesce(F.col("doc_id").cast("string"), F.lit("")))) / F.lit(float(1 << 32))
    copies = rows.filter("taken > 0").groupBy("doc_id", "src", "size").agg(F.sum("taken").alias("taken"), F.count("*").alias("rows"))
    copies = copies.withColumn("copies", F.floor(F.col("taken") / (F.col("size") * F.col("rows")) + part).cast("int")).filter("copies > 0")
    copies = copies.select(F.col("doc_id").alias("_id"), F.col("src").alias("_src"), F.col("size").alias("_size"), "copies")
    body = inner.withColumns({"_key": _source_key(source), "_words": F.regexp_count(text_or_empty(text), F.lit(WORD_RUN)).cast("long")})
    joined = body.join(copies, F.col(key).eqNullSafe(F.col("_id")) & (F.col("_key") == F.col("_src")) & (F.col("_words") == F.col("_size")))
    return restore(joined.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("copies")))))


def op5_query(spark, sf_dir: str) -> DataFrame:
    """What the mix takes of every document, and the first and last of the output shards that hold it."""
    rows, _, _ = mix(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return rows.select("doc_id", "size", "source_size", "target", "taken", "first_shard", "last_shard")


OP5_SQL = f"""
WITH sized AS (
  SELECT doc_id, coalesce('1' || source, '2') AS src,
         len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::BIGINT AS size,
         md5(coalesce(doc_id::VARCHAR, '') || '/' || md5(coalesce(text, ''))) AS digest FROM documents),
totals AS (SELECT src, sum(size)::BIGINT AS source_size FROM sized GROUP BY src),
weighed AS (SELECT *, [5.0::DOUBLE, 2.0::DOUBLE, 1.0::DOUBLE][1 + (row_number() OVER (ORDER BY src) - 1) % 3] AS w FROM totals),
tried AS (
  SELECT *, 2.0::DOUBLE * source_size AS bound, 2.0::DOUBLE * source_size / w AS ratio FROM weighed),
levels AS (
  SELECT *, (1.5::DOUBLE * sum(source_size) OVER () - coalesce(sum(bound) OVER b, 0.0::DOUBLE))
            / (sum(w) OVER () - coalesce(sum(w) OVER b, 0.0::DOUBLE)) AS level
  FROM tried WINDOW b AS (ORDER BY ratio, src ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
chosen AS (SELECT level FROM levels WHERE level <= ratio ORDER BY ratio, src LIMIT 1),
targets AS (SELECT src, source_size, least(bound, w * coalesce((SELECT level FROM chosen), 0.0::DOUBLE)) AS target FROM levels),
plan AS (
  SELECT *, CASE WHEN source_size > 0 THEN least(2 * blocks, round(target * blocks / source_size)::BIGINT) ELSE 0 END AS slots
  FROM (SELECT *, (source_size + 127) // 128 AS blocks FROM targets)),
lanes AS (SELECT greatest({LANES[0]}, least({LANES[1]}, 1::BIGINT << length(bin(count(*) // {LANES[2]}))))::BIGINT AS n FROM sized),
packed AS (
  SELECT *, coalesce(sum(size) OVER (PARTITION BY src ORDER BY ('0x' || digest[1:4])::BIGINT % (SELECT n FROM lanes), digest, doc_id, size
                                     ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS "at" FROM sized),
pieces AS (
  SELECT src, "at", least("at" + size, (block + 1) * 128) - greatest("at", block * 128) AS words, block
  FROM (SELECT src, "at", size, unnest(range("at" // 128, ("at" + size - 1) // 128 + 1)) AS block FROM packed WHERE size > 0)),
shards AS (SELECT greatest(1, ceil(sum(slots) / 4096.0))::BIGINT AS n FROM plan),
drawn AS (
  SELECT src, blocks, ('0x' || md5('shard/' || src || '/' || slot::VARCHAR)[1:8])::BIGINT % (SELECT n FROM shards) AS shard
  FROM (SELECT src, blocks, unnest(range(slots)) AS slot FROM plan WHERE slots > 0)),
slots AS (
  SELECT *, src || '/' || (j // blocks)::VARCHAR AS name
  FROM (SELECT src, blocks, shard, row_number() OVER (PARTITION BY src ORDER BY shard) - 1 AS j FROM drawn)),
chosen_blocks AS (
  SELECT src, shard, list_reduce(list_prepend(j % blocks, range(1, {ROUNDS + 1})), lambda x, r:
    CASE WHEN ('0x' || md5('swap/' || name || '/' || r::VARCHAR || '/' || greatest(x, (('0x' || md5('key/' || name || '/' || r::VARCHAR)[1:15])::BIGINT % blocks - x + blocks) % blocks)::VARCHAR)[1:1])::BIGINT < 8
         THEN (('0x' || md5('key/' || name || '/' || r::VARCHAR)[1:15])::BIGINT % blocks - x + blocks) % blocks ELSE x END) AS block FROM slots),
got AS (SELECT p.src, p."at", sum(p.words)::BIGINT AS taken, min(t.shard)::BIGINT AS first_shard, max(t.shard)::BIGINT AS last_shard
        FROM pieces p JOIN chosen_blocks t ON p.src = t.src AND p.block = t.block GROUP BY ALL)
SELECT k.doc_id, k.size, n.source_size, n.target, coalesce(g.taken, 0)::BIGINT AS taken, g.first_shard, g.last_shard
FROM packed k JOIN plan n ON k.src = n.src LEFT JOIN got g ON k.src = g.src AND k."at" = g."at" AND k.size > 0
"""
