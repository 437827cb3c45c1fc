"""Document fingerprints: bottom-k sketches of shingle hashes, in DataFrame operations only.

A sketch is the sorted array of the k least distinct 64-bit hashes of a text's word shingles (lower
case, words between white space, `width` words a shingle; a shorter text is one shingle, a text
without words has none). Sketches of parts merge into the sketch of the whole, and two sketches
estimate resemblance, containment and the number of distinct shingles.

Successors by doc_id come from ranges of ids, not from one window over everything; an id that fills a range by itself (nulls too)
is spread over parts of that range by a hash of its texts. Up to 65,536 ranges are made, so beyond 131 million rows a range
holds more than 2,000 of them and its sort may spill.

Nulls: a null text is an empty one; null ids come first. Two empty sketches resemble each other fully, an empty and a filled
one not at all. Very long texts are sketched in their row; nothing is cut. Ties: rows of one id go on by a hash of their texts; repeated
rows follow each other and are like each other. Columns other than doc_id and text are not read, so none can clash. Empty
tables give empty results.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

EMPTY = "array<bigint>"


def sketch(text: Column, k: int = 128, width: int = 5) -> Column:
    """array<bigint>: the bottom-k sketch of one text."""
    words = F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"\s+"), lambda x: x != "")
    hashed = F.transform(words, lambda x: F.xxhash64(x))

    def least(w: Column) -> Column:
        starts = F.sequence(F.lit(0), F.greatest(F.size(w) - width, F.lit(0)))
        runs = F.transform(starts, lambda i: F.xxhash64(*[F.get(w, i + j) for j in range(width)]))
        return F.when(F.size(w) == 0, F.array().cast(EMPTY)).otherwise(F.slice(F.sort_array(F.array_distinct(runs)), 1, k))

    return F.get(F.transform(F.array(hashed), least), F.lit(0))  # the inner array is bound once


def merge(a: Column, b: Column, k: int = 128) -> Column:
    """The sketch of two parts together."""
    return F.slice(F.sort_array(F.array_union(a, b)), 1, k)


def merge_agg(df: DataFrame, keys: list[str], col: str, k: int = 128) -> DataFrame:
    """Sketches merged by keys: hashes are made distinct before the shuffle, ranks taken after it."""
    values = df.select(*keys, F.explode(col).alias("_h")).distinct()
    w = Window.partitionBy(*keys).orderBy("_h")
    return values.withColumn("_n", F.row_number().over(w)).filter(F.col("_n") <= k).groupBy(*keys).agg(F.sort_array(F.collect_list("_h")).alias(col))


def resemblance(a: Column, b: Column, k: int = 128) -> Column:
    """Estimated Jaccard similarity of the shingle sets, 0 to 1."""
    both = F.slice(F.sort_array(F.array_union(a, b)), 1, k)
    shared = F.size(F.array_intersect(F.array_intersect(a, b), both))
    return F.when((F.size(a) == 0) & (F.size(b) == 0), F.lit(1.0)).otherwise(shared / F.size(both))


def distinct_count(a: Column, k: int = 128) -> Column:
    """Estimated number of distinct shingles; exact below k."""
    top = (F.element_at(a, -1).cast("double") + F.lit(float(2**63))) / F.lit(float(2**64))
    return F.when(F.size(a) < k, F.size(a).cast("double")).otherwise((k - 1) / top)


def containment(a: Column, b: Column, k: int = 128) -> Column:
    """Estimated share of a's shingles that b holds."""
    r, n, m = resemblance(a, b, k), distinct_count(a, k), distinct_count(b, k)
    return F.when(F.size(a) == 0, F.lit(1.0)).otherwise(F.least(F.lit(1.0), r * (n + m) / (F.lit(1.0) + r) / n))


def to_text(a: Column) -> Column:
    """Sixteen hex digits a hash."""
    return F.array_join(F.transform(a, lambda x: F.lpad(F.hex(x), 16, "0")), "")


def _longs(values: list) -> Column:
    """An array literal."""
    return F.array(*[F.lit(int(b)).cast("long") for b in values]) if len(values) < 200 else F.split(F.lit(",".join(str(int(b)) for b in values)), ",").cast(EMPTY)


def _bucket(col: str, bounds: list) -> Column:
    """Number of bounds at or below col, by binary search; nulls 0."""
    if not bounds:
        return F.lit(0)
    array = _longs(bounds)
    steps = F.array(*[F.lit(1 << s) for s in reversed(range(len(bounds).bit_length()))])
    return F.aggregate(steps, F.lit(0), lambda at, h: at + F.when(F.coalesce(F.get(array, at + h - 1) <= F.col(col), F.lit(False)), h).otherwise(0))


def with_next(df: DataFrame, *, text: str = "text", rows_per_bucket: int = 2000, max_buckets: int = 65_536) -> tuple[DataFrame, Window]:
    """(rows with _text, _next and _ghost, the window they are ordered by): each row's successor by doc_id.

    Rows are dealt into ranges of doc_id, and rows of the id that a range begins with (null in the first range) into parts of it by the
    first bits of their texts' hashes; the first row of a range or part is also dealt, as a ghost, to the one
    before (that of the last one is the first of all). Equal ids go on by a hash of the text. Ghosts
    must be dropped when the window has been used.
    """
    spark = df.sparkSession
    slim = df.select("doc_id", F.coalesce(F.col(text), F.lit("")).alias("_text"))
    rows = df.count()
    buckets = max(1, min(max_buckets, -(-rows // rows_per_bucket)))
    cuts = [i / buckets for i in range(1, buckets)]
    bounds = sorted(set(df.agg(F.percentile_approx(F.col("doc_id").cast("long"), cuts, max(10_000, 10 * buckets))).first()[0] or [])) if cuts else []
    lead = F.get(_longs(bounds), F.col("_bucket") - 1) if bounds else F.lit(None).cast("long")
    sub = F.when(F.col("doc_id").cast("long").eqNullSafe(lead), F.shiftright("_tie", 59).cast("int") + 16).otherwise(F.lit(32))  # 32 parts, then the rest
    laid = slim.withColumns({"_tie": F.xxhash64("_text"), "_bucket": _bucket("doc_id", bounds)}).withColumn("_sub", sub)
    key = F.struct(F.col("doc_id").isNotNull().alias("full"), "doc_id", "_tie")
    firsts = sorted((r[0], r[1], r[2]) for r in laid.groupBy("_bucket", "_sub").agg(F.min(key).alias("first")).collect())  # a few rows for each range
    order = Window.partitionBy("_bucket", "_sub").orderBy("_ghost", F.col("doc_id").asc_nulls_first(), "_tie")
    if not firsts:
        return laid.withColumns({"_ghost": F.lit(False), "_next": F.lit("")}), order
    befores = [(b, s, f["doc_id"], f["_tie"], *firsts[i - 1][:2]) for i, (b, s, f) in enumerate(firsts)]
    table = F.broadcast(spark.createDataFrame(befores, "_b int, _s int, _id long, _t long, _before int, _before_sub int"))  # a few rows for each range
    met = (F.col("_bucket") == F.col("_b")) & (F.col("_sub") == F.col("_s")) & F.col("doc_id").cast("long").eqNullSafe(F.col("_id")) & (F.col("_tie") == F.col("_t"))
    marked = laid.join(table, met, "left")
    here = F.struct(F.col("_bucket").alias("b"), F.col("_sub").alias("s"), F.lit(False).alias("g"))
    there = F.struct(F.col("_before").alias("b"), F.col("_before_sub").alias("s"), F.lit(True).alias("g"))
    dealt = marked.select("doc_id", "_text", "_tie", F.explode(F.when(F.col("_before").isNotNull(), F.array(here, there)).otherwise(F.array(here))).alias("z"))
    dealt = dealt.select("doc_id", "_text", "_tie", F.col("z.b").alias("_bucket"), F.col("z.s").alias("_sub"), F.col("z.g").alias("_ghost"))
    return dealt.withColumn("_next", F.coalesce(F.lead("_text").over(order), F.lit(""))), order


def fingerprint_edits(docs: DataFrame, *, k: int = 128, width: int = 5, text: str = "text") -> DataFrame:
    """The fingerprint of each text, of its edited text, and their likeness to each other and to the next text's."""
    rows, order = with_next(docs, text=text)
    n = F.char_length("_text")
    quarter = F.floor(n / 4).cast("int")
    edited = F.concat(F.substring(F.col("_text"), F.lit(1), n - quarter), F.substring(F.col("_next"), F.lit(1), quarter))
    made = rows.withColumn("_edited", edited).select(
        "doc_id", "_tie", "_bucket", "_sub", "_ghost", n.cast("long").alias("n_chars"), F.sha2(F.encode("_edited", "UTF-8"), 256).alias("edited_sha256"),
        sketch(F.col("_text"), k, width).alias("_own"), sketch(F.col("_edited"), k, width).alias("_changed"),
    )
    led = made.withColumn("_after", F.lead("_own").over(order)).filter(~F.col("_ghost"))
    return led.select(
        "doc_id", "n_chars", "edited_sha256", to_text(F.col("_own")).alias("fingerprint"), to_text(F.col("_changed")).alias("edited_fingerprint"),
        resemblance(F.col("_own"), F.col("_changed"), k).alias("near_edited"), resemblance(F.col("_own"), F.col("_after"), k).alias("near_next"),
    )


def op9_query(spark, sf_dir: str) -> DataFrame:
    """Fingerprints of every document and its edited text."""
    return fingerprint_edits(spark.read.parquet(f"{sf_dir}/documents.parquet"))
