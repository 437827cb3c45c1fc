"""More queries: indexes and text, windows, scalar functions, streams, experiments."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .functions import scalar, udf
from .measures import metrics, workloads
from .operators import aggregates as A
from .operators import index as I
from .operators import windows as W
from .plans.extsort import model_sort
from .plans.mergesort import make_runs
from .plans.sampling import SampleSpec
from .queries import EVENTS, ORACLE_SQL, QUERIES, model_sql, query, table, table_size  # noqa: F401  (one table of queries)
from .session import scratch
from .sources import io
from .sources.datagen import SkewSpec, generate_records
from .streaming import fragments as ST

# ---- index, shards, text -----------------------------------------------------------------------------


def _by_orderkey(spark, d):
    return model_sort(table(spark, d, "orders").select("o_orderkey", "o_totalprice", "o_orderdate"), ["o_orderkey"], f=16)


_LOOK = "SELECT o_orderkey, o_totalprice, o_orderdate FROM orders"
query("lookup_keys", f"{_LOOK} WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity = 50 AND l_discount = 0.1)")(
    lambda s, d: I.lookup(_by_orderkey(s, d), table(s, d, "lineitem").filter("l_quantity = 50 AND l_discount = 0.1"), "l_orderkey")
)
query("range_scan", f"{_LOOK} WHERE o_orderkey BETWEEN 100 AND 900")(lambda s, d: I.range_scan(_by_orderkey(s, d), 100, 900))


def _priced(spark, d):
    """orders in slices of a model of every tenth order's price."""
    df = table(spark, d, "orders").select("o_orderkey", "o_totalprice", "o_orderdate")
    return model_sort(df, ["o_totalprice"], f=16, sample=SampleSpec(method="systematic", pk="o_orderkey", every=10))


query("build_index_sparse", f"{model_sql('orders', 'o_totalprice', 'o_orderkey % 10 = 0', 16)} SELECT key, pid, pos FROM (SELECT code AS key, pid, row_number() OVER (PARTITION BY pid ORDER BY code) - 1 AS pos FROM predicted) WHERE pos % 50 = 0")(
    lambda s, d: I.build_index(_priced(s, d), "o_totalprice", 50)
)
query("zone_map", "SELECT event_type AS pid, count(*) AS rows, min(value) AS min_value, max(value) AS max_value FROM events GROUP BY event_type")(lambda s, d: I.zone_map(table(s, d, "events"), ["value"], "event_type"))


@query("learned_locate", "SELECT count(*) AS n, count(*) AS inside FROM events")
def _learned(spark, d):
    """Every stored key's place lies in its predicted span."""
    sf = model_sort(table(spark, d, "events").select("event_id", "value"), ["value", "event_id"], f=16)
    index = I.learned_index(sf)
    placed = I.learned_locate(index, sf.with_rn(), "value")
    return placed.agg(F.count("*").alias("n"), F.sum(((F.col("rn") - 1).between(F.col("low"), F.col("high"))).cast("long")).alias("inside"))


@query("shard_ranges", "SELECT count(*) AS rows, 0::BIGINT AS overlaps FROM customer")
def _shard(spark, d):
    from .measures.validate import invariant_violations

    sharded = I.shard(table(spark, d, "customer"), "c_acctbal", 8)
    return sharded.agg(F.count("*").alias("rows")).crossJoin(invariant_violations(sharded, F.col("c_acctbal"), "shard").withColumnRenamed("violations", "overlaps"))


@query("cluster_by_two", "SELECT count(*) AS rows, count(DISTINCT c_custkey) AS keys, true AS near FROM customer")
def _clustered(spark, d):
    """All rows stay, and a partition spans far less of both keys than the table does: cells follow a curve."""
    out = I.cluster_by(table(spark, d, "customer"), ["c_acctbal", "c_nationkey"], f=8).withColumn("part", F.spark_partition_id())
    area = (F.max("c_acctbal") - F.min("c_acctbal")) * (F.max("c_nationkey") - F.min("c_nationkey"))
    parts = out.groupBy("part").agg(area.alias("area"))
    whole = out.agg(F.count("*").alias("rows"), F.countDistinct("c_custkey").alias("keys"), area.alias("whole"))
    return parts.agg(F.avg("area").alias("mean")).crossJoin(whole).select("rows", "keys", (F.col("mean") < F.col("whole") / 2).alias("near"))  # one row each


_TOK = r"(SELECT doc_id, unnest(list_filter(regexp_split_to_array(lower(text), '[ \t\n\x0B\f\r]+'), lambda x: x <> '')) AS term FROM documents)"
query("inverted_index", f"SELECT term, count(DISTINCT doc_id) AS docs, count(*) AS hits FROM {_TOK} GROUP BY term")(
    lambda s, d: I.inverted_index(table(s, d, "documents")).select("term", F.explode("postings").alias("p")).groupBy("term").agg(F.count("*").alias("docs"), F.sum(F.size("p.positions")).cast("long").alias("hits"))
)
for _mode, _cond in (("and", "count(DISTINCT term) = 2"), ("or", "count(*) > 0")):
    query(f"search_{_mode}", f"SELECT doc_id AS doc, count(*) AS hits FROM {_TOK} WHERE term IN ('the', 'que') GROUP BY doc_id HAVING {_cond}")(
        lambda s, d, m=_mode: I.search(I.inverted_index(table(s, d, "documents")), ["the", "que"], m)
    )

# ---- windows -----------------------------------------------------------------------------------------

query("window_running_sum", "SELECT event_id, user_id, (sum(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING))::BIGINT AS running FROM events")(
    lambda s, d: W.running(table(s, d, "events"), ["user_id"], ["ts", "event_id"], F.col("event_id")).select("event_id", "user_id", "running")
)
query("window_moving_avg", "SELECT event_id, avg(event_id) OVER (PARTITION BY event_type ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND 1 FOLLOWING) AS moving FROM events")(
    lambda s, d: W.moving_avg_rows(table(s, d, "events"), ["event_type"], ["ts", "event_id"], F.col("event_id"), 3, 1).select("event_id", "moving")
)
query("window_range_frame", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice RANGE BETWEEN 500 PRECEDING AND 500 FOLLOWING) AS near FROM orders")(
    lambda s, d: W.range_frame(table(s, d, "orders"), ["o_orderpriority"], F.col("o_totalprice"), F.count("*"), 500, 500, "near").select("o_orderkey", "near")
)
query("sessionize", """SELECT event_id, user_id, (sum(new) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING))::BIGINT AS session FROM (
  SELECT event_id, user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR epoch_us(ts) - epoch_us(lag(ts) OVER w) > 3600000000 THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts))""")(
    lambda s, d: W.sessionize(table(s, d, "events"), "user_id", "ts", 3600).select("event_id", "user_id", "session")
)

_PW = "OVER (PARTITION BY event_type ORDER BY ts, event_id)"
query("window_ranks", f"""SELECT event_id, row_number() {_PW} AS rn, rank() OVER (PARTITION BY event_type ORDER BY user_id) AS rnk, dense_rank() OVER (PARTITION BY event_type ORDER BY user_id) AS drnk,
 round(percent_rank() OVER (PARTITION BY event_type ORDER BY user_id), 9) AS prnk, round(cume_dist() OVER (PARTITION BY event_type ORDER BY user_id), 9) AS cdist, ntile(5) {_PW} AS tile FROM events""")(
    lambda s, d: W.partitioned_ranks(table(s, d, "events"), ["event_type"], ["ts", "event_id"], ["user_id"], 5).select("event_id", "rn", "rnk", "drnk", F.round("prnk", 9).alias("prnk"), F.round("cdist", 9).alias("cdist"), "tile")
)
query("window_values", f"""SELECT event_id, first_value(user_id) OVER w AS first_user, last_value(user_id) OVER w AS last_user, nth_value(user_id, 3) OVER w AS third_user, lag(user_id, 2) {_PW} AS before, lead(user_id, 2) {_PW} AS after
 FROM events WINDOW w AS (PARTITION BY event_type ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""")(
    lambda s, d: W.partitioned_values(table(s, d, "events"), ["event_type"], ["ts", "event_id"], "user_id", 3, 2).select("event_id", F.col("first").alias("first_user"), F.col("last").alias("last_user"), F.col("nth").alias("third_user"), F.col("lag").alias("before"), F.col("lead").alias("after"))
)
query("filters", """SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'middle' ELSE 'large' END AS class, nullif(p_size, 7) IS NULL AS seven FROM part
 WHERE (p_brand IN ('Brand#11', 'Brand#12', 'Brand#23') OR p_name LIKE '%e%' OR NOT regexp_matches(p_type, '^[A-M]')) AND p_size BETWEEN 2 AND 45 AND p_retailprice IS NOT NULL AND NOT (p_size = 20 AND p_partkey > 100)""")(
    lambda s, d: table(s, d, "part").filter((F.col("p_brand").isin("Brand#11", "Brand#12", "Brand#23") | F.col("p_name").like("%e%") | ~F.col("p_type").rlike("^[A-M]")) & F.col("p_size").between(2, 45) & F.col("p_retailprice").isNotNull() & ~((F.col("p_size") == 20) & (F.col("p_partkey") > 100)))
    .select("p_partkey", F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "middle").otherwise("large").alias("class"), F.nullif(F.col("p_size"), F.lit(7)).isNull().alias("seven"))
)
query("modes_and_sets", """SELECT o_orderstatus, string_agg(DISTINCT o_orderpriority, ',' ORDER BY o_orderpriority) AS priorities,
 (SELECT k FROM (SELECT o.o_custkey AS k, count(*) AS n FROM orders o WHERE o.o_orderstatus = g.o_orderstatus GROUP BY 1) ORDER BY n DESC, k LIMIT 1) AS usual FROM orders g GROUP BY o_orderstatus""")(
    lambda s, d: table(s, d, "orders").groupBy("o_orderstatus").agg(F.array_join(F.sort_array(F.collect_set("o_orderpriority")), ",").alias("priorities"), F.mode("o_custkey", True).alias("usual"))
)
query("kll_percentiles")(lambda s, d: A.kll_percentile(table(s, d, "events"), "value", [0.1, 0.5, 0.9]))

# ---- scalar functions --------------------------------------------------------------------------------

query("string_fns", """SELECT p_partkey, length(p_name)::INTEGER AS len, strlen(p_name)::INTEGER AS bytes, upper(p_name) AS up, lower(p_name) AS low, substr(p_name, 1, 4) AS head, lpad(p_name, 20, '*') AS padded,
 concat_ws('-', p_name, p_name) AS joined, split_part(p_name, ' ', 1) AS part, regexp_extract(p_name, '([0-9]+)', 1) AS digits, regexp_replace(p_name, '[aeiou]', '_', 'g') AS masked, instr(p_name, 'a')::INTEGER AS "at",
 translate(p_name, 'abc', 'xyz') AS swapped, reverse(p_name) AS turned, ascii(p_name)::INTEGER AS first_code, hex(p_name) AS hexed, levenshtein(p_name, 'green')::INTEGER AS distance, trim(' ' || p_name || ' ') AS trimmed FROM part""")(
    lambda s, d: table(s, d, "part").select("p_partkey", *[c.alias(n) for n, c in scalar.string_functions(F.col("p_name")).items()])
)
query("date_fns", """SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, quarter(o_orderdate)::INTEGER AS q, month(o_orderdate)::INTEGER AS m, day(o_orderdate)::INTEGER AS d, dayofyear(o_orderdate)::INTEGER AS doy,
 date_trunc('month', o_orderdate)::DATE AS month_start, o_orderdate::DATE + 10 AS plus10, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INTEGER AS days, last_day(o_orderdate)::DATE AS month_end,
 (o_orderdate::DATE + INTERVAL 1 MONTH)::DATE AS next_month, strftime(o_orderdate, '%Y-%m-%d') AS text, epoch_us(o_orderdate) AS micros FROM orders""")(
    lambda s, d: table(s, d, "orders").select("o_orderkey", *[c.alias(n) for n, c in scalar.date_functions(F.col("o_orderdate")).items()])
)
query("math_fns", """SELECT c_custkey, floor(c_acctbal)::BIGINT AS fl, ceil(c_acctbal)::BIGINT AS ce, abs(c_acctbal) AS ab, sign(c_acctbal)::INTEGER AS sg, round(sqrt(abs(c_acctbal)), 6) AS sq, round(ln(abs(c_acctbal) + 1), 6) AS ln1,
 round(exp(-abs(c_acctbal) / 10000), 6) AS ex, greatest(c_acctbal, 0.0::DOUBLE) AS gr, least(c_acctbal, 0.0::DOUBLE) AS le, ((floor(c_acctbal)::BIGINT % 7 + 7) % 7) AS pm,
 greatest(0, least(12, floor((c_acctbal + 1000) / 1000) + 1))::BIGINT AS bucket, floor(abs(c_acctbal))::BIGINT >> 3 AS shifted FROM customer""")(
    lambda s, d: table(s, d, "customer").select("c_custkey", *[c.alias(n) for n, c in scalar.math_functions(F.col("c_acctbal")).items() if n != "r1"])
)
_WORDS = r"list_filter(regexp_split_to_array(lower(text), '[ \t\n\x0B\f\r]+'), lambda x: x <> '')"
query("array_fns", f"""SELECT doc_id, len(w)::INTEGER AS n, w[1] AS first, len(list_distinct(w))::INTEGER AS uniq, list_max(list_transform(w, lambda x: length(x)))::INTEGER AS longest,
 array_to_string(list_sort(w)[1:3], ',') AS ordered, list_sum(list_transform(w, lambda x: length(x)))::INTEGER AS chars, len(list_filter(w, lambda x: length(x) < 4))::INTEGER AS short, list_contains(w, 'the') AS has_the
 FROM (SELECT doc_id, {_WORDS} AS w FROM documents) WHERE len(w) > 0""")(
    lambda s, d: table(s, d, "documents").withColumn("w", I.tokens(F.col("text"))).filter("size(w) > 0").select("doc_id", *[c.alias(n) for n, c in scalar.array_functions(F.col("w")).items()])
)
query("vector_norms", "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 6) AS norm FROM embeddings")(
    lambda s, d: table(s, d, "embeddings").select("vec_id", F.round(scalar.vector_norm(F.col("embedding")), 6).alias("norm"))
)
query("json_props", "SELECT event_id, (props->>'k')::BIGINT AS k, (props->>'k')::BIGINT AS parsed, '{\"k\":' || (props->>'k') || '}' AS again, md5(props) AS digest FROM events")(
    lambda s, d: table(s, d, "events").select("event_id", *[c.alias(n) for n, c in scalar.json_functions(F.col("props")).items() if n != "crc"])
)


@query("table_functions", """SELECT i::INTEGER AS slice, (i / 8)::DOUBLE AS low, ((i + 1) / 8)::DOUBLE AS high, count(*) AS rows FROM range(8) t(i)
 JOIN (SELECT (o_totalprice - lo) / (hi - lo) AS y FROM orders, (SELECT min(o_totalprice) AS lo, max(o_totalprice) AS hi FROM orders)) ON y >= i / 8 AND (y < (i + 1) / 8 OR i = 7 AND y = 1) GROUP BY i""")
def _udtf(spark, d):
    """The table function's slices, and how many orders' prices lie in each."""
    udf.register_all(spark)
    df = table(spark, d, "orders")
    low, high = df.agg(F.min("o_totalprice"), F.max("o_totalprice")).first()
    y = df.select(((F.col("o_totalprice") - F.lit(low)) / F.lit(high - low)).alias("y"))
    slices = spark.sql("SELECT * FROM quantile_slices(8)")
    inside = (F.col("y") >= F.col("low")) & ((F.col("y") < F.col("high")) | (F.col("slice") == 7) & (F.col("y") == 1))
    return y.join(F.broadcast(slices), inside).groupBy("slice", "low", "high").agg(F.count("*").alias("rows"))


# ---- streams -----------------------------------------------------------------------------------------


def _stream(spark, d, **kw):
    return ST.stream_table(spark, d, "events", **kw)


def _drain(df: DataFrame, mode: str = "complete") -> DataFrame:
    return ST.run_to_table(df, f"q{uuid.uuid4().hex}", mode, scratch(df.sparkSession, "stream"))


_SUM = "count(*) AS n, sum(user_id)::BIGINT AS users"


def _sums():
    return [F.count("*").alias("n"), F.sum("user_id").alias("users")]


query("stream_tumbling", f'SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY AS "end", event_type, {_SUM} FROM events GROUP BY ALL')(
    lambda s, d: _drain(ST.tumbling(_stream(s, d), "ts", "1 day", ["event_type"], _sums()))
)
query("stream_sliding", f"""SELECT b + INTERVAL (k * 6) HOUR AS start, b + INTERVAL (k * 6 + 12) HOUR AS "end", {_SUM} FROM (SELECT user_id, time_bucket(INTERVAL 6 HOUR, ts) AS b, unnest([0, -1]) AS k FROM events) GROUP BY ALL""")(
    lambda s, d: _drain(ST.sliding(_stream(s, d), "ts", "12 hours", "6 hours", [], _sums()))
)
query("stream_session", """SELECT min(ts) AS start, max(ts) + INTERVAL 2 HOUR AS "end", user_id, count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS g FROM (
 SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 2 HOUR THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, g""")(
    lambda s, d: _drain(ST.session(_stream(s, d), "ts", "2 hours", ["user_id"], [F.count("*").alias("n")]))
)
query("stream_dedup", "SELECT count(*) AS n FROM (SELECT DISTINCT user_id, event_type FROM events)")(
    lambda s, d: _drain(ST.stream_dedup(_stream(s, d), ["user_id", "event_type"], "ts", "3650 days").select("user_id", "event_type"), "append").agg(F.count("*").alias("n"))
)
query("stream_static_join", "SELECT event_id, c_name FROM events JOIN customer ON user_id = c_custkey")(
    lambda s, d: _drain(ST.stream_static_join(_stream(s, d), table(s, d, "customer"), F.col("user_id") == F.col("c_custkey")).select("event_id", "c_name"), "append")
)


@query("stream_interval_join", "SELECT a.event_id AS left_id, b.event_id AS right_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 10 HOURS WHERE a.event_id % 2 = 0 AND b.event_id % 2 = 1")
def _interval(spark, d):
    a = _stream(spark, d).filter("event_id % 2 = 0").select(F.col("event_id").alias("left_id"), F.col("user_id").alias("u1"), F.col("ts").cast("timestamp").alias("t1"))
    b = _stream(spark, d).filter("event_id % 2 = 1").select(F.col("event_id").alias("right_id"), F.col("user_id").alias("u2"), F.col("ts").cast("timestamp").alias("t2"))
    return _drain(ST.stream_interval_join(a, b, "u1", "u2", "t1", "t2", "10 hours", "30 days").select("left_id", "right_id"), "append")


def _event_model(spark, d):
    sf = model_sort(table(spark, d, "events"), ["value", "event_id"], f=8, sample=SampleSpec(method="systematic", pk="event_id", every=10))
    return sf.spec, sf.model


@query("stream_fragments", "SELECT event_id, value, row_number() OVER (ORDER BY value, event_id) AS rn FROM events")
def _fragments(spark, d):
    """A stream appended to slices by a frozen model, then sealed."""
    spec, model = _event_model(spark, d)
    path = scratch(spark, "fragments")
    ST.stream_fragments(_stream(spark, d).select("event_id", "value"), spec, model, 8, f"{path}/data", f"{path}/checkpoint").awaitTermination()
    return ST.finalize_fragments(spark, f"{path}/data", ["value", "event_id"], "event_id long, value double", 8)


@query("drift_monitor", f"{model_sql('events', 'value', 'event_id % 10 = 0', 8)} SELECT p::INTEGER AS slice, count(pid)::BIGINT AS rows, round(count(pid) / (SELECT count(*) FROM predicted), 9) AS share FROM range(8) t(p) LEFT JOIN predicted ON p = pid GROUP BY p")
def _drift(spark, d):
    """Shares of slices in a stream, under a model of every tenth event."""
    spec, model = _event_model(spark, d)
    seen = _drain(ST.drift_monitor(_stream(spark, d).select("event_id", "value"), spec, model, 8), "update")
    last = seen.groupBy("slice").agg(F.max(F.struct("rows", "share")).alias("r"))  # counts only grow
    return last.select("slice", F.col("r.rows").alias("rows"), F.round("r.share", 9).alias("share"))


# ---- sources and sinks -------------------------------------------------------------------------------


@query("write_read_sorted", "SELECT event_id, value, row_number() OVER (ORDER BY value, event_id) AS rn FROM events")
def _round_trip(spark, d):
    path = scratch(spark, "sorted")
    io.write_sorted(model_sort(table(spark, d, "events").select("event_id", "value"), ["value", "event_id"], f=8), path)
    return io.read_sorted(spark, path)


@query("read_sorted_range", "SELECT * FROM (SELECT event_id, value, row_number() OVER (ORDER BY value, event_id) AS rn FROM events) WHERE rn BETWEEN 100 AND 199")
def _round_trip_range(spark, d):
    path = scratch(spark, "sorted")
    io.write_sorted(model_sort(table(spark, d, "events").select("event_id", "value"), ["value", "event_id"], f=8), path)
    return io.read_sorted(spark, path, low=100, high=199)


for _fmt in ("csv", "json", "orc"):

    @query(f"read_records_{_fmt}", "SELECT c_custkey, c_name, c_acctbal FROM customer")
    def _formats(spark, d, fmt=_fmt):
        path, df = scratch(spark, fmt), table(spark, d, "customer").select("c_custkey", "c_name", "c_acctbal")
        df.write.format(fmt).save(path)
        return io.read_records(spark, path, fmt, df.schema)


@query("read_fixed_records", "SELECT c_name AS key, rpad(c_mktsegment, 12, ' ') AS payload FROM customer")
def _fixed(spark, d):
    path = scratch(spark, "fixed")
    io.write_fixed(table(spark, d, "customer").select("c_name", "c_mktsegment"), path, {"c_name": 18, "c_mktsegment": 12})
    return io.read_fixed(spark, path, {"key": 18, "payload": 12})


query("read_striped", "SELECT count(*) AS n FROM lineitem")(lambda s, d: io.read_striped(s, f"{d}/lineitem.parquet", 6).agg(F.count("*").alias("n")))


@query("write_sharded", "SELECT count(*) AS n, sum(o_orderkey)::BIGINT AS keys FROM orders")
def _sharded(spark, d):
    path = scratch(spark, "shards")
    io.write_sharded(_by_orderkey(spark, d), path)
    return spark.read.parquet(path).agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("keys"))


@query("write_bucketed", "SELECT l_orderkey, count(*) AS n FROM lineitem GROUP BY l_orderkey")
def _bucketed(spark, d):
    """A bucketed table's groups by its key need no exchange."""
    name = f"equidepth_{uuid.uuid4().hex}"
    io.write_bucketed(table(spark, d, "lineitem").select("l_orderkey", "l_quantity"), name, "l_orderkey", 8)
    return spark.table(name).groupBy("l_orderkey").agg(F.count("*").alias("n"))


@query("slice_cv_udf", "SELECT true AS near")
def _cv(spark, d):
    """The grouped function and the built-in agree on the variation of slice sizes."""
    sf = model_sort(table(spark, d, "events").select("value"), ["value"], f=8)
    sizes = sf.offsets_frame().withColumn("rows", F.col("rows").cast("double"))
    return sizes.agg(udf.bin_cv("rows").alias("a")).crossJoin(sizes.agg((F.stddev_pop("rows") / F.avg("rows")).alias("b"))).select((F.abs(F.col("a") - F.col("b")) < 1e-9).alias("near"))


# ---- experiments -------------------------------------------------------------------------------------


@query("w01_uniform_records")
def _w01(spark, d):
    """Prices of lineitem are uniform."""
    return metrics.bin_skew(metrics.equi_width_histogram(table(spark, d, "lineitem"), "l_extendedprice"))


@query("w02_skewed_records")
def _w02(spark, d):
    out = None
    for tab, col in (("events", "value"), ("documents", "n_chars")):
        one = metrics.bin_skew(metrics.equi_width_histogram(table(spark, d, tab), col)).withColumn("key", F.lit(col))
        out = one if out is None else out.unionByName(one)
    return out


def _inputs(spark, d):
    return {"uniform": (table(spark, d, "lineitem"), "l_extendedprice"), "skewed": (table(spark, d, "events"), "value")}


def _records(spark, n=50_000):
    """Generated records of one count and width: uniform keys, and keys half of which start with a prefix of the table."""
    return {"uniform": (generate_records(spark, n), "key"), "skewed": (generate_records(spark, n, skew=SkewSpec(share=0.5, rule="uniform")), "key")}


@query("w03_storage")
def _w03(spark, d):
    found = workloads.media(spark, scratch(spark, "storage"))
    return workloads.run_storage(spark, _inputs(spark, d), found, ["model", "os_merge", "builtin"], formats=("parquet", "csv", "orc"), codecs=("snappy", "none", "zstd"))


@query("w05_skew_effect")
def _w05(spark, d):
    """Both files have the same number and width of records, so the drop is the skew's."""
    found = workloads.media(spark, scratch(spark, "skew"))
    return workloads.run_skew(workloads.run_storage(spark, _records(spark), found, ["model", "radix", "builtin", "os_merge"]), "uniform", "skewed")


query("w04_histogram_events", "SELECT greatest(0, least(999, floor((value - lo) / (hi - lo) * 1000)))::INTEGER AS bin, count(*) AS n FROM events, (SELECT min(value) AS lo, max(value) AS hi FROM events) GROUP BY 1")(
    lambda s, d: workloads.run_histogram(table(s, d, "events"), "value").select("bin", "n")
)


@query("w06_scale")
def _w06(spark, d):
    """Eight sizes of customer in equal steps, up to the whole."""
    df = table(spark, d, "customer")
    return workloads.run_scale(spark, [(float(k), df.filter(F.pmod("c_custkey", F.lit(8)) < k)) for k in range(1, 9)], ["c_name"], ["model", "builtin", "os_merge"])


@query("w07_energy")
def _w07(spark, d):
    import time

    df, secs = table(spark, d, "lineitem"), {}
    for name in ("model", "builtin", "radix", "os_merge"):
        began = time.perf_counter()
        io.write_noop(workloads.sorters()[name](df, ["l_extendedprice"]))
        secs[name] = time.perf_counter() - began
    return workloads.run_energy(spark, secs, 65.0)


query("w08_phases")(lambda s, d: workloads.run_phases(table(s, d, "lineitem"), ["l_extendedprice"], scratch(s, "phases")))
query("w09_io")(lambda s, d: workloads.run_io(table(s, d, "lineitem"), ["l_extendedprice"], ["model", "radix", "builtin", "os_merge", "binary_merge", "hier_merge"], scratch(s, "io")))


@query("w10_sample_curve")
def _w10(spark, d):
    out = None
    for tab, col in (("events", "ts"), ("events", "value"), ("lineitem", "l_extendedprice")):
        one = workloads.run_sample_curve(table(spark, d, tab), col, [0.001, 0.005, 0.01, 0.05, 0.2, 1.0], ["bernoulli", "first_batch"]).withColumn("key", F.lit(col))
        out = one if out is None else out.unionByName(one)
    return out


query("w11_balance_records")(lambda s, d: workloads.run_balance(table(s, d, "events").select(F.format_string("%010.3f", "value").alias("key")), "key", [8, 16, 64]))
query("w11_balance_events")(lambda s, d: workloads.run_balance(table(s, d, "events"), "value", [8, 16, 64]))
query("w11_balance_text")(lambda s, d: workloads.run_balance(table(s, d, "documents"), "text", [8, 16]))
query("w11_balance_price")(lambda s, d: workloads.run_balance(table(s, d, "lineitem"), "l_extendedprice", [8, 16, 64]))


def _wide(spark, d):
    """lineitem with a number of its own and a payload of some 200 bytes behind a narrow key."""
    line = table(spark, d, "lineitem").withColumn("row_id", F.monotonically_increasing_id())
    return line.withColumn("payload", F.repeat(F.md5(F.concat_ws("-", "l_orderkey", "l_partkey")), 6))


query("w12_coalesce")(lambda s, d: workloads.run_coalesce(_wide(s, d), ["l_extendedprice"], "row_id", scratch(s, "coalesce")))
query("w12_coalesce_documents")(lambda s, d: workloads.run_coalesce(table(s, d, "documents"), ["n_chars"], "doc_id", scratch(s, "coalesce")))
query("w13_memory_sorts")(lambda s, d: workloads.run_memory_sorts(table(s, d, "lineitem"), "l_extendedprice"))


@query("w15_plans")
def _w15(spark, d):
    """Plans for orders as it is, and for 1.2 TB and 100 TB of such rows."""
    n, width = table_size(table(spark, d, "orders"))
    return workloads.run_plan(spark, [(n, width), (1.2e12 / width, width), (1e14 / width, width)])


query("w15_two_rounds")(lambda s, d: workloads.run_rounds(table(s, d, "lineitem"), ["l_extendedprice", "l_orderkey"]))


@query("w17_code_width")
def _w17(spark, d):
    out = None
    for label, df, col, raw, widths in (("url", table(spark, d, "pages"), "url", False, range(1, 10)), ("text", table(spark, d, "documents"), "text", True, range(1, 8)), ("records", generate_records(spark, 50_000), "key", False, range(1, 10))):
        one = workloads.run_code_width(df, col, list(widths), raw=raw).withColumn("key", F.lit(label))
        out = one if out is None else out.unionByName(one)
    return out


@query("work_span_formula", "SELECT * FROM (VALUES (1000000.0::DOUBLE, 10::INTEGER, 4::INTEGER, 850000.0::DOUBLE)) t(n, r, s, span)")
def _span(spark, d):
    return spark.createDataFrame([(1e6, 10, 4, metrics.work_span(1e6, 10, 4)["span"])], "n double, r int, s int, span double")


@query("merge_cost_model")
def _merge_cost(spark, d):
    """Of the runs that orders makes."""
    n, runs = make_runs(table(spark, d, "orders"), ["o_totalprice", "o_orderkey"], 2000).agg(F.count("o_totalprice"), F.countDistinct("run_id")).first()
    rows = [(k, float(c["passes"]), c["moved"], c["comparisons"]) for k in ("slices", "heap", "binary", "hier") for c in (metrics.merge_cost(float(n), runs, k, (200, 6)),)]
    return spark.createDataFrame(rows, "strategy string, passes double, moved double, comparisons double")


@query("model_size")
def _model_size(spark, d):
    spec, model = _event_model(spark, d)
    return model.to_df(spark).withColumn("model_bytes", F.lit(model.bytes))
