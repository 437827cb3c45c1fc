"""Queries over the given tables, and the same in SQL where SQL can say it.

Comparison of results ignores order, so sorted results carry their place as `rn`.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import udf
from .measures import metrics, workloads
from .measures.validate import check_sorted, checksum, invariant_violations, validate_all
from .operators import aggregates as A
from .operators import joins as J
from .operators import ranks as R
from .operators import sets as S
from .plans import keys as K
from .plans import mergesort as M
from .plans import memsort
from .plans.cdf_model import train_cdf, train_cdf_sql
from .plans.extsort import PID, builtin_sort, concurrent_slices, fragment_matrix, makespan, model_sort, pointer_sorted, radix_sort, sort_late_payload
from .plans.partitioners import exact_pid, hash_pid, quantile_pid, radix_bits_pid, radix_pid, sketch_pid
from .plans.sampling import SampleSpec, draw_sample, sample_frame
from .session import scratch
from .sources import io

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}

LINEITEM = "l_orderkey l_partkey l_suppkey l_linenumber l_quantity l_extendedprice l_discount l_tax l_returnflag l_linestatus l_shipdate".split()
SAMPLE = SampleSpec(method="systematic", pk="l_orderkey", every=10)


def query(name: str, sql: str | None = None):
    def put(fn: Query) -> Query:
        QUERIES[name] = fn
        if sql is not None:
            ORACLE_SQL[name] = sql
        return fn

    return put


def table(spark: SparkSession, d: str, name: str) -> DataFrame:
    return io.read_table(spark, d, name)


def rest(cols: list[str], *first: str) -> list[str]:
    return [*first, *[c for c in cols if c not in {f.lstrip("-") for f in first}]]


def sql_order(cols: list[str]) -> str:
    return ", ".join(f"{c[1:]} DESC NULLS LAST" if c.startswith("-") else f"{c} ASC NULLS FIRST" for c in cols)


def sort_sql(tab: str, cols: list[str], by: list[str]) -> str:
    return f"SELECT {', '.join(cols)}, row_number() OVER (ORDER BY {sql_order(by)}) AS rn FROM {tab}"


def model_sql(tab: str, col: str, picked: str, f: int, leaves: int = 64, columns: str = "") -> str:
    """WITH ... predicted(code, y, pid, ...): a linear root and its leaves fitted on the rows `picked`, applied to all rows of a table."""
    return f"""WITH s AS (SELECT {col}::DOUBLE AS code FROM {tab} WHERE {picked}),
t AS (SELECT code, cume_dist() OVER (ORDER BY code) AS y FROM s), m AS (SELECT min(code) AS x0 FROM s),
r AS (SELECT regr_slope(y, code - x0) AS a, regr_intercept(y, code - x0) AS b FROM t, m),
p AS (SELECT greatest(0, least({leaves - 1}, floor((a * (code - x0) + b) * {leaves})))::INTEGER AS leaf, code, y FROM t, m, r),
c AS (SELECT leaf, min(code) AS c0, max(y) AS hi FROM p GROUP BY leaf),
g AS (SELECT leaf, any_value(c0) AS c0, any_value(hi) AS hi, greatest(0, coalesce(regr_slope(y, code - c0), 0)) AS a, avg(y) AS my, avg(code - c0) AS mx FROM p JOIN c USING (leaf) GROUP BY leaf),
leaf AS (SELECT k::INTEGER AS leaf, a, c0, my - a * mx AS b, coalesce(max(hi) OVER (ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS lo, coalesce(max(hi) OVER (ORDER BY k), 0) AS hi FROM range({leaves}) u(k) LEFT JOIN g ON k = leaf),
placed AS (SELECT {columns}{col}::DOUBLE AS code, greatest(0, least({leaves - 1}, floor((a * ({col} - x0) + b) * {leaves})))::INTEGER AS leaf FROM {tab}, m, r),
predicted AS (SELECT *, least({f - 1}, floor(y * {f}))::INTEGER AS pid FROM (SELECT q.*, greatest(0, least(1, greatest(lo, least(hi, coalesce(a * (code - c0) + b, lo))))) AS y FROM placed q JOIN leaf USING (leaf)))"""


# ---- sorts: the model's, then every baseline against the same SQL ------------------------------------

EVENTS = "event_id ts user_id event_type value props".split()
ORDERS = "o_orderkey o_custkey o_orderstatus o_totalprice o_orderdate o_orderpriority".split()
CUSTOMER = "c_custkey c_name c_nationkey c_acctbal c_mktsegment".split()
SORTS = {
    "sort_lineitem_price": ("lineitem", LINEITEM, rest(LINEITEM, "l_extendedprice")),
    "sort_events_value": ("events", EVENTS, ["value", "event_id"]),
    "sort_events_value_desc": ("events", EVENTS, ["-value", "event_id"]),
    "sort_orders_multi": ("orders", ORDERS, ["o_orderdate", "-o_totalprice", "o_orderkey"]),
    "sort_customer_name": ("customer", CUSTOMER, ["c_name", "c_custkey"]),
    "sort_pages_url": ("pages", ["page_id", "url"], ["url", "page_id"]),
    "sort_documents_text": ("documents", ["doc_id", "text", "source"], ["text", "doc_id"]),
    "sort_part_name_dups": ("part", ["p_partkey", "p_name", "p_retailprice"], ["p_name", "p_partkey"]),
    "sort_events_ts": ("events", EVENTS, ["ts", "event_id"]),
    "sort_acctbal_negative": ("customer", CUSTOMER, ["c_acctbal", "c_custkey"]),
    "sort_shipdate": ("lineitem", LINEITEM, rest(LINEITEM, "-l_shipdate")),
}
for _name, (_tab, _cols, _by) in SORTS.items():
    query(_name, sort_sql(_tab, _cols, _by))(lambda s, d, t=_tab, c=_cols, b=_by: model_sort(table(s, d, t).select(*c), b, f=16).with_rn())

_NULLED = "SELECT l_orderkey, l_linenumber, l_partkey, nullif(l_quantity, 7.0) AS q, l_extendedprice FROM lineitem"


def _nulled(spark, d):
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.when(F.col("l_quantity") != 7.0, F.col("l_quantity")).alias("q"), "l_extendedprice")


for _lead in (True, False):
    _n = "FIRST" if _lead else "LAST"
    query(f"sort_nulls_{_n.lower()}", f"SELECT *, row_number() OVER (ORDER BY q ASC NULLS {_n}, l_orderkey, l_linenumber, l_partkey, l_extendedprice) AS rn FROM ({_NULLED})")(
        lambda s, d, lead=_lead: model_sort(_nulled(s, d), [K.Order("q", nulls_first=lead), "l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice"], f=16).with_rn()
    )

_EV = ["value", "event_id"]
query("sort_two_rounds", sort_sql("lineitem", LINEITEM, rest(LINEITEM, "l_extendedprice")))(lambda s, d: model_sort(table(s, d, "lineitem"), rest(LINEITEM, "l_extendedprice"), f=16, rounds=2).with_rn())
query("sort_event_type_five_keys", sort_sql("events", EVENTS, ["event_type", "event_id"]))(lambda s, d: model_sort(table(s, d, "events"), ["event_type", "event_id"], f=16, split_ties=True).with_rn())
query("sort_recursive_root", sort_sql("events", EVENTS, _EV))(lambda s, d: model_sort(table(s, d, "events"), _EV, f=16, root="recursive").with_rn())
query("sort_first_batch_sample", sort_sql("events", EVENTS, ["ts", "event_id"]))(lambda s, d: model_sort(table(s, d, "events"), ["ts", "event_id"], f=16, sample=SampleSpec(method="first_batch", batch_rows=1000)).with_rn())
query("sort_files_sample", sort_sql("events", EVENTS, ["ts", "event_id"]))(lambda s, d: model_sort(table(s, d, "events"), ["ts", "event_id"], f=16, sample=SampleSpec(method="files")).with_rn())
query("sort_late_payload", sort_sql("orders", ORDERS, ["o_totalprice", "o_orderkey"]))(lambda s, d: sort_late_payload(table(s, d, "orders"), ["o_totalprice", "o_orderkey"], "o_orderkey", f=16))
query("sort_url_refined", sort_sql("pages", ["page_id", "url"], ["url", "page_id"]))(lambda s, d: model_sort(table(s, d, "pages").select("page_id", "url"), ["url", "page_id"], f=8, refine=True).with_rn())
query("sort_split_ties", sort_sql("events", EVENTS, ["event_type", "-value", "event_id"]))(lambda s, d: model_sort(table(s, d, "events"), ["event_type", "-value", "event_id"], f=16, split_ties=True).with_rn())
query("sort_pointers", sort_sql("events", EVENTS, ["-value", "event_id"]))(lambda s, d: _pointers(s, d))
query("radix_sort", sort_sql("events", EVENTS, _EV))(lambda s, d: radix_sort(table(s, d, "events"), _EV, 16).with_rn())


def _pointers(spark, d):
    """Places of rows that leave a slice by sorted pointers, a few at a time."""
    sf = model_sort(table(spark, d, "events"), ["-value", "event_id"], f=16)
    out = pointer_sorted(sf, 2_000).withColumn("_i", F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1))
    return out.join(F.broadcast(sf.offsets_frame().select(PID, "row_offset")), PID).select(*EVENTS, (F.col("row_offset") + F.col("_i") + 1).cast("long").alias("rn"))


@query("builtin_sort", sort_sql("events", EVENTS, _EV))
def _builtin(spark, d):
    """Places of a built-in sort: partition sizes, then a number inside each partition."""
    df = builtin_sort(table(spark, d, "events"), _EV).withColumns({"_p": F.spark_partition_id(), "_i": F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1)})
    path = scratch(spark, "builtin")
    df.write.parquet(path)
    kept = spark.read.parquet(path)
    sizes = kept.groupBy("_p").count().orderBy("_p").collect()
    before, rows = 0, []
    for p, n in sizes:
        rows.append((p, before))
        before += n
    starts = spark.createDataFrame(rows, "_p int, _b long")
    return kept.join(F.broadcast(starts), "_p").select(*EVENTS, (F.col("_b") + F.col("_i") + 1).cast("long").alias("rn"))


_OE = ["o_totalprice", "o_orderkey"]
for _name, _how, _fan in (("heap", "heap", (200,)), ("binary", "binary", (2,)), ("hier", "hier", (4, 6))):
    query(f"merge_sort_{_name}", sort_sql("orders", ORDERS, _OE))(lambda s, d, h=_how, k=_fan: M.merge_runs(M.make_runs(table(s, d, "orders"), _OE, 2000), _OE, h, k))
for _p in ("os", "A", "B", "C"):
    query(f"merge_preset_{_p.lower()}", sort_sql("customer", CUSTOMER, ["-c_acctbal", "c_custkey"]))(lambda s, d, p=_p: M.external_merge_sort(table(s, d, "customer"), ["-c_acctbal", "c_custkey"], p, 500))
query("merge_model_runs", sort_sql("orders", ORDERS, _OE))(lambda s, d: M.merge_runs(M.make_runs(table(s, d, "orders"), _OE, 4000, routine="model"), _OE, "heap"))
query("merge_key_index_runs", sort_sql("orders", ORDERS, _OE))(lambda s, d: M.fetch_payload(M.merge_runs(M.make_runs(table(s, d, "orders"), _OE, 4000, payload=False, locator="o_orderkey"), _OE, "heap"), table(s, d, "orders"), "o_orderkey"))


def _memory(spark, d, routine, insertion_rows=1_000):
    """The in-memory routine on every slice, in the slice's own task. Insertion sort is quadratic: it gets so many slices that one has about
    insertion_rows rows, and a task takes several."""
    df = table(spark, d, "events").select("event_id", "value")
    f = max(16, -(-df.count() // insertion_rows)) if routine == "insertion" else 16
    sf = model_sort(df, _EV, f=f)
    tasks = min(f, max(16, int(spark.conf.get("spark.sql.shuffle.partitions"))))
    dealt = sf.exchanged if f == 16 else sf.sliced.repartitionById(tasks, F.floor(F.col(PID) * tasks / f).cast("int")).sortWithinPartitions(PID)

    def kernel(batches):
        import pyarrow as pa

        parts = list(batches)
        if parts:
            whole = pa.Table.from_batches(parts)
            pid = whole.column(PID).to_numpy()
            ends = [0, *(np.flatnonzero(pid[1:] != pid[:-1]) + 1).tolist(), len(pid)]
        for a, b in zip(ends, ends[1:], strict=False) if parts else ():
            t = whole.slice(a, b - a)
            ids, vals = t.column("event_id").to_numpy(), t.column("value").to_numpy()
            by_id = np.argsort(ids, kind="stable")
            order = by_id[memsort.memory_order(vals[by_id], routine)] if routine in ("merge", "natural", "insertion", "radix", "model") else None
            if order is None:  # unstable routines: equal values are put in order of id afterwards
                order = memsort.memory_order(vals, routine)
                order = order[np.lexsort((ids[order], vals[order]))]
            out = t.take(pa.array(order)).append_column("_k", pa.array(np.arange(1, len(order) + 1), pa.int64()))
            yield from out.combine_chunks().to_batches()

    kinds = ", ".join(f"`{n}` {t}" for n, t in sf.exchanged.dtypes)
    done = dealt.mapInArrow(kernel, kinds + ", _k long")
    return done.join(F.broadcast(sf.offsets_frame().select(PID, "row_offset")), PID).select("event_id", "value", (F.col("row_offset") + F.col("_k")).alias("rn"))


for _r in memsort.ROUTINES:
    query(f"memory_sort_{_r}", sort_sql("events", ["event_id", "value"], _EV))(lambda s, d, r=_r: _memory(s, d, r))

# ---- ranks, top-k, percentiles -----------------------------------------------------------------------

_VAL = ["value", "event_id"]


def _ev(spark, d):
    return model_sort(table(spark, d, "events").select("event_id", "value", "event_type"), _VAL, f=16)


def _ev_sql(expr: str, name: str) -> str:
    return f"SELECT event_id, value, event_type, {expr} AS {name} FROM events"


_TYPE = ["event_type", "event_id"]


def _et(spark, d):
    return model_sort(table(spark, d, "events").select("event_id", "value", "event_type"), _TYPE, f=8)


query("global_row_number", _ev_sql("row_number() OVER (ORDER BY value, event_id)", "rn"))(lambda s, d: R.global_row_number(_ev(s, d)))
query("global_rank", _ev_sql("rank() OVER (ORDER BY event_type)", "rnk"))(lambda s, d: R.global_rank(_et(s, d)))
query("global_dense_rank", _ev_sql("dense_rank() OVER (ORDER BY event_type)", "drnk"))(lambda s, d: R.global_dense_rank(_et(s, d)))
query("global_percent_rank", _ev_sql("percent_rank() OVER (ORDER BY value)", "prnk"))(lambda s, d: R.global_percent_rank(_ev(s, d)))
query("global_cume_dist", _ev_sql("cume_dist() OVER (ORDER BY event_type)", "cdist"))(lambda s, d: R.global_cume_dist(_et(s, d)))
query("global_ntile", "SELECT event_id, value, event_type, row_number() OVER w AS rn, ntile(7) OVER w::INTEGER AS tile FROM events WINDOW w AS (ORDER BY value, event_id)".replace("ntile(7) OVER w::INTEGER", "(ntile(7) OVER w)::INTEGER"))(lambda s, d: R.global_ntile(_ev(s, d), 7))
query("global_lag", "SELECT event_id, value, event_type, row_number() OVER w AS rn, lag(value, 2) OVER w AS prev FROM events WINDOW w AS (ORDER BY value, event_id)")(lambda s, d: R.global_lag(_ev(s, d), "value", 2))
query("global_lead", "SELECT event_id, value, event_type, row_number() OVER w AS rn, lead(event_id, 1) OVER w AS nxt FROM events WINDOW w AS (ORDER BY value, event_id)")(lambda s, d: R.global_lag(_ev(s, d), "event_id", 1, "nxt", lead=True))
query("global_running_sum", "SELECT event_id, value, event_type, row_number() OVER w AS rn, (sum(user_id) OVER w)::BIGINT AS running FROM events WINDOW w AS (ORDER BY value, event_id ROWS UNBOUNDED PRECEDING)")(
    lambda s, d: R.global_running(model_sort(table(s, d, "events").select("event_id", "value", "event_type", "user_id"), _VAL, f=16), F.col("user_id")).drop("user_id")
)
query("top_k_price", f"SELECT * FROM ({sort_sql('lineitem', LINEITEM, rest(LINEITEM, '-l_extendedprice'))}) WHERE rn <= 25")(lambda s, d: R.top_k(model_sort(table(s, d, "lineitem"), rest(LINEITEM, "-l_extendedprice"), f=16), 25))
query("bottom_k_value", f"SELECT * FROM ({sort_sql('events', EVENTS, _EV)}) WHERE rn <= 40")(lambda s, d: R.top_k(model_sort(table(s, d, "events"), _EV, f=16), 40))
query("limit_offset", f"SELECT * FROM ({sort_sql('events', EVENTS, _EV)}) WHERE rn BETWEEN 501 AND 560")(lambda s, d: R.limit_offset(model_sort(table(s, d, "events"), _EV, f=16), 500, 60))
query("builtin_top_k", "SELECT l_orderkey, l_partkey, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_partkey LIMIT 25")(
    lambda s, d: table(s, d, "lineitem").select("l_orderkey", "l_partkey", "l_extendedprice").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_partkey").limit(25)
)
query("exact_median_value", "SELECT 0.5::DOUBLE AS q, quantile_disc(value, 0.5) AS value FROM events")(lambda s, d: R.exact_percentile(_ev(s, d), [0.5]))
query("exact_percentiles", "SELECT q::DOUBLE AS q, v AS value FROM (SELECT unnest([0.05, 0.25, 0.75, 0.99]) AS q, unnest(quantile_disc(o_totalprice, [0.05, 0.25, 0.75, 0.99])) AS v FROM orders)")(
    lambda s, d: R.exact_percentile(model_sort(table(s, d, "orders").select("o_totalprice"), ["o_totalprice"], f=16), [0.05, 0.25, 0.75, 0.99])
)

# ---- codes -------------------------------------------------------------------------------------------

_DIGITS = " + ".join(f"CASE WHEN length(p_name) >= {i} THEN (ascii(substr(p_name, {i}, 1)) - 31) ELSE 0 END * {96 ** (9 - i)}::BIGINT" for i in range(1, 10))
_FIXED = " + ".join(f"(ascii(substr(c_name, {i}, 1)) - 32) * {95 ** (9 - i)}::BIGINT" for i in range(1, 10))
query("ascii_code_fixed", f"SELECT c_name, ({_FIXED})::BIGINT AS code FROM customer")(lambda s, d: table(s, d, "customer").select("c_name", K.ascii_code(F.col("c_name")).alias("code")))
query("ascii_code_variable", f"SELECT p_name, ({_DIGITS})::BIGINT AS code FROM part")(lambda s, d: table(s, d, "part").select("p_name", K.ascii_code(F.col("p_name"), variable=True).alias("code")))
_HEX = "('0x' || rpad(substr(hex(encode(text)), 1, 14), 14, '0'))::BIGINT"
query("byte_code_documents", f"SELECT doc_id, {_HEX} AS code FROM documents")(lambda s, d: table(s, d, "documents").select("doc_id", K.byte_code(F.col("text")).alias("code")))
query("common_prefix", "SELECT (SELECT max(k) FROM range(1, 19) t(k) WHERE (SELECT min(left(c_name, k)) = max(left(c_name, k)) FROM customer))::INTEGER AS shared")(
    lambda s, d: s.createDataFrame([(K.common_prefix_len(table(s, d, "customer"), "c_name"),)], "shared int")
)
query("code_collisions", "SELECT count(DISTINCT url) AS keys, count(DISTINCT left(url, 9)) AS codes, count(DISTINCT left(url, 9)) / count(DISTINCT url) AS ratio FROM pages")(
    lambda s, d: K.code_collisions(table(s, d, "pages"), K.ascii_code(F.col("url"), variable=True), "url")
)
_CODES = "(ascii(x) - 32) * 95 - 32 AS px, (ascii(y) - 32) * 95 + ascii(substr(y, 2, 1)) - 32 AS py, (ascii(x) - 31) * 96 AS lx, (ascii(y) - 31) * 96 + ascii(substr(y, 2, 1)) - 31 AS ly"


@query("pad_violation", f"""WITH k AS (SELECT x, y, {_CODES} FROM (SELECT substr(text, 2, 1) AS x, substr(text, 3, 2) AS y FROM documents WHERE regexp_full_match(substr(text, 2, 3), '[ -~]{{3}}')))
SELECT 'paper' AS pad, coalesce(sum((x < y AND px >= py OR x > y AND px <= py)::INTEGER), 0)::BIGINT AS broken FROM k UNION ALL SELECT 'low', coalesce(sum((x < y AND lx >= ly OR x > y AND lx <= ly)::INTEGER), 0)::BIGINT FROM k""")
def _pad(spark, d):
    """Pairs of keys whose codes fall the wrong way, by padding rule: the literal rule breaks, base 96 does not. A pair is a document's
    second character and the two after it, where all are printable."""
    df = table(spark, d, "documents").filter(F.substring("text", 2, 3).rlike("^[ -~]{3}$")).select(F.substring("text", 2, 1).alias("x"), F.substring("text", 3, 2).alias("y"))
    out = []
    for pad in ("paper", "low"):
        x, y = (K.ascii_code(F.col(c), 2, variable=True, pad=pad) for c in ("x", "y"))
        out.append(df.agg(F.sum((((F.col("x") < F.col("y")) & (x >= y)) | ((F.col("x") > F.col("y")) & (x <= y))).cast("int")).alias("broken")).select(F.lit(pad).alias("pad"), F.coalesce("broken", F.lit(0)).cast("long").alias("broken")))
    return out[0].unionByName(out[1])




@query("code_capacity", "SELECT o_orderkey, length(o_orderpriority)::INTEGER AS width, round(length(o_orderpriority) * log2(95), 6) AS bits, length(o_orderpriority) <= 9 AS fits FROM orders")
def _capacity(spark, d):
    """Bits that the code of each order's whole priority needs, and whether it fits."""
    df = table(spark, d, "orders").select("o_orderkey", F.length("o_orderpriority").alias("width"))
    longest = df.agg(F.max("width")).first()[0] or 0
    caps = spark.createDataFrame([(w, round(float(np.log2(95.0)) * w, 6), K.code_capacity(w)["fits"]) for w in range(1, longest + 1)], "width int, bits double, fits boolean")
    return df.join(F.broadcast(caps), "width", "left").select("o_orderkey", "width", "bits", "fits")


# ---- samples, model, slices --------------------------------------------------------------------------

_SYS = "SELECT l_extendedprice AS code FROM lineitem WHERE l_orderkey % 10 = 0"


def _price(spark, d):
    df = table(spark, d, "lineitem")
    return df, K.resolve(df, K.Order("l_extendedprice"))


def _sys(spark, d):
    df, spec = _price(spark, d)
    return sample_frame(df, spec.code(), SAMPLE, 0)


_TARGETS = f"SELECT code, count(*) AS n, (sum(count(*)) OVER (ORDER BY code) / sum(count(*)) OVER ())::DOUBLE AS y FROM ({_SYS}) GROUP BY code"
_ROOT = f"""WITH t AS (SELECT code, y FROM (SELECT code, cume_dist() OVER (ORDER BY code) AS y FROM ({_SYS}))),
r AS (SELECT regr_slope(y, code - m) AS a, regr_intercept(y, code - m) AS b, any_value(m) AS m FROM t, (SELECT min(code) AS m FROM t))"""
query("systematic_sample", f"SELECT count(*) AS n, min(code) AS low, max(code) AS high, sum(code::DECIMAL(18,2))::DECIMAL(28,2) AS total FROM ({_SYS})")(
    lambda s, d: _sys(s, d).agg(F.count("*").alias("n"), F.min("code").alias("low"), F.max("code").alias("high"), F.sum(F.col("code").cast("decimal(18,2)")).alias("total"))
)


@query("cdf_targets", f"SELECT code, round(y, 9) AS y FROM ({_TARGETS})")
def _targets(spark, d):
    """The sample's distribution at each value, by ranks of slices."""
    sf = model_sort(_sys(spark, d), ["code"], f=8)
    return R.global_cume_dist(sf, 1, "y").groupBy("code").agg(F.round(F.max("y"), 9).alias("y"))


@query("root_fit", f"{_ROOT} SELECT round(a * 1e6, 5) AS slope_e6, round(b, 6) AS intercept FROM r")
def _root(spark, d):
    """The root's line, from the numpy trainer."""
    df, spec = _price(spark, d)
    m = train_cdf(draw_sample(df, spec.code(), SAMPLE, 0), 64, "linear")
    return spark.createDataFrame([(round(m.top[0] * 1e6, 5), round(m.top[2], 6))], "slope_e6 double, intercept double")


_LEAF = f"""{_ROOT}, p AS (SELECT greatest(0, least(15, floor((a * (code - m) + b) * 16)))::INTEGER AS leaf, code - m AS x, y FROM t, (SELECT a, b, m FROM r))
SELECT leaf, count(*) AS n, round(greatest(0, coalesce(regr_slope(y, x), 0)) * 1e6, 3) AS slope_e6, round(max(y), 6) AS hi FROM p GROUP BY leaf"""
query("leaf_fit", _LEAF)(lambda s, d: train_cdf_sql(_sys(s, d), 16).select("leaf", "n", F.round(F.col("slope") * 1e6, 3).alias("slope_e6"), F.round("hi", 6).alias("hi")))


def _model(spark, d, leaves=64, root="linear"):
    df, spec = _price(spark, d)
    return df, spec, train_cdf(draw_sample(df, spec.code(), SAMPLE, 0), leaves, root)


_PRICE_MODEL = model_sql("lineitem", "l_extendedprice", "l_orderkey % 10 = 0", 16)
_EVENT_MODEL = model_sql("events", "value", "event_id % 10 = 0", 16)
_TENTH = SampleSpec(method="systematic", pk="event_id", every=10)


@query("cdf_error_price", f"{_PRICE_MODEL} SELECT round(max(e), 7) AS max, round(avg(e), 7) AS mean, round(sqrt(avg(e * e)), 7) AS rms FROM (SELECT abs(y - cume_dist() OVER (ORDER BY code)) AS e FROM predicted)")
def _cdf_error(spark, d):
    df, spec, m = _model(spark, d)
    return metrics.cdf_error(m, df, spec.code()).select(*[F.round(c, 7).alias(c) for c in ("max", "mean", "rms")])


@query("predict_pid_counts", f"{_PRICE_MODEL} SELECT pid, count(*) AS n FROM predicted GROUP BY pid")
def _pid_counts(spark, d):
    df, spec, m = _model(spark, d)
    return df.groupBy(m.pid(spec.code(), 16).alias("pid")).agg(F.count("*").alias("n"))


@query("predict_udf_agrees", "SELECT count(*) AS n, 0::BIGINT AS differ FROM lineitem")
def _udf_agrees(spark, d):
    """The vector function and the expression give the same slice."""
    df, spec, m = _model(spark, d)
    both = df.select(m.pid(spec.code(), 16).alias("a"), udf.predict_udf(m, 16)(spec.code()).alias("b"))
    return both.agg(F.count("*").alias("n"), F.sum((F.col("a") != F.col("b")).cast("long")).alias("differ"))


_LOHI = "(SELECT min(value) AS lo, max(value) AS hi FROM events)"
_RAD = f"least(15, floor((value - lo) / (hi - lo) * 16))::INTEGER"
_STATS = "count(*) AS slices, min(n)::BIGINT AS \"min\", max(n)::BIGINT AS \"max\", avg(n) AS mean, round(var_pop(n), 3) AS var, round(stddev_pop(n) / avg(n), 6) AS cv, round(max(n) / avg(n), 6) AS max_over_mean, count(*) FILTER (n = 0) AS \"empty\""


def _stats(df: DataFrame) -> DataFrame:
    return df.select("slices", "min", "max", "mean", F.round("var", 3).alias("var"), F.round("cv", 6).alias("cv"), F.round("max_over_mean", 6).alias("max_over_mean"), "empty")


def _radix(spark, d):
    df = table(spark, d, "events").select("event_id", "value")
    spec = K.resolve(df, K.Order("value"))
    seen = K.profile(df, spec)
    return df, radix_pid(spec.code(), seen["low"], seen["high"], 16)


@query("radix_pid_counts", f"SELECT {_RAD} AS pid, count(*) AS n FROM events, {_LOHI} GROUP BY 1")
def _radix_counts(spark, d):
    df, pid = _radix(spark, d)
    return df.groupBy(pid.alias("pid")).agg(F.count("*").alias("n"))


query("exact_pid_counts", "SELECT pid, count(*) AS n FROM (SELECT (ntile(16) OVER (ORDER BY value, event_id) - 1)::INTEGER AS pid FROM events) GROUP BY pid")(
    lambda s, d: exact_pid(table(s, d, "events").select("value"), F.col("value"), 16).groupBy("pid").agg(F.count("*").alias("n"))
)
query("slice_stats_radix", f"SELECT {_STATS} FROM (SELECT coalesce(n, 0)::DOUBLE AS n FROM range(16) t(p) LEFT JOIN (SELECT {_RAD} AS pid, count(*) AS n FROM events, {_LOHI} GROUP BY 1) ON p = pid)")(
    lambda s, d: _stats(metrics.slice_stats(*_radix(s, d), 16))
)
query("slice_stats_exact", f"SELECT {_STATS} FROM (SELECT count(*)::DOUBLE AS n FROM (SELECT ntile(16) OVER (ORDER BY value) AS pid FROM events) GROUP BY pid)")(
    lambda s, d: _stats(metrics.slice_stats(exact_pid(table(s, d, "events").select("value"), F.col("value"), 16), "pid", 16))
)


@query("slice_stats_model", f"{_EVENT_MODEL} SELECT {_STATS} FROM (SELECT count(pid)::DOUBLE AS n FROM range(16) t(p) LEFT JOIN predicted ON p = pid GROUP BY p)")
def _stats_model(spark, d):
    sf = model_sort(table(spark, d, "events").select("value", "event_id"), ["value"], f=16, sample=_TENTH)
    return _stats(metrics.slice_stats(sf.sliced, PID, 16))


def _event_sample(spark, d):
    df = table(spark, d, "events").select("event_id", "value")
    return df, draw_sample(df, F.col("value"), _TENTH, 0)


_SPLIT = "WITH s AS (SELECT value, row_number() OVER (ORDER BY value) - 1 AS k, count(*) OVER () AS n FROM events WHERE event_id % 10 = 0), c AS (SELECT DISTINCT value AS cut FROM s WHERE k IN (SELECT least(n - 1, i * n // 16) FROM range(1, 16) t(i)))"


@query("quantile_pid_counts", f"{_SPLIT} SELECT pid, count(*) AS n FROM (SELECT (SELECT count(*) FROM c WHERE cut <= e.value)::INTEGER AS pid FROM events e) GROUP BY pid")
def _quantile_counts(spark, d):
    """Splitters at a sample's quantiles."""
    df, sample = _event_sample(spark, d)
    return df.groupBy(quantile_pid(F.col("value"), sample, 16).alias("pid")).agg(F.count("*").alias("n"))


@query("sketch_pid_counts", "SELECT 16 AS slices, true AS even FROM events LIMIT 1")
def _sketch_counts(spark, d):
    """Splitters from an approximate percentile of all rows: every slice within a tenth of its share."""
    df = table(spark, d, "events").select("value")
    n = df.groupBy(sketch_pid(df, F.col("value"), 16).alias("pid")).agg(F.count("*").alias("n"))
    return n.agg(F.count("*").cast("int").alias("slices"), (F.max("n") <= 1.1 * F.avg("n")).alias("even"))


@query("hash_pid_counts", "SELECT 16 AS slices, count(*) AS rows, true AS whole FROM events")
def _hash_counts(spark, d):
    """Slices by hash: no row is lost and no slice holds twice its share, whatever the key's skew."""
    df = table(spark, d, "events").select("event_id")
    n = df.groupBy(hash_pid(F.col("event_id"), 16).alias("pid")).agg(F.count("*").alias("n"))
    return n.agg(F.count("*").cast("int").alias("slices"), F.sum("n").alias("rows"), (F.max("n") <= 2 * F.avg("n")).alias("whole"))


query("radix_bits_pid_counts", "SELECT ascii(url) >> 4 AS pid, count(*) AS n FROM pages GROUP BY 1")(
    lambda s, d: table(s, d, "pages").groupBy(radix_bits_pid(K.byte_code(F.col("url")), 56, 4).alias("pid")).agg(F.count("*").alias("n"))
)

_BIN = "greatest(0, least(999, floor((l_extendedprice - lo) / (hi - lo) * 1000)))::INTEGER"
_HIST = f"SELECT {_BIN} AS bin, count(*) AS n FROM lineitem, (SELECT min(l_extendedprice) AS lo, max(l_extendedprice) AS hi FROM lineitem) GROUP BY 1"
query("bin_histogram_1000", f"SELECT bin, n, n / sum(n) OVER () AS frequency FROM ({_HIST})")(lambda s, d: metrics.equi_width_histogram(table(s, d, "lineitem"), "l_extendedprice"))
query("bin_skew", f"SELECT round(sqrt(sum(n::DOUBLE * n) / 1000 - (sum(n) / 1000) ** 2) / (sum(n) / 1000) * 100, 6) AS deviation_percent, round(max(n) / (sum(n) / 1000), 6) AS max_over_mean, count(*) AS filled FROM ({_HIST})")(
    lambda s, d: metrics.bin_skew(metrics.equi_width_histogram(table(s, d, "lineitem"), "l_extendedprice")).select(F.round("deviation_percent", 6).alias("deviation_percent"), F.round("max_over_mean", 6).alias("max_over_mean"), "filled")
)


@query("invariant_violations", "SELECT 0::BIGINT AS violations")
def _invariant(spark, d):
    """Key order implies slice order, whole keys compared, over documents."""
    sf = model_sort(table(spark, d, "documents").select("text"), ["text"], f=16)
    return invariant_violations(sf.sliced, F.col("text"))


@query("write_offsets", f"{_EVENT_MODEL}, n AS (SELECT p::INTEGER AS pid, count(pid) AS rows FROM range(16) t(p) LEFT JOIN predicted ON p = pid GROUP BY p) SELECT pid, rows, coalesce(sum(rows) OVER (ORDER BY pid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS row_offset FROM n")
def _offsets(spark, d):
    """Where each slice of the model begins in the whole."""
    sf = model_sort(table(spark, d, "events").select("event_id", "value"), ["value"], f=16, sample=_TENTH)
    return sf.offsets_frame().withColumnRenamed(PID, "pid")


@query("fragment_matrix", f"{_EVENT_MODEL} SELECT pid, count(*) AS rows FROM predicted GROUP BY pid")
def _fragments(spark, d):
    """Rows of every reader by slice, summed over readers."""
    sf = model_sort(table(spark, d, "events").select("event_id", "value"), ["value"], f=16, sample=_TENTH)
    return fragment_matrix(sf.sliced, F.col(PID)).groupBy("pid").agg(F.sum("rows").alias("rows"))




@query("concurrent_slices", f"""{_EVENT_MODEL}, n AS (SELECT p::INTEGER AS pid, count(pid) AS rows FROM range(16) t(p) LEFT JOIN predicted ON p = pid GROUP BY p), memory AS (SELECT (SELECT count(*) FROM events) // 3 AS m)
SELECT 'prefix' AS mode, greatest(1, count(*))::INTEGER AS s FROM (SELECT sum(rows) OVER (ORDER BY pid) AS held FROM n), memory WHERE held <= m
UNION ALL SELECT 'any_window', greatest(1, coalesce(max(k), 1))::INTEGER FROM (SELECT k, max(total) AS most FROM (SELECT k, a.pid, sum(b.rows) AS total FROM range(1, 17) t(k), n a, n b WHERE a.pid + k <= 16 AND b.pid BETWEEN a.pid AND a.pid + k - 1 GROUP BY ALL) GROUP BY k), memory WHERE most <= m""")
def _concurrent(spark, d):
    """How many consecutive slices of the model fit into a third of all rows together."""
    df = table(spark, d, "events").select("event_id", "value")
    sizes = model_sort(df, ["value"], f=16, sample=_TENTH).sizes
    return spark.createDataFrame([(m, concurrent_slices(sizes, sum(sizes) // 3, m)) for m in ("prefix", "any_window")], "mode string, s int")




@query("makespan_plan", f"""{_EVENT_MODEL.replace("WITH", "WITH RECURSIVE", 1)}, n AS (SELECT p::INTEGER AS pid, count(pid) AS rows FROM range(16) t(p) LEFT JOIN predicted ON p = pid GROUP BY p),
q AS (SELECT policy, rows, row_number() OVER (PARTITION BY policy ORDER BY CASE WHEN policy = 'given' THEN pid ELSE -rows END) AS i FROM n, (VALUES ('largest_first'), ('given')) t(policy)),
w(policy, i, a, b) AS (SELECT DISTINCT policy, 0::BIGINT, 0::BIGINT, 0::BIGINT FROM q UNION ALL SELECT w.policy, q.i, CASE WHEN a <= b THEN a + rows ELSE a END, CASE WHEN a <= b THEN b ELSE b + rows END FROM w JOIN q ON q.policy = w.policy AND q.i = w.i + 1)
SELECT policy, greatest(a, b)::BIGINT AS finish FROM w WHERE i = 16""")
def _makespan(spark, d):
    """When two workers are done with the model's slices of events, in rows."""
    sizes = model_sort(table(spark, d, "events").select("event_id", "value"), ["value"], f=16, sample=_TENTH).sizes
    return spark.createDataFrame([(p, makespan(sizes, 2, p)) for p in ("largest_first", "given")], "policy string, finish long")


def table_size(df: DataFrame) -> tuple[float, float]:
    """(rows, mean bytes of a row): eight for a value, of text its bytes."""
    text = [n for n, t in df.dtypes if t == "string"]
    r = df.agg(F.count("*"), *[F.avg(F.octet_length(c)) for c in text], *[F.count(c) for c in df.columns if c not in text]).first()
    return float(r[0]), sum(r[i + 1] or 0.0 for i in range(len(text))) + 8.0 * (len(df.columns) - len(text))


@query("plan_slices_100tb")
def _plan_100tb(spark, d):
    """Plans for lineitem as it is, and for 1 TB and 100 TB of such rows."""
    n, width = table_size(table(spark, d, "lineitem"))
    return workloads.run_plan(spark, [(n, width), (1e12 / width, width), (1e14 / width, width)])


# ---- validation --------------------------------------------------------------------------------------

query("check_sorted", "SELECT count(*) AS rows, 0::BIGINT AS gaps, 0::BIGINT AS unordered, (count(*) - count(DISTINCT (event_type, value)))::BIGINT AS dups FROM events")(
    lambda s, d: check_sorted(model_sort(table(s, d, "events").select("event_type", "value"), ["event_type", "value"], f=16).with_rn(), ["event_type", "value"])
)


@query("checksum_before_after", "SELECT count(*) AS rows, true AS same FROM lineitem")
def _checksums(spark, d):
    df = table(spark, d, "lineitem")
    a, b = checksum(df), checksum(model_sort(df, ["l_extendedprice"], f=16).plain()).toDF("r", "t", "m")
    return a.crossJoin(b).select("rows", ((F.col("rows") == F.col("r")) & (F.col("total") == F.col("t")) & (F.col("mixed") == F.col("m"))).alias("same"))


@query("validate_all", "SELECT count(*) AS rows, 0::BIGINT AS gaps, 0::BIGINT AS unordered, true AS same_rows, 0::BIGINT AS violations FROM documents")
def _validate(spark, d):
    df = table(spark, d, "documents").select("doc_id", "text")
    return validate_all(df, model_sort(df, ["text", "doc_id"], f=16)).drop("dups")


# ---- joins -------------------------------------------------------------------------------------------

def _cust_orders(spark, d):
    return table(spark, d, "customer").select("c_custkey", "c_name"), table(spark, d, "orders").select("o_orderkey", "o_custkey", "o_totalprice")


for _how, _sql in (("inner", "JOIN"), ("left", "LEFT JOIN"), ("right", "RIGHT JOIN"), ("full", "FULL JOIN")):
    query(f"merge_join_{_how}", f"SELECT c_custkey, c_name, o_orderkey, o_custkey, o_totalprice FROM customer {_sql} orders ON c_custkey = o_custkey")(
        lambda s, d, h=_how: J.model_merge_join(*_cust_orders(s, d), "c_custkey", "o_custkey", h)
    )
for _how in ("semi", "anti"):
    query(f"merge_join_{_how}", f"SELECT c_custkey, c_name FROM customer {_how.upper()} JOIN orders ON c_custkey = o_custkey")(
        lambda s, d, h=_how: J.model_merge_join(*_cust_orders(s, d), "c_custkey", "o_custkey", f"left_{h}")
    )
query("merge_join_lineitem", "SELECT l_orderkey, l_linenumber, l_partkey, l_extendedprice, o_orderdate FROM lineitem JOIN orders ON l_orderkey = o_orderkey")(
    lambda s, d: J.model_merge_join(table(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice"), table(s, d, "orders").select("o_orderkey", "o_orderdate"), "l_orderkey", "o_orderkey").drop("o_orderkey")
)
_LS = "SELECT l_orderkey, l_linenumber, l_extendedprice, s_name FROM lineitem JOIN supplier ON l_suppkey = s_suppkey"
for _name, _fn in (("broadcast_join", J.broadcast_join), ("hash_join", J.hash_join), ("builtin_merge_join", J.builtin_merge_join)):
    query(_name, _LS)(lambda s, d, f=_fn: f(table(s, d, "lineitem"), table(s, d, "supplier"), F.col("l_suppkey") == F.col("s_suppkey")).select("l_orderkey", "l_linenumber", "l_extendedprice", "s_name"))
query("theta_join", "SELECT s_suppkey, n_name FROM supplier, nation WHERE s_acctbal > n_nationkey * 400")(
    lambda s, d: J.theta_join(table(s, d, "supplier"), table(s, d, "nation"), F.col("s_acctbal") > F.col("n_nationkey") * 400).select("s_suppkey", "n_name")
)
query("range_join", "SELECT o_orderkey, o_totalprice, p_partkey, p_retailprice AS lo, p_retailprice + p_size AS hi FROM orders JOIN part ON o_totalprice BETWEEN p_retailprice AND p_retailprice + p_size")(
    lambda s, d: J.range_join(table(s, d, "orders").select("o_orderkey", "o_totalprice"), "o_totalprice", table(s, d, "part").select("p_partkey", F.col("p_retailprice").alias("lo"), (F.col("p_retailprice") + F.col("p_size")).alias("hi")), "lo", "hi")
)
query("band_join", "SELECT c_custkey, c_acctbal, s_suppkey, s_acctbal FROM customer JOIN supplier ON c_acctbal BETWEEN s_acctbal - 5 AND s_acctbal + 5")(
    lambda s, d: J.band_join(table(s, d, "customer").select("c_custkey", "c_acctbal"), "c_acctbal", table(s, d, "supplier").select("s_suppkey", "s_acctbal"), "s_acctbal", 5.0)
)
_RIGHT = "(SELECT ts AS rts, event_type AS rtype, max(event_id) AS event_id FROM events WHERE event_id % 7 = 0 GROUP BY ALL)"
_LEFT = "(SELECT event_id AS left_id, ts, event_type FROM events WHERE event_id % 7 <> 0)"


def _asof(spark, d, **kw):
    ev = table(spark, d, "events")
    right = ev.filter("event_id % 7 = 0").groupBy("ts", "event_type").agg(F.max("event_id").alias("event_id"))
    left = ev.filter("event_id % 7 <> 0").select(F.col("event_id").alias("left_id"), "ts", "event_type")
    return J.asof_join(left, right, "ts", "event_type", "event_id", f=8, **kw)


query("asof_join", f"SELECT left_id, ts, event_type, rts AS right_on, event_id AS right_event_id FROM {_LEFT} l ASOF LEFT JOIN {_RIGHT} r ON event_type = rtype AND ts >= rts")(lambda s, d: _asof(s, d))
query("asof_join_forward", f"SELECT left_id, ts, event_type, rts AS right_on, event_id AS right_event_id FROM {_LEFT} l ASOF LEFT JOIN {_RIGHT} r ON event_type = rtype AND ts <= rts")(lambda s, d: _asof(s, d, direction="forward"))
query("asof_join_tolerance", f"SELECT left_id, ts, event_type, CASE WHEN ts - rts <= INTERVAL 1 HOUR THEN rts END AS right_on, CASE WHEN ts - rts <= INTERVAL 1 HOUR THEN event_id END AS right_event_id FROM {_LEFT} l ASOF LEFT JOIN {_RIGHT} r ON event_type = rtype AND ts >= rts")(
    lambda s, d: _asof(s, d, tolerance=F.expr("interval 1 hour"))
)

# ---- groups ------------------------------------------------------------------------------------------

query("group_by_orderkey", "SELECT l_orderkey, count(*) AS n, sum(l_quantity::DECIMAL(18,2))::DECIMAL(28,2) AS qty FROM lineitem GROUP BY l_orderkey")(
    lambda s, d: A.model_group_by(table(s, d, "lineitem").select("l_orderkey", "l_quantity"), ["l_orderkey"], [F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("decimal(18,2)")).alias("qty")])
)
_DEC = "sum(l_extendedprice::DECIMAL(18,2))::DECIMAL(28,2)"
query("pricing_summary", f"SELECT l_returnflag, l_linestatus, sum(l_quantity::DECIMAL(18,2))::DECIMAL(28,2) AS qty, {_DEC} AS price, round(avg(l_discount), 6) AS disc, count(*) AS n FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02' GROUP BY ALL")(
    lambda s, d: A.hash_group_by(table(s, d, "lineitem").filter(F.col("l_shipdate") <= F.lit("1998-09-02").cast("timestamp_ntz")), ["l_returnflag", "l_linestatus"], [F.sum(F.col("l_quantity").cast("decimal(18,2)")).alias("qty"), F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).alias("price"), F.round(F.avg("l_discount"), 6).alias("disc"), F.count("*").alias("n")])
)
query("salted_group_by", "SELECT event_type, sum(user_id)::BIGINT AS user_id, count(*)::BIGINT AS n FROM events GROUP BY event_type")(lambda s, d: A.salted_group_by(table(s, d, "events").select("event_type", "user_id", "event_id"), ["event_type"], ["user_id"]))
for _name, _sql in (("rollup", "ROLLUP (l_returnflag, l_linestatus)"), ("cube", "CUBE (l_returnflag, l_linestatus)"), ("grouping_sets", "GROUPING SETS ((l_returnflag), (l_linestatus), ())")):

    @query(_name, f"SELECT l_returnflag, l_linestatus, count(*) AS n, {_DEC} AS price FROM lineitem GROUP BY {_sql}")
    def _sets(spark, d, name=_name):
        df, keys = table(spark, d, "lineitem"), ["l_returnflag", "l_linestatus"]
        aggs = [F.count("*").alias("n"), F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).alias("price")]
        if name == "grouping_sets":
            return A.grouping_sets(df, [["l_returnflag"], ["l_linestatus"], []], keys, aggs)
        return (df.rollup(*keys) if name == "rollup" else df.cube(*keys)).agg(*aggs)


query("pivot", "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS F, count(*) FILTER (o_orderstatus = 'O') AS O FROM orders GROUP BY o_orderpriority")(
    lambda s, d: table(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O"]).agg(F.count(F.lit(1))).na.fill(0, ["F", "O"])
)
query("distinct_counts", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem")(lambda s, d: table(s, d, "lineitem").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers")))
query("approx_distinct")(lambda s, d: A.approx_distinct(table(s, d, "lineitem"), "l_partkey"))
query("approx_percentiles")(lambda s, d: A.approx_percentile(table(s, d, "events"), "value", [0.1, 0.5, 0.9]))
query("listagg", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names, min_by(n_name, n_nationkey) AS low, max_by(n_name, n_nationkey) AS high FROM nation GROUP BY n_regionkey")(
    lambda s, d: table(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.sort_array(F.collect_list("n_name")), ",").alias("names"), F.min_by("n_name", "n_nationkey").alias("low"), F.max_by("n_name", "n_nationkey").alias("high"))
)
query("regr", "SELECT round(regr_slope(o_totalprice, o_custkey), 4) AS slope, round(corr(o_totalprice, o_custkey), 6) AS c, round(stddev_pop(o_totalprice), 2) AS sd, round(var_samp(o_totalprice) / 1e6, 4) AS v FROM orders")(
    lambda s, d: table(s, d, "orders").agg(F.round(F.regr_slope("o_totalprice", "o_custkey"), 4).alias("slope"), F.round(F.corr("o_totalprice", "o_custkey"), 6).alias("c"), F.round(F.stddev_pop("o_totalprice"), 2).alias("sd"), F.round(F.var_samp("o_totalprice") / 1e6, 4).alias("v"))
)
query("heavy_keys", "SELECT p_name, count(*) AS n FROM part GROUP BY p_name ORDER BY n DESC, p_name LIMIT 10")(lambda s, d: A.heavy_keys(table(s, d, "part"), "p_name", 10))

# ---- duplicates and sets -----------------------------------------------------------------------------

query("distinct_text", "SELECT DISTINCT text FROM documents")(lambda s, d: S.model_distinct(table(s, d, "documents"), ["text"]))
query("distinct_pairs", "SELECT DISTINCT l_orderkey, l_linenumber FROM lineitem")(lambda s, d: S.model_distinct(table(s, d, "lineitem"), ["l_orderkey", "l_linenumber"]))
query("dedup_keep_first", "SELECT doc_id, text, source FROM (SELECT doc_id, text, source, row_number() OVER (PARTITION BY text ORDER BY doc_id) AS k FROM documents) WHERE k = 1")(lambda s, d: S.dedup_keep_first(table(s, d, "documents").select("doc_id", "text", "source"), "text", "doc_id"))


def _two(spark, d):
    li = table(spark, d, "lineitem")
    return li.filter("l_quantity < 30").select("l_partkey", "l_suppkey"), li.filter("l_quantity > 20").select("l_partkey", "l_suppkey")


_T2 = ["SELECT l_partkey, l_suppkey FROM lineitem WHERE l_quantity < 30", "SELECT l_partkey, l_suppkey FROM lineitem WHERE l_quantity > 20"]
query("model_intersect", " INTERSECT ".join(_T2))(lambda s, d: S.model_intersect(*_two(s, d)))
query("model_except", " EXCEPT ".join(_T2))(lambda s, d: S.model_except(*_two(s, d)))
query("union_all", " UNION ALL ".join(_T2))(lambda s, d: _two(s, d)[0].unionByName(_two(s, d)[1]))
query("intersect_all", " INTERSECT ALL ".join(_T2))(lambda s, d: _two(s, d)[0].intersectAll(_two(s, d)[1]))
query("except_all", " EXCEPT ALL ".join(_T2))(lambda s, d: _two(s, d)[0].exceptAll(_two(s, d)[1]))
