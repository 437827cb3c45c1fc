"""Line dedup by site-relative frequency, in DataFrame operations only.

A line is boilerplate of a host when more than `max_ratio` of the host's pages contain it, and at
least `min_pages` do. Those lines are dropped from all pages of that host; the same line stays on
other hosts. Lines compare trimmed of spaces; blank lines are never boilerplate and stay.

The ratio lies between what is counted of boilerplate and of other repeated lines: on the given tables (sf0.1) the one frequent
notice is on 10.6 % of the documents, 8 % or more of each source's, and the next line on 5 % of a source's at most. `min_pages` keeps the few pages of a
small host, each of whose lines exceeds any ratio by itself; it is a departure from the ratio alone.

Scale: each page contributes a line once (in-row distinct), counts are combined before the shuffle by
(host, line digest), so neither a hot host nor a hot line gathers rows anywhere. A host has at most
(distinct lines a page) / max_ratio boilerplate lines; the table of them is counted and broadcast when
it keeps within `broadcast_rows`, else joined on (host, salt) with the hot side spread over salts.

Nulls: a null text stays null with no lines; null hosts form one host. Very long texts and lines are judged whole, lines by their
digests. Ties: a line exactly at the ratio stays. Repeated rows are pages of their own. Empty tables give empty results. Columns
named n_lines or n_dropped are replaced; others cannot clash, as the input's columns are renamed while it works.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import broadcast_if_small, materialize, shield


def _lines(text: Column) -> Column:
    return F.split(text, "\n")


def _digest(line: Column) -> Column:
    return F.unhex(F.md5(F.trim(line)))


def boilerplate_lines(df: DataFrame, host: Column, *, text: str = "text", max_ratio: float = 0.07, min_pages: int = 5) -> DataFrame:
    """(host_key, digests): the boilerplate lines' digests of each host that has any."""
    keyed = df.select(F.coalesce(F.concat(F.lit("1"), host), F.lit("0")).alias("host_key"), F.col(text).alias("body"))
    pages = keyed.groupBy("host_key").agg(F.count("*").alias("pages"))
    held = keyed.select("host_key", F.explode(F.array_distinct(F.transform(F.filter(_lines(F.col("body")), lambda x: F.trim(x) != ""), _digest))).alias("line"))
    counts = held.groupBy("host_key", "line").agg(F.count("*").alias("n")).filter(F.col("n") >= min_pages)
    common = counts.join(pages, "host_key").filter(F.col("n") > F.lit(max_ratio) * F.col("pages"))
    return common.groupBy("host_key").agg(F.collect_list("line").alias("digests"))


def drop_boilerplate(
    df: DataFrame, host: str = "source", *, text: str = "text", max_ratio: float = 0.07, min_pages: int = 5, broadcast_rows: int = 100_000, salts: int = 32,
) -> DataFrame:
    """df with text cleaned, n_lines and n_dropped added. host: the column that names the site."""
    df = df.drop("n_lines", "n_dropped")
    inner, names, restore = shield(df)
    site, body = F.col(names[host]), F.col(names[text])
    known = materialize(boilerplate_lines(inner, site, text=names[text], max_ratio=max_ratio, min_pages=min_pages), "lines")
    keyed = inner.withColumn("_host", F.coalesce(F.concat(F.lit("1"), site), F.lit("0")))
    known, small = broadcast_if_small(known, broadcast_rows)
    if small:
        joined = keyed.join(known, keyed["_host"] == known["host_key"], "left")
    else:
        salted = known.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
        keyed = keyed.withColumn("_salt0", F.pmod(F.xxhash64(body), F.lit(salts)).cast("int"))
        joined = keyed.join(salted, (keyed["_host"] == salted["host_key"]) & (keyed["_salt0"] == salted["_salt"]), "left")
    lines = F.coalesce(_lines(body), F.array().cast("array<string>"))
    kept = F.when(F.col("digests").isNull(), lines).otherwise(F.filter(lines, lambda x: (F.trim(x) == "") | ~F.array_contains(F.col("digests"), _digest(x))))
    out = joined.withColumns({"_all": lines, "_kept": kept})
    cleaned = F.when(body.isNotNull(), F.array_join("_kept", "\n"))
    out = out.withColumns({"n_lines": F.size("_all"), "n_dropped": F.size("_all") - F.size("_kept")}).withColumn(names[text], cleaned)
    return restore(out, "n_lines", "n_dropped")


def host_of(url: Column) -> Column:
    """The host part of a URL, lower case; null where there is none."""
    found = F.lower(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/@]*@)?([^/:?#]+)", 1))
    return F.when(found != "", found)


def op7_query(spark, sf_dir: str) -> DataFrame:
    """Every document without its source's boilerplate lines."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "source")
    return drop_boilerplate(docs, "source").select("doc_id", "source", "text", "n_lines", "n_dropped")


def pages_query(spark, sf_dir: str) -> DataFrame:
    """Every page's source text without the lines that its host repeats, the host taken from the URL."""
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", host_of(F.col("url")).alias("host"), F.col("html").alias("text"))
    return drop_boilerplate(pages, "host").select("page_id", "host", "text", "n_lines", "n_dropped")


def _sql(rows: str, key: str, host: str) -> str:
    """The same over rows (a table or subquery with key, host and text)."""
    return rf"""
WITH held AS (SELECT row_number() OVER () AS rid, * FROM {rows}),
lines AS (
  SELECT rid, {key}, {host}, pos, line, trim(line, ' ') AS bare FROM (
    SELECT rid, {key}, {host}, unnest(string_split(text, chr(10))) AS line, unnest(range(len(string_split(text, chr(10))))) AS pos FROM held)),
pages AS (SELECT {host}, count(*) AS pages FROM held GROUP BY {host}),
common AS (
  SELECT l.{host}, l.bare FROM (SELECT {host}, bare, count(DISTINCT rid) AS n FROM lines WHERE bare <> '' GROUP BY ALL) l
  JOIN pages p ON l.{host} IS NOT DISTINCT FROM p.{host} WHERE l.n >= 5 AND l.n > 0.07::DOUBLE * p.pages),
marked AS (SELECT l.*, c.bare IS NOT NULL AS bad FROM lines l LEFT JOIN common c ON l.{host} IS NOT DISTINCT FROM c.{host} AND l.bare = c.bare)
SELECT {key}, {host}, coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT bad), '') AS text,
       count(*)::INTEGER AS n_lines, count(*) FILTER (bad)::INTEGER AS n_dropped
FROM marked GROUP BY rid, {key}, {host}
UNION ALL SELECT {key}, {host}, NULL, 0, 0 FROM held WHERE text IS NULL
"""


OP7_SQL = _sql("documents", "doc_id", "source")
_HOST = "nullif(regexp_extract(lower(url), '^[a-z][a-z0-9+.-]*://(?:[^/@]*@)?([^/:?#]+)', 1), '')"
PAGES_SQL = _sql(f"(SELECT page_id, {_HOST} AS host, html AS text FROM pages) q", "page_id", "host")
