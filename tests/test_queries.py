"""Every query with SQL must agree with DuckDB on the smallest tables; the others must run."""

import duckdb
import pytest

from equidepth import queries_more as Q

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
HEAVY = {n for n in Q.QUERIES if n.startswith(("w0", "w1"))}


@pytest.fixture(scope="module")
def duck(data):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{data}/{t}.parquet')")
    return c


def rows_of(names, rows):
    at = [names.index(n) for n in sorted(names)]
    return sorted(repr(tuple(r[i] for i in at)) for r in rows)


@pytest.mark.parametrize("name", sorted(Q.ORACLE_SQL))
def test_agrees_with_sql(spark, data, duck, name):
    df = Q.QUERIES[name](spark, data)
    got = rows_of(df.columns, [tuple(r) for r in df.collect()])
    cur = duck.execute(Q.ORACLE_SQL[name])
    assert got == rows_of([d[0] for d in cur.description], cur.fetchall())


@pytest.mark.parametrize("name", sorted(set(Q.QUERIES) - set(Q.ORACLE_SQL) - HEAVY))
def test_runs(spark, data, name):
    assert Q.QUERIES[name](spark, data).count() > 0
