"""The joins over whole tables against brute force."""

import pytest

from equidepth import queries


def test_range_join_takes_every_part(spark):
    data = "/root/testdata/sf0.01"  # prices meet intervals there
    points = spark.read.parquet(f"{data}/orders.parquet").select("o_orderkey", "o_totalprice").toPandas()
    parts = spark.read.parquet(f"{data}/part.parquet").selectExpr("p_partkey", "p_retailprice AS lo", "p_retailprice + p_size AS hi").collect()
    price, keys = points["o_totalprice"].to_numpy(), points["o_orderkey"].to_numpy()
    want = sorted((o, p) for p, lo, hi in parts for o in keys[(price >= lo) & (price <= hi)].tolist())
    assert any(p % 20 for _, p in want)
    assert sorted((r["o_orderkey"], r["p_partkey"]) for r in queries.QUERIES["range_join"](spark, data).collect()) == want


@pytest.mark.parametrize("how", ["inner", "left", "right", "full", "semi", "anti"])
def test_merge_join_takes_every_row(spark, data, how):
    names = {r[0] for r in spark.read.parquet(f"{data}/customer.parquet").select("c_custkey").collect()}
    orders = spark.read.parquet(f"{data}/orders.parquet").select("o_custkey", "o_orderkey").collect()
    buyers = {c for c, _ in orders}
    want = [(c, o) for c, o in orders if c in names]
    want += [(c, None) for c in names - buyers] if how in ("left", "full") else []
    want += [(None, o) for c, o in orders if c not in names] if how in ("right", "full") else []
    got = queries.QUERIES[f"merge_join_{how}"](spark, data).collect()
    if how in ("semi", "anti"):
        assert sorted(r["c_custkey"] for r in got) == sorted(names & buyers if how == "semi" else names - buyers)
    else:
        assert sorted(map(repr, want)) == sorted(repr((r["c_custkey"], r["o_orderkey"])) for r in got)
