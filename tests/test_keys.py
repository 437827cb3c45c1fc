import math

import pytest
from pyspark.sql import functions as F

from equidepth.plans import keys as K


def codes(spark, values, code):
    rows = spark.createDataFrame([(v,) for v in values], "k string").select("k", code.alias("c")).collect()
    return {r["k"]: r["c"] for r in rows}


def test_fixed_code_hand_values(spark):
    one = codes(spark, [" ", "~"], K.ascii_code(F.col("k"), 1))
    assert one == {" ": 0, "~": 94}
    assert codes(spark, ["!!"], K.ascii_code(F.col("k"), 2)) == {"!!": 96}
    assert codes(spark, ["~" * 9], K.ascii_code(F.col("k"), 9)) == {"~" * 9: 95**9 - 1}


def test_capacity_by_both_sums():
    nine, ten = K.code_capacity(9), K.code_capacity(10)
    assert round(nine["bits_by_sum"], 2) == 59.14 and round(ten["bits_by_sum"], 2) == 65.71
    assert nine["fits"] and not ten["fits"] and K.widest() == 9
    assert nine["bits"] == pytest.approx(math.log2(95**9 - 1))


def test_variable_code_keeps_order_where_the_literal_pad_breaks_it(spark):
    words = sorted(["", "a", "a ", "a~", "ab", "b", "b "])
    low = codes(spark, words, K.ascii_code(F.col("k"), 2, variable=True))
    assert [low[w] for w in words] == sorted(low.values()) and len(set(low.values())) == len(words)
    paper = codes(spark, words, K.ascii_code(F.col("k"), 2, variable=True, pad="paper"))
    assert paper["b"] < paper["a~"]


def test_byte_code_of_any_text(spark):
    words = ["", "\n", "\t", "a", "a\x7f", "é", "漢", "😀", "zz"]
    got = codes(spark, words, K.byte_code(F.col("k")))
    ordered = sorted(words, key=lambda w: w.encode())
    assert [got[w] for w in ordered] == sorted(got.values())
    assert got[""] == 0
    assert codes(spark, [None], K.byte_code(F.col("k"))) == {None: None}


def test_common_prefix(spark, data):
    assert K.common_prefix_len(spark.read.parquet(f"{data}/customer.parquet"), "c_name") >= 9
    assert K.common_prefix_len(spark.createDataFrame([], "k string"), "k") == 0


def test_number_codes_rise_with_the_order(spark):
    values = [float("-inf"), -1e300, -1.0, -0.0, 0.0, 5e-324, 1.0, 1e300, float("inf"), float("nan")]
    spec = K.KeySpec(K.Order("v"), "double")
    df = spark.createDataFrame([(i, v) for i, v in enumerate(values)], "i int, v double").select("i", spec.code().alias("c")).orderBy("i")
    got = [r["c"] for r in df.collect()]
    assert got == sorted(got) and all(abs(x) <= 1e150 for x in got)
