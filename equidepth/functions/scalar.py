"""Scalar functions over the given tables' columns: Catalyst built-ins, by group."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..plans.keys import ascii_code, byte_code, common_prefix_len  # noqa: F401  (part of this surface)


def string_functions(c: Column) -> dict[str, Column]:
    return {
        "len": F.length(c), "bytes": F.octet_length(c), "up": F.upper(c), "low": F.lower(c), "head": F.substring(c, 1, 4), "padded": F.lpad(c, 20, "*"), "joined": F.concat_ws("-", c, c),
        "part": F.split_part(c, F.lit(" "), F.lit(1)), "digits": F.regexp_extract(c, "([0-9]+)", 1), "masked": F.regexp_replace(c, "[aeiou]", "_"), "at": F.instr(c, "a"), "swapped": F.translate(c, "abc", "xyz"),
        "turned": F.reverse(c), "first_code": F.ascii(c), "hexed": F.hex(c), "distance": F.levenshtein(c, F.lit("green")), "trimmed": F.trim(F.concat(F.lit(" "), c, F.lit(" "))),
    }


def date_functions(c: Column) -> dict[str, Column]:
    return {
        "y": F.year(c), "q": F.quarter(c), "m": F.month(c), "d": F.dayofmonth(c), "doy": F.dayofyear(c), "month_start": F.to_date(F.date_trunc("month", c)), "plus10": F.date_add(F.to_date(c), 10),
        "days": F.datediff(F.to_date(c), F.lit("1992-01-01").cast("date")), "month_end": F.last_day(F.to_date(c)), "next_month": F.to_date(F.add_months(F.to_date(c), 1)), "text": F.date_format(c, "yyyy-MM-dd"),
        "micros": F.unix_micros(c.cast("timestamp")),
    }


def math_functions(c: Column) -> dict[str, Column]:
    return {
        "fl": F.floor(c), "ce": F.ceil(c), "r1": F.round(c, 1), "ab": F.abs(c), "sg": F.signum(c).cast("int"), "sq": F.round(F.sqrt(F.abs(c)), 6), "ln1": F.round(F.log(F.abs(c) + 1), 6), "ex": F.round(F.exp(-F.abs(c) / 10000), 6),
        "gr": F.greatest(c, F.lit(0.0)), "le": F.least(c, F.lit(0.0)), "pm": F.pmod(F.floor(c), F.lit(7)).cast("long"), "bucket": F.width_bucket(c, F.lit(-1000.0), F.lit(10000.0), F.lit(11)), "shifted": F.shiftright(F.floor(F.abs(c)).cast("long"), 3),
    }


def array_functions(words: Column) -> dict[str, Column]:
    return {
        "n": F.size(words), "first": F.element_at(words, 1), "uniq": F.size(F.array_distinct(words)), "longest": F.array_max(F.transform(words, lambda x: F.length(x))), "ordered": F.array_join(F.slice(F.sort_array(words), 1, 3), ","),
        "chars": F.aggregate(F.transform(words, lambda x: F.length(x)), F.lit(0), lambda a, x: a + x), "short": F.size(F.filter(words, lambda x: F.length(x) < 4)), "has_the": F.exists(words, lambda x: x == "the"),
    }


def vector_norm(v: Column) -> Column:
    """Euclidean length of an array<float>."""
    return F.sqrt(F.aggregate(F.transform(v, lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x))


def json_functions(props: Column) -> dict[str, Column]:
    return {"k": F.get_json_object(props, "$.k").cast("long"), "parsed": F.from_json(props, "k long")["k"], "again": F.to_json(F.from_json(props, "k long")), "crc": F.crc32(props.cast("binary")), "digest": F.md5(props)}
