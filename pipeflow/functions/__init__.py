"""Scalar functions by group, as dictionaries of named columns: all built-in, all inside generated code."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def string_columns(name: Column) -> dict[str, Column]:
    return {
        "up": F.upper(name), "low": F.lower(F.trim(name)), "head": F.substring(name, 1, 4), "swapped": F.replace(name, F.lit("a"), F.lit("o")),
        "first_word": F.regexp_extract(name, r"^([A-Za-z]+)", 1), "no_digits": F.regexp_replace(name, r"[0-9]+", "#"), "parts": F.size(F.split(name, " ")).cast("long"),
        "joined": F.concat_ws("-", name, F.lit("x")), "n": F.length(name).cast("long"), "at": F.instr(name, "e").cast("long"), "padded": F.lpad(F.length(name).cast("string"), 5, "0"), "moved": F.translate(name, "abc", "xyz"), "back": F.reverse(name),
    }


def date_columns(t: Column) -> dict[str, Column]:
    return {
        "y": F.year(t).cast("long"), "m": F.month(t).cast("long"), "month_start": F.date_format(F.date_trunc("month", t), "yyyy-MM-dd"), "days": F.datediff(t.cast("date"), F.lit("1990-01-01").cast("date")).cast("long"),
        "later": F.date_format(F.add_months(t.cast("date"), 2), "yyyy-MM-dd"), "last": F.date_format(F.last_day(t.cast("date")), "yyyy-MM-dd"), "day": F.date_format(t, "yyyy/MM/dd"), "next": F.date_format(F.date_add(t.cast("date"), 1), "yyyy-MM-dd"),
    }


def math_columns(x: Column, k: Column) -> dict[str, Column]:
    return {
        "down": F.floor(x).cast("long"), "up": F.ceil(x).cast("long"), "rooted": F.round(F.sqrt(x), 6), "logged": F.round(F.log(x + 1), 6), "squared": F.round(F.pow(x, 2), 4), "size": F.abs(x - 25), "side": F.signum(x - 25),
        "rest": F.pmod(k, F.lit(7)), "most": F.greatest(x, F.lit(10.0)), "least": F.least(x, F.lit(10.0)), "bits": k.bitwiseAND(F.lit(15)),
    }


def trig_columns(a: Column) -> dict[str, Column]:
    r = F.radians(a)
    return {n: F.round(c, 6) for n, c in {"s": F.sin(r), "c": F.cos(r), "t": F.tan(r / 4), "as_": F.asin(F.sin(r) / 2), "ac": F.acos(F.cos(r) / 2), "at": F.atan2(F.sin(r), F.cos(r) + 2), "deg": F.degrees(r / 3)}.items()}


def array_columns(v: Column) -> dict[str, Column]:
    d = F.transform(v, lambda x: x.cast("double"))
    return {
        "n": F.size(v).cast("long"), "first": F.element_at(d, 1), "positive": F.size(F.filter(d, lambda x: x > 0)).cast("long"), "total": F.round(F.aggregate(d, F.lit(0.0), lambda a, x: a + x), 6), "any_large": F.exists(d, lambda x: x > 0.5),
        "low": F.element_at(F.array_sort(d), 1), "tail": F.size(F.slice(d, 60, 5)).cast("long"), "dot": F.round(F.aggregate(F.zip_with(d, F.reverse(d), lambda a, b: a * b), F.lit(0.0), lambda a, x: a + x), 6),
    }
