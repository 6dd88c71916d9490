"""Column helpers: null-safe arithmetic, vectors in arrays, features of text, dates and JSON."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def first_non_null(*cols: Column) -> Column:
    return F.coalesce(*cols)


def safe_div(a: Column, b: Column) -> Column:
    """Null where the divisor is zero."""
    return F.try_divide(a, b)


def safe_cast(c: Column, kind: str) -> Column:
    """Null where the value has no such form."""
    return c.try_cast(kind)


def choose(cases: list[tuple[Column, Column]], otherwise: Column) -> Column:
    """The value of the first case that holds."""
    return F.coalesce(*[F.when(test, value) for test, value in cases], otherwise)


def math_features(c: Column) -> dict[str, Column]:
    return {"log1p": F.log1p(F.abs(c)), "sqrt": F.sqrt(F.abs(c)), "square": F.pow(c, F.lit(2)), "sign": F.signum(c), "rounded": F.bround(c, 2)}


def pack(names: list[str]) -> Column:
    """Columns as one struct, which sorts and aggregates as a whole."""
    return F.struct(*names)


def bucket(c: Column, m: int) -> Column:
    return F.pmod(F.xxhash64(c), F.lit(m))


def money(c: Column) -> Column:
    return c.cast("decimal(18,4)")


def json_field(c: Column, path: str, kind: str) -> Column:
    return F.get_json_object(c, path).cast(kind)


def vec_dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, v: s + v)


def vec_norm(a: Column) -> Column:
    return F.sqrt(vec_dot(a, a))


def vec_argmax(a: Column) -> Column:
    """Place of the first largest element, from 0."""
    return F.array_position(a, F.array_max(a)) - 1


def sparse_map(names: list[str]) -> Column:
    """Columns other than zero as a map from name to value."""
    keys = F.array(*map(F.lit, names))
    return F.map_filter(F.map_from_arrays(keys, F.array(*[F.col(n).cast("double") for n in names])), lambda _, v: v != 0)


def text_features(c: Column) -> dict[str, Column]:
    return {
        "n_chars": F.char_length(c), "n_words": F.size(F.split(F.trim(c), "\\s+")), "n_digits": F.regexp_count(c, F.lit("[0-9]")),
        "head": F.substring(c, 1, 3), "upper": F.upper(F.substring(c, 1, 3)),
    }


def date_features(c: Column) -> dict[str, Column]:
    return {"year": F.year(c), "quarter": F.quarter(c), "month": F.month(c), "day": F.dayofmonth(c), "month_start": F.date_trunc("month", c).cast("date")}
