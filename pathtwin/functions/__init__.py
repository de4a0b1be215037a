"""Column helpers."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of ``value``, which is worked out once even where ``body`` uses it inside lambdas."""
    return F.transform(F.array(value), body)[0]


def windows(items: Column, size: int, sep: str = "\x01") -> Column:
    """Texts of ``size`` consecutive items; empty for shorter arrays."""
    whole = lambda s: F.transform(F.sequence(F.lit(0), F.size(s) - size), lambda i: F.concat_ws(sep, *[F.get(s, i + k) for k in range(size)]))
    return F.when(F.size(items) < size, F.array().cast("array<string>")).otherwise(let(items, whole))
