"""Semirings as builders of column expressions: an aggregate and a binary product."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Semiring:
    """add: an aggregate of products; times: of two values; sql_add, sql_times: the same as SQL text
    with {x}, {a} and {b}. again combines partial results (count's partials are summed)."""

    name: str
    add: Callable[[Column], Column]
    times: Callable[[Column, Column], Column]
    sql_add: str
    sql_times: str
    again: Callable[[Column], Column] | None = None

    def merge(self, partial: Column) -> Column:
        return (self.again or self.add)(partial)


_one = lambda a, b: F.lit(1).cast("bigint")

PLUS_TIMES = Semiring("plus_times", F.sum, lambda a, b: a * b, "CAST(SUM({x}) AS BIGINT)", "{a} * {b}")
MIN_PLUS = Semiring("min_plus", F.min, lambda a, b: a + b, "MIN({x})", "{a} + {b}")
MAX_MIN = Semiring("max_min", F.max, F.least, "MAX({x})", "LEAST({a}, {b})")
OR_AND = Semiring("or_and", F.bool_or, lambda a, b: a & b, "BOOL_OR({x})", "({a} AND {b})")
MIN_SECOND = Semiring("min_second", F.min, lambda a, b: b, "MIN({x})", "{b}")
MIN_FIRST = Semiring("min_first", F.min, lambda a, b: a, "MIN({x})", "{a}")
MAX_SECOND = Semiring("max_second", F.max, lambda a, b: b, "MAX({x})", "{b}")
ANY_PAIR = Semiring("any_pair", F.max, _one, "MAX({x})", "CAST(1 AS BIGINT)")
PLUS_PAIR = Semiring("plus_pair", F.sum, _one, "CAST(SUM({x}) AS BIGINT)", "CAST(1 AS BIGINT)")
PLUS_SECOND = Semiring("plus_second", F.sum, lambda a, b: b, "CAST(SUM({x}) AS BIGINT)", "{b}")
MAX_TIMES = Semiring("max_times", F.max, lambda a, b: a * b, "MAX({x})", "{a} * {b}")

SEMIRINGS = {s.name: s for s in (PLUS_TIMES, MIN_PLUS, MAX_MIN, OR_AND, MIN_SECOND, MIN_FIRST, MAX_SECOND, ANY_PAIR, PLUS_PAIR, PLUS_SECOND, MAX_TIMES)}
