"""Semirings of the engine."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Semiring:
    """``times`` joins weights, ``plus`` sums them out; ``divide`` is None where there is no inverse."""

    name: str
    times: Callable[[Column, Column], Column]
    plus: Callable[[Column], Column]
    one: object
    divide: Callable[[Column, Column], Column] | None = None
    whole: Callable[[Column, Column], Column] | None = None  # division of integers that leaves no remainder
    keep: Callable[[Column], Column] | None = None  # which weights are not the zero


SUM_PRODUCT = Semiring("sum_product", lambda a, b: a * b, F.sum, 1, lambda a, b: a / b, lambda a, b: F.call_function("div", a, b), lambda w: w > 0)
MAX_PRODUCT = Semiring("max_product", lambda a, b: a * b, F.max, 1, keep=lambda w: w > 0)
MIN_SUM = Semiring("min_sum", lambda a, b: a + b, F.min, 0, lambda a, b: a - b, keep=lambda w: w.isNotNull())
BOOLEAN = Semiring("boolean", lambda a, b: F.least(a, b), F.max, 1, keep=lambda w: w > 0)
ALL = {s.name: s for s in (SUM_PRODUCT, MAX_PRODUCT, MIN_SUM, BOOLEAN)}
