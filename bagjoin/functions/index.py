"""Mixed-radix indices of code tuples (M15): one integer per row, JVM arithmetic only."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


class IndexWidthError(ValueError):
    """The product of the domain sizes does not fit the index type."""


def index_bits(sizes: list[int]) -> float:
    """log2 of the number of cells (C17)."""
    return sum(math.log2(max(1, s)) for s in sizes)


def check_width(sizes: list[int], wide: bool = False) -> str:
    """Type of an index over ``sizes``: bigint, or decimal(38,0) if ``wide`` allows it."""
    cells = math.prod(sizes)
    if cells <= 2**63 - 1:
        return "bigint"
    if wide and cells < 10**38:
        return "decimal(38,0)"
    raise IndexWidthError(f"{cells} cells need more than 63 bits; keep the columns or pass wide=True")


def _weighted(cols: list, sizes: list[int], factors: list[int], wide: bool) -> Column:
    kind = check_width(sizes, wide)
    out = F.lit(0).cast(kind)
    for c, f in zip(cols, factors):
        c = F.col(c) if isinstance(c, str) else c
        out = out + c.cast(kind) * F.lit(f).cast(kind)
    return out.cast(kind)


def _places(sizes: list[int], forward: bool) -> list[int]:
    out, n = [], 1
    for s in reversed(sizes) if forward else sizes:
        out.append(n)
        n *= s
    return out[::-1] if forward else out


def forward_index(cols: list, sizes: list[int], wide: bool = False) -> Column:
    """First variable most significant."""
    return _weighted(cols, sizes, _places(sizes, True), wide)


def reverse_index(cols: list, sizes: list[int], wide: bool = False) -> Column:
    """First variable least significant, so that it peels off by modulo."""
    return _weighted(cols, sizes, _places(sizes, False), wide)


def decode_index(idx, sizes: list[int], forward: bool = True) -> list[Column]:
    """Codes of an index, in variable order."""
    c = F.col(idx) if isinstance(idx, str) else idx
    return [F.pmod(_div(c, p), F.lit(s)) for p, s in zip(_places(sizes, forward), sizes)]


def _div(c: Column, by: int) -> Column:
    return F.call_function("div", c, F.lit(by)) if by != 1 else c


def reindex(idx, sizes: list[int], forward: bool = True) -> Column:
    """The other index of the same tuple: forward to reverse or back (M15d); no shuffle."""
    codes = decode_index(idx, sizes, forward)
    return (reverse_index if forward else forward_index)(codes, sizes)


FUNCTIONS_SQL = {
    "fwd_index": "CREATE OR REPLACE TEMPORARY FUNCTION fwd_index(codes ARRAY<BIGINT>, sizes ARRAY<BIGINT>) RETURNS BIGINT RETURN aggregate(arrays_zip(codes, sizes), 0L, (a, x) -> a * x.sizes + x.codes)",
    "rev_index": "CREATE OR REPLACE TEMPORARY FUNCTION rev_index(codes ARRAY<BIGINT>, sizes ARRAY<BIGINT>) RETURNS BIGINT RETURN aggregate(reverse(arrays_zip(codes, sizes)), 0L, (a, x) -> a * x.sizes + x.codes)",
}


def register(spark) -> None:
    """fwd_index and rev_index as SQL functions over arrays."""
    for sql in FUNCTIONS_SQL.values():
        spark.sql(sql)
