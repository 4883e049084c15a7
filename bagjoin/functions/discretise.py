"""Finite domains from continuous columns (O9), portable hashing (O8f) and key sampling."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

_MODULUS = 2147483647


def bin_width(col, low: float, width: float) -> Column:
    """Number of the bin of the given width that holds the value, from ``low``."""
    c = F.col(col) if isinstance(col, str) else col
    return F.floor((c - F.lit(low)) / F.lit(width)).cast("int")


def bin_ntile(df: DataFrame, col: str, n: int, out: str, exact: bool = False) -> DataFrame:
    """Add the number of the quantile bin. Approximate cut points by default (no global sort)."""
    if exact:
        return df.withColumn(out, F.ntile(n).over(Window.orderBy(col)) - 1)
    cuts = df.agg(F.percentile_approx(col, [i / n for i in range(1, n)], 10000)).first()[0] or []
    return df.withColumn(out, sum(((F.col(col) > F.lit(c)).cast("int") for c in cuts), F.lit(0)))


def sign_bit(col) -> Column:
    c = F.col(col) if isinstance(col, str) else col
    return (c > 0).cast("int")


def percent(col) -> Column:
    """A fraction stored as double, as whole percent."""
    c = F.col(col) if isinstance(col, str) else col
    return F.round(c * 100).cast("int")


def portable_hash(cols: list, seed: int = 0) -> Column:
    """Hash by plain integer arithmetic, the same in any SQL engine; columns are integers."""
    out = F.lit(seed % _MODULUS).cast("bigint")
    for c in cols:
        c = F.col(c) if isinstance(c, str) else c
        out = F.pmod(out * F.lit(48271) + F.pmod(c.cast("bigint"), F.lit(_MODULUS)) * F.lit(69621) + F.lit(11), F.lit(_MODULUS))
    return out


def sample_by_key(df: DataFrame, cols: list[str], fraction: float, seed: int = 0) -> DataFrame:
    """Keep the rows of a hashed share of the keys, so that samples of two relations still join."""
    return df.filter(F.pmod(F.xxhash64(F.lit(seed), *[F.col(c) for c in cols]), F.lit(1_000_000)) < F.lit(int(fraction * 1_000_000)))


def log_sum_exp(df: DataFrame, keys: list[str], col: str, out: str) -> DataFrame:
    """Sum of weights kept as logarithms (O14): the maximum first, then scaled sums."""
    top = df.groupBy(*keys).agg(F.max(col).alias("__m"))
    both = df.join(top, keys) if keys else df.crossJoin(top)
    agg = both.groupBy(*keys).agg((F.max("__m") + F.log(F.sum(F.exp(F.col(col) - F.col("__m"))))).alias(out))
    return agg
