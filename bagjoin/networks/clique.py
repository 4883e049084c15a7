"""All pairs of binned embedding dimensions, thinned out: constraint cliques."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import W, Factor, Network
from ..sources.tables import table


def bins(spark: SparkSession, sf_dir: str, dims: int) -> DataFrame:
    """b0, b1, ...: floor((x + 1) * 22) of the leading dimensions."""
    e = table(spark, sf_dir, "embeddings", "embedding")
    return e.select(*[F.floor((F.element_at("embedding", i + 1).cast("double") + 1) * 22).cast("bigint").alias(f"b{i}") for i in range(dims)])


def pair(spark: SparkSession, sf_dir: str, i: int, j: int, keep: int, low: int, diagonal: int | None = None) -> Factor:
    """Pair table of two dimensions, codes from ``low``, kept by a portable rule (about ``keep`` percent of cells)."""
    b = bins(spark, sf_dir, max(i, j) + 1).select((F.col(f"b{i}") - low).alias(f"d{i}"), (F.col(f"b{j}") - low).alias(f"d{j}")).distinct()
    rule = F.pmod(7919 * F.col(f"d{i}") + 104729 * F.col(f"d{j}") + 31 * i + 17 * j, F.lit(100)) < 100 * keep // 42
    rows = b.filter(rule | (F.col(f"d{i}") == F.col(f"d{j}")))
    if diagonal:
        d = spark.range(diagonal).select(F.col("id").alias(f"d{i}"), F.col("id").alias(f"d{j}"))
        rows = rows.union(d).distinct()
    return Factor(f"pair_{i}_{j}", (f"d{i}", f"d{j}"), rows.withColumn(W, F.lit(1).cast("bigint")))


def network(spark: SparkSession, sf_dir: str, dims: int = 8, keep: int = 20, forced: bool = False) -> Network:
    """``forced`` also adds the missing diagonal rows, as the sparsity rule states it."""
    b = bins(spark, sf_dir, dims)
    low, high = b.agg(F.least(*[F.min(c) for c in b.columns]), F.greatest(*[F.max(c) for c in b.columns])).first()
    fs = [pair(spark, sf_dir, i, j, keep, low, high - low + 1 if forced else None) for i in range(dims) for j in range(i + 1, dims)]
    return Network.of(fs, {f"d{i}": high - low + 1 for i in range(dims)})
