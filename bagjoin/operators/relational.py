"""Materialising, joining and comparing factors (O3, O6, O7, O11p)."""

from __future__ import annotations

import tempfile
import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.cleanup import short_lived_shuffles
from ..functions.semiring import SUM_PRODUCT, Semiring
from ..model import W, Factor


def shared_folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir; a temporary one only where none is set."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        current = spark.sparkContext._jsc.sc().getCheckpointDir()
        if current.isDefined():
            return current.get()
        found = "file://" + tempfile.mkdtemp(prefix="bagjoin-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def materialise(df: DataFrame, mode: str = "parquet") -> DataFrame:
    """Cut the lineage of ``df`` (O11p): ``parquet`` or ``checkpoint`` in the shared folder, ``persist``, or ``lazy``."""
    if mode == "lazy":
        return df
    if mode == "persist":
        return df.persist()
    if mode == "checkpoint":
        shared_folder(df.sparkSession)
        return df.checkpoint()
    path = f"{shared_folder(df.sparkSession)}/bag-{uuid.uuid4().hex}"
    with short_lived_shuffles(df.sparkSession):
        df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


#: Cells that a join without a shared variable may produce.
CROSS_LIMIT = 10_000_000


#: Rows of a side up to which a broadcast hint is obeyed; a larger one is shuffled.
BROADCAST_LIMIT = 1_000_000


class CrossProductError(ValueError):
    """A product of factors without a shared variable would be too large."""


def multiply(a: Factor, b: Factor, hint: str | None = None, semiring: Semiring = SUM_PRODUCT, cross_limit: int | None = CROSS_LIMIT) -> Factor:
    """Weighted natural join (O3a). ``hint``: broadcast, shuffle_hash, merge or shuffle_replicate_nl.

    Factors without a shared variable are cross-joined behind a check of their sizes (O3c).
    """
    on = [v for v in a.vars if v in set(b.vars)]
    right = b.df.withColumnRenamed(W, "__w")
    if hint:
        right = right.hint(hint)
    if on:
        out = a.df.join(right, on)
    else:
        if cross_limit is not None and a.vars and b.vars:
            x = a.df.limit(cross_limit + 1).count()
            if x * b.df.limit(max(1, cross_limit // max(1, x)) + 1).count() > cross_limit:
                raise CrossProductError(f"{a.name} x {b.name}")
        out = a.df.crossJoin(right)
    vars = a.vars + tuple(v for v in b.vars if v not in set(a.vars))
    return Factor(f"{a.name}*{b.name}", vars, out.select(*vars, semiring.times(F.col(W), F.col("__w")).alias(W)))


def reduce_by(a: Factor, b: Factor | DataFrame) -> Factor:
    """Rows of ``a`` that some row of ``b`` agrees with (O3d)."""
    other = b.df if isinstance(b, Factor) else b
    on = [v for v in a.vars if v in set(other.columns)]
    return Factor(a.name, a.vars, a.df.join(other.select(*on), on, "left_semi")) if on else a


def dead_rows(a: Factor, b: Factor | DataFrame) -> DataFrame:
    """Rows of ``a`` that no row of ``b`` agrees with (O3e)."""
    other = b.df if isinstance(b, Factor) else b
    on = [v for v in a.vars if v in set(other.columns)]
    return a.df.join(other.select(*on), on, "left_anti")


def hash_product(big: Factor, small: Factor, op: str = "mul", hint: str = "shuffle_hash", semiring: Semiring = SUM_PRODUCT) -> Factor:
    """Probe the rows of ``big`` in a hash table of ``small``: multiply or divide, and drop what finds nothing.

    ``op``: mul, div, or whole, which divides integers that are known to leave no remainder.
    """
    on = [v for v in big.vars if v in set(small.vars)]
    if hint == "broadcast" and small.df.limit(BROADCAST_LIMIT + 1).count() > BROADCAST_LIMIT:
        hint = "shuffle_hash"
    right = small.df.select(*on, F.col(W).alias("__w"))
    out = big.df.join(right.hint(hint), on) if on else big.df.crossJoin(right)
    times = {"mul": semiring.times, "div": semiring.divide, "whole": semiring.whole}[op]
    return Factor(big.name, big.vars, out.select(*big.vars, times(F.col(W), F.col("__w")).alias(W)))


def sort_merge_product(big: Factor, small: Factor, op: str = "mul", semiring: Semiring = SUM_PRODUCT) -> Factor:
    """The same product by sort-merge join."""
    return hash_product(big, small, op, "merge", semiring)


def stack_marginals(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def common_support(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.intersect(b)


def diff_support(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.exceptAll(b)


def topk(marginals: DataFrame, k: int, by: str = "mass") -> DataFrame:
    """The k largest values of every variable, ties by value."""
    w = Window.partitionBy("variable").orderBy(F.desc(by), "value")
    return marginals.withColumn("rk", F.row_number().over(w)).filter(F.col("rk") <= k)


def most_probable(factor: Factor, k: int) -> DataFrame:
    """The k heaviest rows, ties by the variables' order."""
    return factor.df.orderBy(F.desc(W), *factor.vars).limit(k)


def cube_marginals(df: DataFrame, vars: list[str], semiring: Semiring = SUM_PRODUCT) -> DataFrame:
    """Marginals of every subset of ``vars`` in one pass, with the grouping id (O4e)."""
    return df.cube(*vars).agg(F.grouping_id().alias("gid"), semiring.plus(F.col(W)).alias("mass"))


def subset_marginals(df: DataFrame, vars: list[str], subsets: list[list[str]]) -> DataFrame:
    """Marginals of chosen subsets by grouping sets."""
    return df.groupingSets([[F.col(v) for v in s] for s in subsets], *vars).agg(F.grouping_id().alias("gid"), F.sum(W).alias("mass"))


@dataclass
class Observed:
    """A DataFrame that counts its rows as a side effect of its next action (O4g)."""

    df: DataFrame
    seen: Observation

    @property
    def rows(self) -> int:
        return self.seen.get["n"]


def observe_rows(df: DataFrame, name: str) -> Observed:
    o = Observation(f"{name}-{uuid.uuid4().hex[:8]}")
    return Observed(df.observe(o, F.count(F.lit(1)).alias("n")), o)
