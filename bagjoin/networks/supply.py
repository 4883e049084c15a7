"""Customers, parts and suppliers: triangle, hub triangle and the two-bag look-ahead network (W1, W1s, W2)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import W, Factor, Network
from ..operators.relational import materialise
from ..sources.tables import table


def _lines(spark: SparkSession, sf_dir: str, *columns: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem", *columns)


def cust_part(spark: SparkSession, sf_dir: str, by: str | None = None) -> Factor:
    o = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    x = o.join(_lines(spark, sf_dir, "l_orderkey", "l_partkey"), F.col("o_orderkey") == F.col("l_orderkey"))
    return Factor.counts("cust_part", x, ("o_custkey", "l_partkey"), by)


def cust_supp(spark: SparkSession, sf_dir: str, by: str | None = None) -> Factor:
    o = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    x = o.join(_lines(spark, sf_dir, "l_orderkey", "l_suppkey"), F.col("o_orderkey") == F.col("l_orderkey"))
    return Factor.counts("cust_supp", x, ("o_custkey", "l_suppkey"), by)


def part_supp(spark: SparkSession, sf_dir: str) -> Factor:
    return Factor.counts("part_supp", _lines(spark, sf_dir, "l_partkey", "l_suppkey"), ("l_partkey", "l_suppkey"))


def part_supp_flag(spark: SparkSession, sf_dir: str) -> Factor:
    v = ("l_partkey", "l_suppkey", "l_returnflag")
    return Factor.counts("part_supp_flag", _lines(spark, sf_dir, *v), v)


def ordered_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(l_partkey, l_suppkey, ordered = true) of the lines whose order has a customer."""
    o = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey").filter("o_custkey IS NOT NULL")
    x = _lines(spark, sf_dir, "l_orderkey", "l_partkey", "l_suppkey").join(o, F.col("l_orderkey") == F.col("o_orderkey"), "left_semi")
    return x.select("l_partkey", "l_suppkey").distinct().withColumn("ordered", F.lit(True))


def _dimensions(spark: SparkSession, sf_dir: str) -> dict[str, int]:
    """Domain sizes from the dimension tables, as supports may miss members."""
    one = lambda t: table(spark, sf_dir, t).count()
    return {"o_custkey": one("customer"), "l_partkey": one("part"), "l_suppkey": one("supplier")}


def triangle(spark: SparkSession, sf_dir: str) -> Network:
    return Network.of([cust_part(spark, sf_dir), part_supp(spark, sf_dir), cust_supp(spark, sf_dir)], _dimensions(spark, sf_dir))


def hub(spark: SparkSession, sf_dir: str) -> Network:
    """Three copies of {(k, 0)} and {(0, k)}: pairwise plans are quadratic in it."""
    p = table(spark, sf_dir, "part", "p_partkey")
    k, zero = F.col("p_partkey"), F.lit(0).cast("bigint")
    rows = p.select(k.alias("x"), zero.alias("y")).union(p.select(zero.alias("x"), k.alias("y"))).distinct()
    base = rows.withColumn(W, F.lit(1).cast("bigint"))
    sides = [Factor(f"hub_{a}{b}", (a, b), base.select(F.col("x").alias(a), F.col("y").alias(b), W)) for a, b in (("a", "b"), ("b", "c"), ("c", "a"))]
    return Network.of(sides)


def lookahead(spark: SparkSession, sf_dir: str, store: bool = False) -> Network:
    """``store``: the customers' factors are made once and written, sorted by customer, not made at each use."""
    own = [make(spark, sf_dir, "o_custkey" if store else None) for make in (cust_part, cust_supp)]
    if store:
        own = [Factor(f.name, f.vars, materialise(f.df)) for f in own]
    return Network.of([*own, part_supp_flag(spark, sf_dir)], _dimensions(spark, sf_dir) | {"l_returnflag": 3})
