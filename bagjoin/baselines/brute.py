"""Join every factor, then aggregate (B0): the reference for small networks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import W, Network
from ..operators.product import pairwise_product


def joint(network: Network) -> DataFrame:
    return pairwise_product(network.vars, list(network.factors), "greedy").df


def brute_force(network: Network, vars: tuple[str, ...] | None = None) -> DataFrame:
    """(vars..., mass), or (variable, value, mass, prob) of all variables."""
    df = joint(network)
    if vars is not None:
        return df.groupBy(*vars).agg(F.sum(W).alias("mass"))
    parts = None
    for v in network.vars:
        p = df.groupBy(F.lit(v).alias("variable"), F.col(v).cast("string").alias("value")).agg(F.sum(W).alias("mass"))
        parts = p if parts is None else parts.unionByName(p)
    z = df.agg(F.sum(W).alias("__z"))
    return parts.crossJoin(z).withColumn("prob", F.col("mass") / F.col("__z")).drop("__z")
