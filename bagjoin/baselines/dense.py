"""Dense junction tree (B1): truth tables, cell by cell, on the same tree.

Refuses networks of more cells than the limit, before it builds any table.
"""

from __future__ import annotations

import functools

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import W, Domain, Factor, Network
from ..operators.relational import materialise
from ..plans.decomposition import Decomposition, decompose
from ..plans.measures import RHO_LIMIT, rho


class DenseLimitError(ValueError):
    """The bags have more cells than the limit."""


def dense_table(factor: Factor, domains: dict[str, DataFrame]) -> DataFrame:
    """(vars..., w) over all cells."""
    return factor.to_dense(domains)


def domains_of(network: Network) -> dict[str, DataFrame]:
    out = {}
    for v in network.vars:
        parts = [f.df.select(v) for f in network.factors if v in f.vars]
        out[v] = functools.reduce(DataFrame.union, parts).distinct()
    return out


def dense_junction_tree(network: Network, max_cells: float = RHO_LIMIT, dec: Decomposition | None = None, mode: str = "parquet") -> DataFrame:
    """(variable, value, mass, prob) from dense tables. Cells are numbered by the forward index of their codes."""
    dec = dec or decompose(network)
    if rho(dec) > max_cells:
        raise DenseLimitError(f"{rho(dec)} cells, the limit is {max_cells:g}")
    books = {v: Domain.fit(d, v) for v, d in domains_of(network).items()}
    codes = {v: b.df.select(F.col("code").alias(v)) for v, b in books.items()}

    def coded(f: Factor) -> DataFrame:
        df = f.df
        for v in f.vars:
            df = books[v].encode(df, v)
        return Factor(f.name, f.vars, df.select(*f.vars, F.col(W).cast("double").alias(W))).to_dense(codes)

    def cells(bag: int) -> DataFrame:
        out = functools.reduce(lambda a, b: a.crossJoin(b), [codes[v] for v in dec.chi[bag]])
        return out.withColumn(W, F.lit(1.0))

    def times(table: DataFrame, other: DataFrame) -> DataFrame:
        on = [c for c in other.columns if c != W]
        o = other.withColumnRenamed(W, "__w")
        joined = table.join(o, on) if on else table.crossJoin(o)
        return joined.select(*[c for c in table.columns if c != W], (F.col(W) * F.col("__w")).alias(W))

    tables: dict[int, DataFrame] = {}
    up: dict[int, DataFrame] = {}
    for level in reversed(dec.levels):
        for b in level:
            t = cells(b)
            for n in dec.alpha[b]:
                t = times(t, coded(network.factor(n)))
            for k in dec.children[b]:
                t = times(t, up[k])
            tables[b] = materialise(t, mode)
            if dec.parent[b] >= 0:
                sep = dec.separator(b)
                up[b] = materialise(tables[b].groupBy(*sep).agg(F.sum(W).alias(W)) if sep else tables[b].agg(F.sum(W).alias(W)), mode)
    for level in dec.levels[1:]:
        for b in level:
            sep = list(dec.separator(b))
            down = tables[dec.parent[b]].groupBy(*sep).agg(F.sum(W).alias("__d")) if sep else tables[dec.parent[b]].agg(F.sum(W).alias("__d"))
            share = down.join(up[b], sep) if sep else down.crossJoin(up[b])
            share = share.select(*sep, F.when(F.col(W) > 0, F.col("__d") / F.col(W)).otherwise(0.0).alias(W))
            tables[b] = materialise(times(tables[b], share), mode)
    out = None
    for v in network.vars:
        m = tables[dec.bag_of([v])].groupBy(v).agg(F.sum(W).alias("mass")).filter("mass > 0")
        m = books[v].decode(m, v).select(F.lit(v).alias("variable"), F.col(v).cast("string").alias("value"), "mass")
        out = m if out is None else out.unionByName(m)
    z = out.groupBy("variable").agg(F.sum("mass").alias("__z"))
    return out.join(z, "variable").withColumn("prob", F.col("mass") / F.col("__z")).drop("__z")
