"""Connected components on DataFrames by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stage


def _large_star(e: DataFrame) -> DataFrame:
    """Point every larger neighbour of a node at the node's least neighbour."""
    both = e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.filter(F.col("v") > F.col("u")).join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _small_star(e: DataFrame) -> DataFrame:
    """Point a node and its smaller neighbours at the least of them (edges run from larger u to smaller v)."""
    least = e.groupBy("u").agg(F.min("v").alias("m"))
    moved = e.join(least, "u").filter(F.col("v") != F.col("m")).select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(least.select("u", F.col("m").alias("v")))


def components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """(node, component): component is the least node id reachable; only nodes with an edge appear.

    Works on any number of edges: each round is two aggregations and two equi-joins whose skewed
    partitions adaptive execution splits; rounds are staged in the shared folder. Self loops and
    repeated edges are allowed; null ends are ignored. Ids are of one orderable type.
    """
    cur = stage(edges.filter(F.col(a).isNotNull() & F.col(b).isNotNull() & (F.col(a) != F.col(b))).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct(), "edges")
    mark = _mark(cur)
    for _ in range(max_rounds):
        if not mark[0]:
            break
        nxt = stage(_small_star(_large_star(cur).filter("u != v")).filter("u != v").distinct(), "edges")
        new = _mark(nxt)
        cur = nxt
        if new == mark:
            break
        mark = new
    else:
        raise RuntimeError("components did not settle")
    return cur.select(F.col("u").alias("node"), F.col("v").alias("component")).union(cur.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())


def _mark(e: DataFrame) -> tuple:
    r = e.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
    return (r.n, r.h)
