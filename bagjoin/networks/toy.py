"""Segment, nation, priority and status: the small network of four variables."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..model import Factor, Network
from ..sources.tables import table


def network(spark: SparkSession, sf_dir: str) -> Network:
    c = table(spark, sf_dir, "customer", "c_custkey", "c_nationkey", "c_mktsegment")
    o = table(spark, sf_dir, "orders", "o_custkey", "o_orderpriority", "o_orderstatus")
    oc = o.join(c, F.col("o_custkey") == F.col("c_custkey"))
    return Network.of([
        Factor.counts("seg_nation", c, ("c_mktsegment", "c_nationkey")),
        Factor.counts("seg_prio", oc, ("c_mktsegment", "o_orderpriority")),
        Factor.counts("nation_prio_status", oc, ("c_nationkey", "o_orderpriority", "o_orderstatus")),
    ])
