"""An expert-style network over fourteen low-cardinality columns of the star schema.

Factors are conditional probabilities, as the product of thirteen count tables leaves any integer.
"""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..functions.discretise import percent
from ..model import Factor, Network
from ..sources.tables import table

#: (name, child, parents)
SHAPE = (
    ("region", "region", ()),
    ("nation", "nation", ("region",)),
    ("segment", "segment", ("nation",)),
    ("prio", "prio", ("segment",)),
    ("status", "status", ("prio",)),
    ("linestatus", "linestatus", ("status",)),
    ("flag", "flag", ("linestatus",)),
    ("lineno", "lineno", ("flag",)),
    ("quantity", "quantity", ("lineno",)),
    ("tax", "tax", ("quantity", "discount")),
    ("brand", "brand", ("quantity",)),
    ("type", "ptype", ("brand",)),
    ("size", "psize", ("brand", "ptype")),
)


def base(spark: SparkSession, sf_dir: str):
    """Columns of each factor as DataFrames of the variables' names."""
    n = table(spark, sf_dir, "nation", "n_nationkey", "n_regionkey").select(F.col("n_nationkey").alias("nation"), F.col("n_regionkey").alias("region"))
    c = table(spark, sf_dir, "customer", "c_custkey", "c_nationkey", "c_mktsegment").select("c_custkey", F.col("c_nationkey").alias("nation"), F.col("c_mktsegment").alias("segment"))
    o = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderpriority", "o_orderstatus").select("o_orderkey", "o_custkey", F.col("o_orderpriority").alias("prio"), F.col("o_orderstatus").alias("status"))
    li = table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_linenumber", "l_quantity", "l_discount", "l_tax", "l_returnflag", "l_linestatus")
    li = li.select("l_orderkey", "l_partkey", F.col("l_linenumber").alias("lineno"), F.col("l_quantity").cast("int").alias("quantity"), percent("l_discount").alias("discount"), percent("l_tax").alias("tax"), F.col("l_returnflag").alias("flag"), F.col("l_linestatus").alias("linestatus"))
    p = table(spark, sf_dir, "part", "p_partkey", "p_brand", "p_type", "p_size").select("p_partkey", F.col("p_brand").alias("brand"), F.col("p_type").alias("ptype"), F.col("p_size").alias("psize"))
    return {
        "region": n, "nation": n, "segment": c, "prio": o.join(c, F.col("o_custkey") == F.col("c_custkey")), "status": o,
        "linestatus": li.join(o, F.col("l_orderkey") == F.col("o_orderkey")), "flag": li, "lineno": li, "quantity": li, "tax": li,
        "brand": li.join(p, F.col("l_partkey") == F.col("p_partkey")), "type": p, "size": p,
    }


def network(spark: SparkSession, sf_dir: str) -> Network:
    src = base(spark, sf_dir)
    return Network.of([Factor.conditional(name, src[name], child, parents) for name, child, parents in SHAPE])
