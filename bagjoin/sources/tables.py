"""Table sources and marginal sinks (O1, O1c, O1d)."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import Factor, Network


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A Parquet table, only the named columns; filters on it reach the scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def save_network(network: Network, path: str, bucket_by: dict[str, tuple[int, str]] | None = None, catalog: str | None = None) -> None:
    """One Parquet folder per factor and a manifest; with ``catalog`` also tables bucketed for later joins."""
    spark = network.spark
    for f in network.factors:
        f.df.write.mode("overwrite").parquet(f"{path}/{f.name}")
        if catalog and bucket_by and f.name in bucket_by:
            n, col = bucket_by[f.name]
            f.df.write.mode("overwrite").bucketBy(n, col).sortBy(col).saveAsTable(f"{catalog}_{f.name}")
    manifest = {"factors": [{"name": f.name, "vars": list(f.vars)} for f in network.factors], "domains": network.domains, "sizes": network.sizes, "scale": network.scale}
    spark.createDataFrame([(json.dumps(manifest),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")


def load_network(spark: SparkSession, path: str) -> Network:
    m = json.loads(spark.read.text(f"{path}/manifest").first().value)
    factors = [Factor(f["name"], tuple(f["vars"]), spark.read.parquet(f"{path}/{f['name']}")) for f in m["factors"]]
    return Network(tuple(factors), m["domains"], m["sizes"], m["scale"])


def write_marginals(df: DataFrame, fmt: str, path: str | None = None) -> None:
    """parquet, csv, json, orc to a path; console, noop; memory registers a view of that name."""
    if fmt == "memory":
        df.createOrReplaceTempView(path)
    elif fmt == "console":
        df.show(50, truncate=False)
    elif fmt == "noop":
        df.write.format("noop").mode("overwrite").save()
    else:
        df.write.format(fmt).mode("overwrite").save(path)


def views(network: Network, marginals: DataFrame | None = None, prefix: str = "net") -> None:
    """Temporary views of the factors and, if given, the marginals."""
    for f in network.factors:
        f.df.createOrReplaceTempView(f"{prefix}_{f.name}")
    if marginals is not None:
        marginals.withColumn("prob", F.col("prob")).createOrReplaceTempView(f"{prefix}_marginals")
