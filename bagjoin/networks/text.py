"""Networks over the text tables' attributes."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..functions.discretise import bin_width
from ..model import Factor, Network
from ..sources.tables import table


def labels(spark: SparkSession, sf_dir: str) -> Network:
    """Language, source, length, quality and toxicity of labelled documents."""
    d = table(spark, sf_dir, "documents", "doc_id", "lang", "source", "n_chars").withColumn("size", F.least(bin_width("n_chars", 0, 1000), F.lit(9)))
    x = d.join(table(spark, sf_dir, "labels"), "doc_id")
    return Network.of([Factor.counts("lang_source", d, ("lang", "source")), Factor.counts("lang_size", d, ("lang", "size")), Factor.counts("source_quality_toxic", x, ("source", "quality", "toxic"))])


def roles(spark: SparkSession, sf_dir: str) -> Network:
    """Role given the previous role, and the turn."""
    c = table(spark, sf_dir, "conversations", "conv_id", "turn", "role")
    return Network.of([Factor.transition("step", c, "conv_id", ["turn"], "role", prev="prev_role", nxt="role"), Factor.counts("turn_role", c, ("turn", "role"))])


def hosts(spark: SparkSession, sf_dir: str) -> Network:
    """Host and declared language of pages."""
    p = table(spark, sf_dir, "pages", "url", "html")
    x = p.select(F.lower(F.regexp_extract("url", "^[a-z]+://([^/?#:]+)", 1)).alias("host"), F.regexp_extract("html", '<html lang="([a-z]+)"', 1).alias("lang"))
    return Network.of([Factor.counts("host_lang", x, ("host", "lang"))])
