"""Time-sliced chain of event types with observed keys."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..model import Factor, Network
from ..sources.tables import table


def transition_counts(spark: SparkSession, sf_dir: str) -> Factor:
    e = table(spark, sf_dir, "events", "event_id", "user_id", "ts", "event_type")
    return Factor.transition("transition", e, "user_id", ["ts", "event_id"], "event_type")


def emission_counts(spark: SparkSession, sf_dir: str) -> Factor:
    e = table(spark, sf_dir, "events", "event_type", "props").select("event_type", F.get_json_object("props", "$.k").cast("int").alias("k"))
    return Factor.counts("emission", e, ("event_type", "k"))


def chain(spark: SparkSession, sf_dir: str, slices: int = 720) -> tuple[Network, dict[str, str]]:
    """(network, templates): hidden s0..., observed k0...; every slice repeats the same two tables."""
    t, e = transition_counts(spark, sf_dir), emission_counts(spark, sf_dir)
    trans = _conditional(t, "prev", "next")
    emit = _conditional(e, "event_type", "k")
    n_t, n_e = trans.size(), emit.size()
    states = t.count_support(("prev",))
    keys = e.count_support(("k",))
    factors, templates, sizes = [], {}, {}
    for i in range(slices):
        f = Factor(f"emit{i}", (f"s{i}", f"k{i}"), emit.rename({"event_type": f"s{i}", "k": f"k{i}"}).df)
        factors.append(f)
        templates[f.name], sizes[f.name] = "emit0", n_e
        if i:
            g = Factor(f"step{i}", (f"s{i - 1}", f"s{i}"), trans.rename({"prev": f"s{i - 1}", "next": f"s{i}"}).df)
            factors.append(g)
            templates[g.name], sizes[g.name] = "step1", n_t
    domains = {f"s{i}": states for i in range(slices)} | {f"k{i}": keys for i in range(slices)}
    return Network.of(factors, domains, sizes), templates


def _conditional(f: Factor, parent: str, child: str) -> Factor:
    total = f.df.groupBy(parent).agg(F.sum("w").alias("__t"))
    df = f.df.join(total, parent).select(parent, child, (F.col("w") / F.col("__t")).alias("w"))
    return Factor(f.name, (parent, child), df)
