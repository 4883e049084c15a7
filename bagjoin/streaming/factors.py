"""Incremental count factors, transitions and recalibration (S1-S6). All functions also take batches."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import W, Factor, Network

EVENTS = "event_id bigint, user_id bigint, ts timestamp_ntz, event_type string, value double, props string"


def read_events(spark: SparkSession, folder: str, schema: str = EVENTS, files_per_trigger: int = 1) -> DataFrame:
    """Parquet file stream of events."""
    return with_time(spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder))


def with_time(df: DataFrame, ts: str = "ts") -> DataFrame:
    """Event time as a timestamp, as watermarks need it."""
    return df.withColumn(ts, F.col(ts).cast("timestamp"))


def with_lateness(df: DataFrame, ts: str = "ts", delay: str = "1 hour") -> DataFrame:
    """Rows later than the watermark are dropped by the stateful operators that follow."""
    return df.withWatermark(ts, delay)


def window_counts(df: DataFrame, vars: list[str], size: str | None = None, slide: str | None = None, gap: str | None = None, ts: str = "ts") -> DataFrame:
    """(start, vars..., w): counts over tumbling, sliding or session windows."""
    w = F.session_window(ts, gap) if gap else F.window(ts, size, slide)
    out = df.groupBy(w.alias("win"), *vars).agg(F.count(F.lit(1)).alias(W))
    return out.select(F.col("win.start").alias("start"), *vars, W)


def dedupe(df: DataFrame, key: str = "event_id") -> DataFrame:
    """First row per key within the watermark; in a batch, one row per key."""
    return df.dropDuplicatesWithinWatermark([key]) if df.isStreaming else df.dropDuplicates([key])


def transitions(df: DataFrame, key: str = "user_id", ts: str = "ts", var: str = "event_type", ttl_ms: int = 86_400_000) -> DataFrame:
    """(key, prev, next, ts) as events arrive; the last state of a key is kept until it times out (S3)."""
    kind = dict(df.dtypes)[key]

    def step(group: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        rows = pd.concat(list(batches), ignore_index=True).sort_values(ts, kind="stable")
        last = state.get[0] if state.exists else None
        prev = [last, *rows[var].tolist()[:-1]]
        out = pd.DataFrame({key: group[0], "prev": prev, "next": rows[var].tolist(), ts: rows[ts].tolist()})
        state.update((rows[var].iloc[-1],))
        state.setTimeoutDuration(ttl_ms)
        yield out[out["prev"].notna()]

    return df.select(key, ts, var).groupBy(key).applyInPandasWithState(step, f"{key} {kind}, prev string, next string, {ts} timestamp", "last string", "append", "ProcessingTimeTimeout")


def enrich(stream: DataFrame, static: DataFrame, on: str) -> DataFrame:
    """Stream-static join with a factor of the key."""
    return stream.join(static, on)


def cooccur(a: DataFrame, b: DataFrame, key: str = "user_id", within: str = "1 hour", ts: str = "ts", var: str = "event_type") -> DataFrame:
    """Pairs of two watermarked streams, the second at most ``within`` after the first."""
    x = a.select(F.col(key).alias("ka"), F.col(ts).alias("ta"), F.col(var).alias("a"))
    y = b.select(F.col(key).alias("kb"), F.col(ts).alias("tb"), F.col(var).alias("b"))
    return x.join(y, F.expr(f"ka = kb AND tb >= ta AND tb <= ta + INTERVAL {within}")).select(F.col("ka").alias(key), "a", "b", "ta", "tb")


def recalibrate(stream: DataFrame, network: Network, factor: str, sink: Callable[[DataFrame, int], None], checkpoint: str, strategy: str = "pairwise", config=None):
    """Add each micro-batch's counts to a stored factor and calibrate again on the same tree.

    The counts so far live in a Parquet folder per batch beside the checkpoint, written before they
    are used, so a repeated batch replaces its own folder. Returns the writer; start it with
    ``.start()`` or an ``availableNow`` trigger.
    """
    from ..operators.infer import InferConfig, infer
    from ..plans.decomposition import Decomposition, decompose

    dec = decompose(network)
    base = network.factor(factor)
    spark = base.df.sparkSession

    def one(batch: DataFrame, number: int) -> None:
        folder = f"{checkpoint}/counts"
        batch.groupBy(*base.vars).agg(F.count(F.lit(1)).alias(W)).write.mode("overwrite").parquet(f"{folder}/batch={number}")
        seen = spark.read.parquet(folder).filter(F.col("batch") <= number).select(*base.vars, W)
        new = Factor(base.name, base.vars, base.df.select(*base.vars, W).unionByName(seen).groupBy(*base.vars).agg(F.sum(W).alias(W)))
        n = network.replaced([new])
        tree = Decomposition(dec.chi, dec.parent, dec.alpha, dec.lam, n)  # only sizes and messages move
        sink(infer(n, strategy, config=config or InferConfig(), dec=tree).variable_marginals(), number)

    return stream.writeStream.foreachBatch(one).option("checkpointLocation", f"{checkpoint}/state")


def write_factor(df: DataFrame, path: str, checkpoint: str):
    """Append a finished windowed factor to a Parquet folder."""
    return df.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append")
