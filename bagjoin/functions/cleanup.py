"""Shuffle files of finished executions."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import SparkSession

_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def short_lived_shuffles(spark: SparkSession) -> Iterator[None]:
    """Executions begun inside delete their shuffle files as they end, not when the driver collects its garbage.

    For writes and for frames that are used once: a frame that runs again would have to redo its shuffles.
    """
    before, able = spark.conf.get(_CLEANUP, None), spark.conf.isModifiable(_CLEANUP)
    if able:
        spark.conf.set(_CLEANUP, "true")
    try:
        yield
    finally:
        if able:
            spark.conf.unset(_CLEANUP) if before is None else spark.conf.set(_CLEANUP, before)
