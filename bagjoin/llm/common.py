"""Shared plumbing of the training-data operators: tables, staging, Arrow streams."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space of the word contracts: space and TAB, LF, VT, FF, CR.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
SPACE_CLASS = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given Parquet tables, read only through Spark's own readers."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one only where none is set (tests)."""
    found = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = found.get() if found.isDefined() else None
    if not found:
        found = "file://" + tempfile.mkdtemp(prefix="bagjoin-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def new_folder(spark: SparkSession, kind: str) -> str:
    """A fresh path under the shared folder."""
    return f"{shared_dir(spark)}/{kind}-{uuid.uuid4().hex}"


#: Lets a finished SQL execution delete its shuffle files at once; nothing reads them again after a stage is written.
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def stage(df: DataFrame, kind: str = "stage") -> DataFrame:
    """Write ``df`` once to the shared folder and read it back: cuts lineage and survives lost executors."""
    path = new_folder(df.sparkSession, kind)
    _written(df.sparkSession, lambda: df.write.option("compression", "zstd").parquet(path))
    return df.sparkSession.read.schema(df.schema).parquet(path)


class Bucketed:
    """``df`` written once to the shared folder in buckets of ``by``; a join on all of ``by`` does not move it again.

    Best where ``df`` already lies in partitions by ``by``, as after an aggregation: then a bucket is a
    file. ``drop`` forgets the table and deletes its files; call it when nothing will read them again.
    """

    def __init__(self, df: DataFrame, by: list[str], kind: str):
        self.spark, self.path = df.sparkSession, new_folder(df.sparkSession, kind)
        self.name = f"{kind}_{self.path[-32:]}"
        most = int(self.spark.conf.get("spark.sql.sources.bucketing.maxBuckets"))
        out = df.write.bucketBy(min(n_parts(self.spark), most), *by).option("path", self.path).option("compression", "zstd")
        _written(self.spark, lambda: out.format("parquet").saveAsTable(self.name))
        self.rows = self.spark.table(self.name)

    def drop(self) -> None:
        self.spark.sql(f"DROP TABLE IF EXISTS {self.name}")
        path = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)


def _written(spark: SparkSession, write: Callable[[], None]) -> None:
    """Run ``write``; the shuffle files of its query go as soon as it ends."""
    before = spark.conf.get(_CLEANUP, None)
    if spark.conf.isModifiable(_CLEANUP):
        spark.conf.set(_CLEANUP, "true")
    try:
        write()
    finally:
        if spark.conf.isModifiable(_CLEANUP):
            spark.conf.unset(_CLEANUP) if before is None else spark.conf.set(_CLEANUP, before)


def sheltered(docs: DataFrame, *own: str) -> tuple[DataFrame, Callable[[DataFrame], DataFrame]]:
    """``docs`` with its columns that begin with two underscores under other names, and the way back.

    Such names are the operators' working names; the columns ``own`` keep theirs.
    """
    moved = {c: f"column {i} of the input" for i, c in enumerate(docs.columns) if c.startswith("__") and c not in own}
    return docs.withColumnsRenamed(moved), lambda out: out.withColumnsRenamed({v: k for k, v in moved.items()})


def n_parts(spark: SparkSession, at_least: int = 1) -> int:
    return max(at_least, int(spark.conf.get("spark.sql.shuffle.partitions")))


def text_column(batch: pa.RecordBatch, name: str) -> list[str]:
    """Strings of an Arrow column, null as empty."""
    return [x or "" for x in batch.column(name).to_pylist()]


def grouped(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.Table]:
    """Whole groups of consecutive equal ``keys`` from batches that arrive sorted by them.

    Only the open group is held, so memory follows the largest group, not the partition.
    """
    held: list[pa.Table] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        t = pa.Table.from_batches([batch])
        cols = [t.column(k).combine_chunks().to_numpy(zero_copy_only=False) for k in keys]
        cut = np.zeros(t.num_rows, dtype=bool)
        for c in cols:
            cut[1:] |= c[1:] != c[:-1]
        first = tuple(c[0] for c in cols)
        starts = np.flatnonzero(cut).tolist()
        if last is not None and first != last:
            yield pa.concat_tables(held)
            held = []
        pos = 0
        for s in starts:
            held.append(t.slice(pos, s - pos))
            yield pa.concat_tables(held)
            held, pos = [], s
        held.append(t.slice(pos))
        last = tuple(c[-1] for c in cols)
    if held:
        yield pa.concat_tables(held)


def spread(df: DataFrame, *keys: str, parts: int | None = None) -> DataFrame:
    """Hash-distribute by ``keys`` and sort within partitions, for ``grouped``."""
    cols = [F.col(k) for k in keys]
    return df.repartition(parts or n_parts(df.sparkSession), *cols).sortWithinPartitions(*cols)


def runs(batches: Iterator[pa.RecordBatch], keys: list[str], least: int = 2) -> Iterator[tuple[dict[str, np.ndarray], list[tuple[int, int]]]]:
    """Columns and the (lo, hi) of every whole run of equal ``keys`` with at least ``least`` rows.

    Input must be sorted by ``keys``; only the open run is carried from batch to batch. Columns come
    as numpy arrays, those that are not numbers as arrays of objects.
    """
    carry: dict[str, np.ndarray] | None = None

    def split(cols: dict[str, np.ndarray], end: bool):
        n = len(cols[keys[0]])
        cut = np.zeros(n, dtype=bool)
        for k in keys:
            cut[1:] |= cols[k][1:] != cols[k][:-1]
        starts = np.concatenate([[0], np.flatnonzero(cut)])
        stop = n if end else int(starts[-1])
        ends = np.append(starts[1:], n)
        keep = (ends - starts >= least) & (ends <= stop)
        return stop, list(zip(starts[keep].tolist(), ends[keep].tolist()))

    for batch in batches:
        if not batch.num_rows:
            continue
        cols = {}
        for name, col in zip(batch.schema.names, batch.columns):
            if pa.types.is_integer(col.type) or pa.types.is_floating(col.type) or pa.types.is_boolean(col.type):
                cols[name] = col.to_numpy(zero_copy_only=False)
            else:
                x = np.empty(len(col), dtype=object)
                x[:] = col.to_pylist()
                cols[name] = x
        if carry is not None:
            cols = {k: np.concatenate([carry[k], v]) for k, v in cols.items()}
        stop, found = split(cols, False)
        if found:
            yield cols, found
        carry = {k: v[stop:] for k, v in cols.items()}
    if carry is not None:
        _, found = split(carry, True)
        if found:
            yield carry, found


def into_cells(df: DataFrame, keys: list[str], by: str, cap: int) -> DataFrame:
    """Deal the rows of every key with two rows or more into cells of at most about 2 x ``cap`` rows.

    Adds cell_a, cell_b and side. A key of up to ``cap`` rows is one cell (0, 0), side 0. A larger
    key is cut into chunks by a hash of ``by``; every two chunks meet in one cell, as sides 1 and 2,
    and each chunk meets itself as side 0: no pair of rows is lost and no task gets a whole hot key.
    """
    sizes = df.groupBy(*keys).agg(F.count("*").alias("__n")).filter("__n > 1")
    chunks = F.ceil(F.col("__n") / cap).cast("int")
    out = df.join(sizes, keys).withColumn("__m", chunks)
    out = out.withColumn("__c", F.when(F.col("__m") == 1, 0).otherwise(F.pmod(F.xxhash64(F.col(by), F.lit(7)), F.col("__m")).cast("int")))
    out = out.withColumn("__j", F.explode(F.sequence(F.lit(0), F.col("__m") - 1)))
    side = F.when(F.col("__c") == F.col("__j"), 0).when(F.col("__c") < F.col("__j"), 1).otherwise(2)
    return out.withColumns({"cell_a": F.least("__c", "__j"), "cell_b": F.greatest("__c", "__j"), "side": side}).drop("__n", "__m", "__c", "__j")


class _Young(dict):
    """Known words; an unknown one is noted, in order, and read as None."""

    __slots__ = ("old", "noted")

    def __missing__(self, word):
        v = self.old.get(word)
        if v is None:
            self.noted.append(word)
            return None
        self[word] = v
        return v


class WordTable:
    """What has been worked out per word, kept in two generations of bounded size.

    When the young generation is full it becomes the old one; words met again move back, so
    frequent words stay. The table saves work and never changes a result.
    """

    def __init__(self, learn, limit: int = 400_000):
        self.learn, self.limit = learn, limit
        self._renew({})

    def _renew(self, old: dict) -> None:
        self.young = _Young()
        self.young.old, self.young.noted = old, []

    def lookup(self, lists: list[list[str]]) -> list[list]:
        """Values of all words of each list; ``learn`` gets the unknown ones as a list."""
        if len(self.young) > self.limit:
            self._renew(dict(self.young))
        young = self.young
        get, noted = young.__getitem__, young.noted
        out, upto = [], []
        for words in lists:
            out.append(list(map(get, words)))
            upto.append(len(noted))
        if noted:
            unknown = list(dict.fromkeys(noted))
            young.update(zip(unknown, self.learn(unknown)))
            later, done = map(get, noted), 0
            for k, end in enumerate(upto):
                if end > done:
                    out[k] = [next(later) if v is None else v for v in out[k]]
                    done = end
            noted.clear()
        return out


_TABLE: dict = {}


def process_table(key, make) -> WordTable:
    """The word table of this worker process for ``key``; a worker keeps one at a time, over its tasks."""
    if key not in _TABLE:
        _TABLE.clear()
        _TABLE[key] = make()
    return _TABLE[key]


def forget_tables() -> None:
    """Let go of the word table of an operator that ran in this worker before."""
    _TABLE.clear()
