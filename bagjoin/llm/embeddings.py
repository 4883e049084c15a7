"""Embedding near-duplicates by spherical-cap filters with random product codes.

A filter is a direction; a vector belongs to the filters whose inner product with it exceeds a
threshold. Directions are the sums of one code word per block of coordinates, so the filters of a
vector are listed without trying them all: the inner products with each block's code words are
sorted, and only combinations that can still exceed the threshold are opened. The threshold is each
vector's own, namely its k-th best inner product, so no vector is without filters. There are
several codes under independent rotations, and k is raised until pairs at the bound, run through
these very codes, miss each other at most at the target rate, whatever the number of vectors. Up to
``CHUNK`` vectors of a label, and where no k reaches the target, all pairs are compared. Vectors that
share a filter and a label are compared exactly, in double precision.

Equal vectors are one node with a multiplicity, so copies are counted without being paired. A pair
that shares several filters is counted in the least of them.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import into_cells, n_parts, runs, stage, table
from .components import components
from .simhash import Forest

#: Rows of a chunk of a filter's vectors.
CHUNK = 800
#: Filters that a vector belongs to at least, and vectors a filter should hold.
FILTERS, HELD = 24, 48
#: Independent codes, target rate of missed pairs at the bound, pairs it is measured on, most filters of a vector.
CODES, MISS, TRIALS, MOST = 2, 0.0005, 4000, 512


class CapCode:
    """Random product code over ``blocks`` groups of coordinates after a random rotation."""

    def __init__(self, dim: int, size: int, threshold: float, blocks: int = 2, seed: int = 17):
        rng = np.random.default_rng(seed)
        self.rotation = np.linalg.qr(rng.normal(size=(dim, dim)))[0]
        self.cuts = [dim * i // blocks for i in range(blocks + 1)]
        self.words = []
        for a, b in zip(self.cuts, self.cuts[1:]):
            w = rng.normal(size=(size, b - a))
            self.words.append(w / np.linalg.norm(w, axis=1, keepdims=True) / math.sqrt(blocks))
        self.size, self.threshold = size, threshold

    def decode(self, unit: np.ndarray) -> list[int]:
        """All filters whose inner product with the unit vector reaches the threshold, ascending."""
        x = self.rotation @ unit
        parts = []
        for (a, b), w in zip(zip(self.cuts, self.cuts[1:]), self.words):
            s = w @ x[a:b]
            o = np.argsort(-s, kind="stable")
            parts.append((o, s[o]))
        best = [p[1][0] for p in parts]
        ids, sums = np.zeros(1, np.int64), np.zeros(1)
        for i, (o, s) in enumerate(parts):
            rest = sum(best[i + 1 :])
            need = self.threshold - rest - sums
            n = np.searchsorted(-s, -need, side="right")  # how many words still reach the threshold
            row = np.repeat(np.arange(len(ids)), n)
            col = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
            ids, sums = ids[row] * self.size + o[col], sums[row] + s[col]
        return np.sort(ids).tolist()

    def best(self, units: np.ndarray, k: int) -> np.ndarray:
        """The ``k`` filters of largest inner product of every row, in no order."""
        x = units @ self.rotation.T
        words, sums = [], []
        for (a, b), w in zip(zip(self.cuts, self.cuts[1:]), self.words):
            s = x[:, a:b] @ w.T
            n = min(k, self.size)
            o = np.argpartition(-s, n - 1, axis=1)[:, :n]
            o = np.take_along_axis(o, np.argsort(-np.take_along_axis(s, o, 1), axis=1, kind="stable"), 1)
            words.append(o)
            sums.append(np.take_along_axis(s, o, 1))
        # the words ranked (i, j) are beaten by (i + 1)(j + 1) - 1 other choices
        ranks = np.zeros((1, 0), np.int64)
        for o in words:
            room = k // np.prod(ranks + 1, axis=1)
            n = np.minimum(room, o.shape[1])
            row = np.repeat(np.arange(len(ranks)), n)
            col = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
            ranks = np.column_stack([ranks[row], col])
        total = sum(s[:, r] for s, r in zip(sums, ranks.T))
        ids = np.zeros((len(x), len(ranks)), np.int64)
        for o, r in zip(words, ranks.T):
            ids = ids * self.size + o[:, r]
        if ids.shape[1] <= k:
            return ids
        return np.take_along_axis(ids, np.argpartition(-total, k - 1, axis=1)[:, :k], 1)


class Filters:
    """Several product codes; lists ``k`` filters of each for a vector, or one for all if ``k`` is 0."""

    def __init__(self, n: int, dim: int, k: int, held: float = HELD, codes: int = CODES, seed: int = 17):
        blocks = 2 if dim < 24 or n * k / held < 1e8 else 3
        size = max(2, math.ceil((n * k / held) ** (1 / blocks)))
        self.k, self.count = k, size**blocks
        self.codes = [CapCode(dim, size, -1.0, blocks, seed + i) for i in range(codes)] if k else []

    def of(self, units: np.ndarray) -> np.ndarray:
        if not self.codes:
            return np.zeros((len(units), 1), np.int64)
        out = []
        for lo in range(0, len(units), 256):
            out.append(np.hstack([c.best(units[lo : lo + 256], self.k) + i * self.count for i, c in enumerate(self.codes)]))
        return np.sort(np.vstack(out), axis=1)

    def missed(self, cosine: float, trials: int = TRIALS, seed: int = 1) -> float:
        """Share of random pairs at ``cosine`` that have no filter in common."""
        rng = np.random.default_rng(seed)
        u, v = rng.normal(size=(2, trials, self.codes[0].rotation.shape[0]))
        u /= np.linalg.norm(u, axis=1, keepdims=True)
        v -= (v * u).sum(axis=1, keepdims=True) * u
        v /= np.linalg.norm(v, axis=1, keepdims=True)
        a, b = self.of(u), self.of(cosine * u + math.sqrt(1 - cosine * cosine) * v)
        return 1 - np.mean([not set(x).isdisjoint(y) for x, y in zip(a.tolist(), b.tolist())])


def filters_for(n: int, dim: int, cosine: float, filters: float = FILTERS, held: float = HELD, seed: int = 17) -> Filters:
    """Filters for ``n`` vectors that lose at most ``MISS`` of the pairs at ``cosine``, at least ``filters`` per vector.

    The rate is measured on the codes themselves. One filter for all (nothing lost) for up to
    ``CHUNK`` vectors, in few dimensions, and if ``MOST`` filters per vector do not reach the rate.
    """
    k = max(1, math.ceil(filters / CODES))
    while n > CHUNK and dim >= 8 and 0 < cosine < 1 and k * CODES <= MOST:
        out = Filters(n, dim, k, held, seed=seed)
        if out.missed(cosine) <= MISS:
            return out
        k = math.ceil(k * 1.3)
    return Filters(n, dim, 0)


def _usable(c):
    bad = F.exists(c, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return c.isNotNull() & (F.size(c) > 0) & ~F.coalesce(bad, F.lit(True)) & F.exists(c, lambda x: x != 0)


def near_vectors(vectors: DataFrame, key: str = "vec_id", vector: str = "embedding", label: str = "label", cosine: float = 0.93, filters: float = FILTERS, held: float = HELD, seed: int = 17) -> DataFrame:
    """(key, n_links, component_id, kept) of every row; links need equal, non-null labels.

    Vectors that are null, empty, zero or hold null or non-finite components link with nothing, and
    neither do vectors of different length. Equal vectors of a label are linked with each other.
    Rows that repeat a key are one vertex per row with that key; a null key never links.
    At most about ``MISS`` of the links at the bound are lost (tests measure it), fewer above it; a
    reported link is exact.
    """
    spark = vectors.sparkSession
    src = vectors.select(vectors[key].alias("id"), vectors[vector].cast("array<double>").alias("x"), vectors[label].alias("label"))
    good = src.filter(_usable(F.col("x")) & F.col("label").isNotNull() & F.col("id").isNotNull())
    scale = F.array_max(F.transform("x", lambda v: F.abs(v)))
    good = good.withColumn("x", F.transform("x", lambda v: v + 0.0))
    nodes = stage(good.groupBy("label", "x").agg(F.min("id").alias("rep"), F.count("*").alias("copies"), F.first(scale).alias("s")).withColumn("s", F.col("s")), "vectors")
    most = nodes.groupBy("label", F.size("x").alias("d")).agg(F.count("*").alias("n")).groupBy("d").agg(F.max("n").alias("n")).collect()
    codes = {r.d: filters_for(r.n, r.d, cosine, filters, held, seed) for r in most}

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            units, lists = [], [None] * batch.num_rows
            for x, s in zip(batch.column("x").to_pylist(), batch.column("s").to_pylist()):
                v = np.array(x) / s
                units.append(v / math.sqrt(v @ v))
            dims = np.array([len(v) for v in units])
            for d in np.unique(dims).tolist():
                at = np.flatnonzero(dims == d)
                for i, fs in zip(at.tolist(), codes[d].of(np.array([units[i] for i in at])).tolist()):
                    lists[i] = fs
            fs = pa.array(lists, pa.list_(pa.int64()))
            xs = pa.array([v.astype("<f8").tobytes() for v in units], pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column("rep"), batch.column("label"), batch.column("copies"), pa.array(dims, pa.int32()), xs, fs], names=["rep", "label", "copies", "d", "x", "fs"])

    kind = dict(src.dtypes)["label"]
    coded = stage(nodes.select("rep", "label", "copies", "x", "s").mapInArrow(decode, f"rep long, label {kind}, copies long, d int, x binary, fs array<long>"), "filters")
    keys = ["lab", "f"]
    rows = coded.select(F.xxhash64("label", "d").alias("lab"), F.explode("fs").alias("f"), "rep")
    cells = into_cells(rows, keys, "rep", CHUNK).join(coded.select("rep", "copies", "x", "fs", F.col("label").cast("string").alias("name"), "d"), "rep")
    keys = [*keys, "cell_a", "cell_b"]
    cells = cells.repartition(n_parts(spark), *keys).sortWithinPartitions(*keys)

    def one_label(cols: dict[str, np.ndarray], lo: int, hi: int) -> Iterator[tuple[dict[str, np.ndarray], int, int]]:
        """The run itself, or a part per label and length where two of them have one hash."""
        names = list(zip(cols["name"][lo:hi].tolist(), cols["d"][lo:hi].tolist()))
        if len(set(names)) == 1:
            yield cols, lo, hi
            return
        for x in sorted(set(names)):
            at = [lo + i for i, y in enumerate(names) if y == x]
            yield {k: v[at] for k, v in cols.items()}, 0, len(at)

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for cols, found in runs(batches, keys):
            a, b, w = [], [], []
            for cols, lo, hi in (x for lo, hi in found for x in one_label(cols, lo, hi)):
                f, side, rep, n = cols["f"][lo], cols["side"][lo:hi], cols["rep"][lo:hi], cols["copies"][lo:hi]
                x = np.frombuffer(b"".join(cols["x"][lo:hi]), "<f8").reshape(hi - lo, -1)
                i, j = (np.flatnonzero(side == 1), np.flatnonzero(side == 2)) if side.any() else (np.arange(hi - lo),) * 2
                near = x[i] @ x[j].T >= cosine
                p, q = np.nonzero(near)
                p, q = i[p], j[q]
                if not side.any():
                    p, q = p[p < q], q[p < q]
                if not len(p):
                    continue
                fs = [frozenset(y) for y in cols["fs"][lo:hi]] if len(p) > 8 * (hi - lo) else None
                forest, count = Forest(), np.zeros(hi - lo, np.int64)
                lists = cols["fs"][lo:hi]
                for u, v in zip(p.tolist(), q.tolist()):
                    common = fs[u] & fs[v] if fs else set(lists[u]).intersection(lists[v])
                    if min(common) == f:
                        count[u] += n[v]
                        count[v] += n[u]
                    if forest.link(int(rep[u]), int(rep[v])):
                        a.append(int(rep[u]))
                        b.append(int(rep[v]))
                        w.append(None)
                for u in np.flatnonzero(count).tolist():
                    a.append(int(rep[u]))
                    b.append(None)
                    w.append(int(count[u]))
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (a, b, w)], names=["a", "b", "w"])

    found = stage(cells.select(*keys, "side", "rep", "copies", "name", "d", "x", "fs").mapInArrow(compare, "a long, b long, w long"), "links")
    counts = found.filter("w is not null").groupBy("a").agg(F.sum("w").alias("far"))
    comp = components(found.filter("b is not null"))
    info = nodes.select("label", "x", "rep", "copies").join(counts, F.col("rep") == counts.a, "left").join(comp, F.col("rep") == comp.node, "left")
    info = info.select(F.col("label").alias("l2"), F.col("x").alias("x2"), (F.col("copies") - 1 + F.coalesce("far", F.lit(0))).alias("n_links"), F.coalesce("component", "rep").alias("component_id"))
    good2 = good.select("id", "label", "x")
    linked = good2.join(info, (F.col("label") == F.col("l2")) & (F.col("x") == F.col("x2"))).select("id", "n_links", "component_id")
    alone = src.filter(~(_usable(F.col("x")) & F.col("label").isNotNull() & F.col("id").isNotNull())).select("id", F.lit(0).cast("long").alias("n_links"), F.col("id").alias("component_id"))
    out = linked.unionByName(alone)
    return out.select(F.col("id").alias(key), "n_links", "component_id", F.coalesce(F.col("id") == F.col("component_id"), F.lit(True)).alias("kept"))


def op10_cap_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Near-duplicate links and groups of all ``embeddings``."""
    return near_vectors(table(spark, sf_dir, "embeddings").select("vec_id", "embedding", "label"))
