"""SimHash near-duplicates, linked through BK-trees.

Distinct fingerprints are dealt to shards such that any two within the radius meet in at least one:
the 64 bits are cut into ``radius + e`` blocks, and every choice of ``e`` blocks is a shard key,
since a pair that differs in at most ``radius`` bits agrees on some ``e`` blocks. A shard's
fingerprints form a BK-tree whose children are keyed by their Hamming distance to the parent; a
query follows only the edges within the radius of its own distance. Shards that are too large are
cut into chunks whose trees are sent to every other chunk of the shard.

A broadcast of trees over *all* fingerprints would grow with the data, so trees go only to the
tasks of their own shard.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import forget_tables, into_cells, n_parts, runs, stage, table, text_column
from .components import components

#: Rows of a shard chunk; a task holds one tree of this size at a time.
CHUNK = 1500
MASK = (1 << 64) - 1


def fingerprint(text: str | None, shingle: int = 4, seed: int = 42) -> int:
    """64-bit SimHash of the word shingles of a text, lower-cased in A-Z only; no words: zero."""
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words])
    if len(words) <= shingle:
        hashes = [xxhash.xxh64_intdigest(joined, seed)]
    else:
        starts = [0, *ends[: len(words) - shingle].tolist()]
        stops = (ends[shingle - 1 :] - 1).tolist()
        digest = xxhash.xxh64_intdigest
        hashes = [digest(joined[a:b], seed) for a, b in zip(starts, stops)]
    ones = np.zeros(64, np.int64)
    for lo in range(0, len(hashes), 1 << 16):
        part = np.array(hashes[lo : lo + (1 << 16)], dtype="<u8")
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    set_ = np.packbits(2 * ones > len(hashes), bitorder="little")
    return int.from_bytes(set_.tobytes(), "little")


def fingerprints(docs: DataFrame, key: str = "doc_id", text: str = "text", shingle: int = 4, seed: int = 42, carry: list[str] | None = None) -> DataFrame:
    """``key``, ``carry`` columns and fp (the fingerprint as a signed long) of every row."""
    cols = [key, *(carry or [])]
    src = docs.select(*[docs[c] for c in cols], docs[text].alias("__text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget_tables()
        for batch in batches:
            fps = np.array([fingerprint(t, shingle, seed) for t in text_column(batch, "__text")], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(c) for c in cols] + [pa.array(fps)], names=[*cols, "fp"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in src.schema if f.name != "__text")
    return src.mapInArrow(run, f"{fields}, fp long")


class BKTree:
    """Metric tree over 64-bit integers under Hamming distance."""

    def __init__(self):
        self.root: list | None = None

    def add(self, x: int) -> None:
        if self.root is None:
            self.root = [x, {}]
            return
        node = self.root
        while True:
            d = (x ^ node[0]).bit_count()
            if d == 0:
                return
            nxt = node[1].get(d)
            if nxt is None:
                node[1][d] = [x, {}]
                return
            node = nxt

    def within(self, x: int, radius: int) -> list[int]:
        found: list[int] = []
        todo = [self.root] if self.root else []
        while todo:
            v, kids = todo.pop()
            d = (x ^ v).bit_count()
            if d <= radius:
                found.append(v)
            if kids:
                if len(kids) <= 2 * radius:
                    todo += [n for k, n in kids.items() if -radius <= k - d <= radius]
                else:
                    todo += [kids[k] for k in range(max(1, d - radius), d + radius + 1) if k in kids]
        return found


class Forest:
    """Union-find that reports whether a link joined two sets."""

    def __init__(self):
        self.up: dict = {}

    def find(self, x):
        up = self.up
        while (p := up.get(x, x)) != x:
            up[x] = up.get(p, p)
            x = p
        return x

    def link(self, a, b) -> bool:
        a, b = self.find(a), self.find(b)
        if a == b:
            return False
        self.up[max(a, b)] = min(a, b)
        return True


def block_masks(radius: int, equal: int) -> list[int]:
    """Masks of every choice of ``equal`` blocks out of ``radius + equal``."""
    n = radius + equal
    edges = [64 * i // n for i in range(n + 1)]
    blocks = [((1 << b) - 1) ^ ((1 << a) - 1) for a, b in zip(edges, edges[1:])]
    return [sum(c) for c in combinations(blocks, equal)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def links(fps: DataFrame, radius: int = 4, chunk: int = CHUNK, equal: int | None = None) -> DataFrame:
    """(a, b): links between the distinct ``fp`` values that keep every group within ``radius`` connected.

    Each shard gives a spanning forest of its links, not all pairs. ``equal`` (blocks that must
    agree) only sets the cost: by default it follows the number of fingerprints, so that shards
    stay small; every value gives the same groups.
    """
    if equal is None:
        n, equal = fps.count(), 1
        while equal < 4 and n > 64 << (64 * equal // (radius + equal)):
            equal += 1
    masks = F.array(*[F.struct(F.lit(i).alias("block"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("part")) for i, m in enumerate(block_masks(radius, equal))])
    rows = fps.select("fp", F.inline(masks))
    cells = into_cells(rows, ["block", "part"], "fp", chunk)
    keys = ["block", "part", "cell_a", "cell_b"]
    cells = cells.repartition(n_parts(fps.sparkSession), *keys).sortWithinPartitions(*keys, "side")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for cols, found in runs(batches, keys):
            a, b = [], []
            fp, side = cols["fp"].view(np.uint64), cols["side"]
            for lo, hi in found:
                tree, forest = BKTree(), Forest()
                for x, s in zip(fp[lo:hi].tolist(), side[lo:hi].tolist()):
                    if s != 1:
                        for y in tree.within(x, radius):
                            if forest.link(x, y):
                                a.append(x)
                                b.append(y)
                    if s != 2:
                        tree.add(x)
            yield pa.RecordBatch.from_arrays([pa.array(np.array(x, np.uint64).view(np.int64)) for x in (a, b)], names=["a", "b"])

    return cells.select(*keys, "side", "fp").mapInArrow(run, "a long, b long")


def near_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text", shingle: int = 4, seed: int = 42, radius: int = 4, carry: list[str] | None = None) -> DataFrame:
    """``key``, fp and component_id (least ``key`` reachable) of every row, with ``carry`` columns.

    Null text counts as empty; rows without words have fingerprint zero and are linked like any
    other. Copies share a fingerprint and so a node. A null key takes part but is never a
    component_id unless its whole group has none (then null). An empty table gives an empty result.
    """
    marks = stage(fingerprints(docs, key, text, shingle, seed, carry), "fingerprints")
    nodes = stage(marks.groupBy("fp").agg(F.min(key).alias("rep")), "nodes")
    comp = components(links(nodes.select("fp"), radius))
    grouped = nodes.join(comp, nodes.fp == comp.node, "left").select("fp", "rep", F.coalesce("component", "fp").alias("__g"))
    least = grouped.groupBy("__g").agg(F.min("rep").alias("component_id"))
    final = grouped.join(least, "__g").select("fp", "component_id")
    return marks.join(final, "fp").select(*[marks[c] for c in [key, *(carry or [])]], "fp", "component_id")


def op3_simhash_bktree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprint and near-duplicate group of all ``documents``."""
    out = near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
