"""Line de-duplication by a segment-partition edit join.

Two lines are linked if their edit distance is at most ``threshold`` (equal lines are one node). A
line is cut into ``threshold + 1`` segments of nearly equal length; a line within the threshold
must contain one of them unchanged, at a place that the lengths restrict. So every line is indexed
under (length, segment number, segment) and probes, for each length up to ``threshold`` shorter,
the few substrings that can match. Only signatures that two lines share go on; their lines meet in
cells of bounded size, where character counts rule out most pairs and a banded bit-parallel edit
distance decides the rest. Cells give spanning links, not all pairs.

Of each connected class the first line, by (key, line number), stays.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Bucketed, forget_tables, n_parts, runs, sheltered, stage, table
from .components import components
from .simhash import Forest

THRESHOLD, MIN_CHARS = 2, 20
#: Lines of one side of a verification cell.
CELL = 600
_BUCKETS = 64
LAST = (1 << 63) - 1


def within_edits(a: str, b: str, k: int) -> bool:
    """Is the edit distance at most ``k``? Bit-parallel over a band of 2k + 1 diagonals.

    Bit ``d + k`` of level ``e`` says that the diagonal ``d`` (characters of b read minus of a) can
    be reached up to the current character of ``a`` with ``e`` edits.
    """
    if abs(len(a) - len(b)) > k:
        return False
    i, n = 0, min(len(a), len(b))
    while i < n and a[i] == b[i]:
        i += 1
    j = 0
    while j < n - i and a[len(a) - 1 - j] == b[len(b) - 1 - j]:
        j += 1
    a, b = a[i : len(a) - j], b[i : len(b) - j]
    if not a or not b:
        return max(len(a), len(b)) <= k
    band = (1 << (2 * k + 1)) - 1
    where: dict[str, int] = {}  # bit p + k: b[p] is the character
    for p, c in enumerate(b):
        where[c] = where.get(c, 0) | 1 << (p + k)
    inside = ((1 << len(b)) - 1) << k

    def spread(levels: list[int], r: int) -> list[int]:
        """Insertions: go on to the next diagonal, within b."""
        ok = (((inside << 1) | (1 << k)) >> r) & band  # diagonals whose count of read characters is 0..len(b)
        for e in range(1, k + 1):
            levels[e] |= (levels[e - 1] << 1 | levels[e - 1]) & ok
        return [x & ok for x in levels]

    levels = spread([1 << k] + [0] * k, 0)
    for r, c in enumerate(a):
        eq = (where.get(c, 0) >> r) & band  # diagonals on which the next characters agree
        nxt = [levels[0] & eq]
        for e in range(1, k + 1):
            # same diagonal: match or replacement; one diagonal lower: the character of a is deleted
            nxt.append(levels[e] & eq | levels[e - 1] | levels[e - 1] >> 1)
        levels = spread(nxt, r + 1)
        if not any(levels):
            return False
    return bool(levels[k] >> (len(b) - len(a) + k) & 1)


def segments(n: int, parts: int) -> list[tuple[int, int]]:
    """(start, length) of the segments of a line of ``n`` characters; the last ones are longer."""
    q, r = divmod(n, parts)
    out, at = [], 0
    for i in range(parts):
        size = q + (r >= parts - i)
        out.append((at, size))
        at += size
    return out


@lru_cache(maxsize=100_000)
def places(n: int, k: int) -> list[tuple[bytes, bool, int, int]]:
    """(prefix, own, from, to) of the signatures of a line of ``n`` characters.

    The own segments serve as index entries and as look-ups; the rest are the substrings at which a
    segment of a line up to ``k`` characters shorter can lie.
    """
    out = []
    for gap in range(min(k, n - 1) + 1):
        for i, (p, size) in enumerate(segments(n - gap, k + 1)):
            for o in range(max(-i, gap - (k - i)), min(i, gap + (k - i)) + 1):
                if p + o >= 0 and p + o + size <= n:
                    out.append((b"%d:%d:" % (n - gap, i), gap == 0 and o == 0, p + o, p + o + size))
    return out


def _chars(lines: list[str]) -> np.ndarray:
    out = np.zeros((len(lines), _BUCKETS), np.int32)
    for i, s in enumerate(lines):
        out[i] = np.bincount(np.frombuffer(s.encode("utf-32-le"), np.uint32) % _BUCKETS, minlength=_BUCKETS)
    return out


def line_links(lines: DataFrame, threshold: int = THRESHOLD, cell: int = CELL, place: tuple[str, ...] = ("lid",)) -> DataFrame:
    """(a, b): links between the distinct ``lines`` (lid, line) that keep every class connected.

    ``place`` names the key by which ``lines`` is stored; texts are fetched by it.
    """
    spark = lines.sparkSession
    parts = n_parts(spark)

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget_tables()
        digest = xxhash.xxh3_64_intdigest
        for batch in batches:
            for lo in range(0, batch.num_rows, 5000):
                part = batch.slice(lo, 5000)
                sig, own, per = [], [], []
                for s in part.column("line").to_pylist():
                    at = places(len(s), threshold)
                    sig += [digest(x + s[a:b].encode()) for x, _, a, b in at]
                    own += [o for _, o, _, _ in at]
                    per.append(len(at))
                lid = np.repeat(part.column("lid").to_numpy(), per)
                yield pa.RecordBatch.from_arrays([pa.array(np.array(sig, np.uint64).view(np.int64)), pa.array(lid), pa.array(own, pa.bool_())], names=["sig", "lid", "own"])

    sigs = lines.select("lid", "line").mapInArrow(sign, "sig long, lid long, own boolean").repartition(parts, "sig").sortWithinPartitions("sig")

    def shared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for cols, found in runs(batches, ["sig"]):
            out: list[list] = [[], [], [], [], []]
            lid, mine = cols["lid"], cols["own"].astype(bool)
            for lo, hi in found:
                own, ask = np.unique(lid[lo:hi][mine[lo:hi]]), np.unique(lid[lo:hi])
                if not len(own) or len(ask) < 2:
                    continue
                a, b = -(-len(own) // cell), -(-len(ask) // cell)
                for side, ids, n, other in ((False, own, a, b), (True, ask, b, a)):
                    for i, x in enumerate(ids.tolist()):
                        for j in range(other):
                            u, v = (i % n, j) if not side else (j, i % n)
                            for o, y in zip(out, (int(cols["sig"][lo]), u, v, side, x)):
                                o.append(y)
            types = (pa.int64(), pa.int32(), pa.int32(), pa.bool_(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(o, t) for o, t in zip(out, types)], names=["sig", "u", "v", "probe", "lid"])

    met = stage(sigs.mapInArrow(shared, "sig long, u int, v int, probe boolean, lid long"), "signatures")
    keys = ["sig", "u", "v"]
    if "lid" not in place:
        met = met.join(lines.select("lid", *place), "lid")
    cells = met.join(lines.select(*place, "line"), list(place)).select(*keys, "probe", "lid", "line")
    cells = cells.repartition(parts, *keys).sortWithinPartitions(*keys)

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for cols, found in runs(batches, keys):
            a, b = [], []
            for lo, hi in found:
                probe = cols["probe"][lo:hi].astype(bool)
                ids, text = cols["lid"][lo:hi], cols["line"][lo:hi]
                own, ask = np.flatnonzero(~probe), np.flatnonzero(probe)
                if not len(own) or not len(ask):
                    continue
                forest = Forest()
                left = _chars(text[own].tolist())
                for q in ask.tolist():
                    s, x = text[q], int(ids[q])
                    if len(own) > 4:
                        h = _chars([s])[0]
                        maybe = own[np.abs(left - h).sum(axis=1) <= 2 * threshold].tolist()
                    else:
                        maybe = own.tolist()
                    for r in maybe:
                        y = int(ids[r])
                        if x != y and forest.find(x) != forest.find(y) and within_edits(text[r], s, threshold):
                            forest.link(x, y)
                            a.append(x)
                            b.append(y)
            yield pa.RecordBatch.from_arrays([pa.array(o, pa.int64()) for o in (a, b)], names=["a", "b"])

    return cells.mapInArrow(verify, "a long, b long")


def dedup_lines(docs: DataFrame, key: str = "doc_id", text: str = "text", threshold: int = THRESHOLD, min_chars: int = MIN_CHARS) -> DataFrame:
    """All columns of ``docs``, ``text`` without repeated lines, and n_lines, n_removed, removed (line numbers).

    Lines end at a line feed; white space at their ends does not count. Lines of fewer than
    ``min_chars`` characters always stay and link with nothing. Lines are equal if 128 bits of hash
    are. Null text stays null with 0 lines; the empty text is one short line. Rows that repeat a
    key are told apart by their text; rows equal in both are one document. A null key ranks last.
    An empty table gives an empty result. Clashing extra columns are replaced.
    """
    docs = docs.drop(*[c for c in ("n_lines", "n_removed", "removed") if c in docs.columns and c != text])
    docs, restored = sheltered(docs, key, text)
    keyed = docs.withColumns({"__d": F.coalesce(F.col(key).cast("long"), F.lit(LAST)), "__uid": F.xxhash64(key, text)})
    every = keyed.select("__d", "__uid", F.posexplode(F.split(text, "\n"))).select("__d", "__uid", F.col("pos").alias("no"), F.btrim("col", F.lit(" \t\r\f\x0b")).alias("line"))
    every = every.filter(F.length("line") >= min_chars)
    every = every.withColumns({"h1": F.xxhash64("line"), "h2": F.xxhash64(F.lit(1), "line")})
    distinct = every.groupBy("h1", "h2").agg(F.min(F.struct("__d", "__uid", "no")).alias("rep"), F.count("*").alias("copies"), F.first("line").alias("line"))
    stored = Bucketed(distinct.withColumn("lid", F.monotonically_increasing_id()), ["h1", "h2"], "lines")
    distinct = stored.rows
    comp = components(line_links(distinct, threshold, place=("h1", "h2")))
    classed = distinct.select("lid", "h1", "h2", "rep", "copies").join(comp, F.col("lid") == comp.node, "left")
    classed = classed.filter("component IS NOT NULL OR copies > 1")  # a single line without links is a class of one, of which nothing goes
    classed = classed.withColumn("g", F.coalesce("component", "lid"))
    first = classed.groupBy("g").agg(F.min("rep").alias("keep"), F.sum("copies").alias("of")).filter("of > 1")
    again = classed.join(first, "g").select("h1", "h2", "keep")
    gone = every.select("__d", "__uid", "no", "h1", "h2").join(again, ["h1", "h2"]).filter(F.struct("__d", "__uid", "no") != F.col("keep"))
    gone = stage(gone.groupBy("__d", "__uid").agg(F.sort_array(F.collect_set("no")).alias("removed")).withColumnsRenamed({"__d": "__rd", "__uid": "__ru"}), "removed")
    stored.drop()
    out = keyed.join(gone, (F.col("__d") == F.col("__rd")) & (F.col("__uid") == F.col("__ru")), "left").drop("__d", "__uid", "__rd", "__ru")
    parts = F.split(text, "\n")
    kept = F.when(F.col("removed").isNull(), F.col(text)).otherwise(F.concat_ws("\n", F.filter(parts, lambda x, i: ~F.array_contains("removed", i))))
    return restored(out).withColumns({"n_lines": F.when(F.col(text).isNull(), 0).otherwise(F.size(parts)).cast("long"), "n_removed": F.when(F.col("removed").isNull(), 0).otherwise(F.size("removed")).cast("long"), text: kept})


def op9_edit_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Repeated lines removed from all ``documents``; counts and digest per document."""
    out = dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "n_lines", "n_removed", F.sha2(F.coalesce("text", F.lit("")).cast("binary"), 256).alias("kept_sha256"))
