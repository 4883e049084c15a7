"""Exact removal of repeated word windows with suffix automata.

A window is ``window`` consecutive words. It is removed where its word sequence also starts in a
document with a smaller id. Reference automata over all documents could not be broadcast, so the
references are cut by content:

1. Every window elects an anchor: among its short word grams the one with the least hash, leftmost
   first. Equal windows elect equal anchors at equal offsets, and neighbouring windows mostly share
   theirs, so a document has few anchors.
2. Anchors that occur in one document only are dropped by an aggregation that combines map-side.
3. The occurrences of an anchor are one reference shard. Its contexts - the words of the windows
   that elected it - are taken in ascending document order: each is first streamed through the
   suffix automaton of the smaller documents for its matching statistics (a statistic of at least
   ``window`` ends a removed window) and then added to it.
4. An anchor with many occurrences is cut into several shards; the windows that a shard has seen
   for the first time meet once more across the anchor's shards, as (128-bit hash, least document).

So every window is compared with all smaller documents, and no task receives a whole hot passage.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import n_parts, runs, stage, table, text_column

WINDOW, GRAM = 50, 8
#: Occurrences of an anchor in one reference shard.
SHARD = 1000
LAST = (1 << 63) - 1
_WORDS = 200_000


class SuffixAutomaton:
    """Online generalised suffix automaton over hashable tokens."""

    __slots__ = ("go", "link", "size")

    def __init__(self):
        self.go: list[dict] = [{}]
        self.link = [-1]
        self.size = [0]

    def add(self, tokens) -> None:
        go, link, size = self.go, self.link, self.size
        last = 0
        for c in tokens:
            nxt = go[last].get(c)
            if nxt is not None and size[nxt] == size[last] + 1:
                last = nxt
                continue
            cur = -1
            if nxt is None:
                cur = len(go)
                go.append({})
                link.append(0)
                size.append(size[last] + 1)
            p = last
            while p != -1 and c not in go[p]:
                go[p][c] = cur
                p = link[p]
            if p == -1:
                last = cur
                continue
            q = go[p][c]
            if size[q] == size[p] + 1:
                link[cur] = q
                last = cur
                continue
            twin = len(go)
            go.append(dict(go[q]))
            link.append(link[q])
            size.append(size[p] + 1)
            while p != -1 and go[p].get(c) == q:
                go[p][c] = twin
                p = link[p]
            link[q] = twin
            if cur == -1:  # the sequence so far is known: its own state is the split-off one
                last = twin
            else:
                link[cur] = twin
                last = cur

    def statistics(self, tokens) -> list[int]:
        """For each position, the length of the longest match that ends there."""
        go, link, size = self.go, self.link, self.size
        state = length = 0
        out = []
        for c in tokens:
            while state and c not in go[state]:
                state = link[state]
                length = size[state]
            nxt = go[state].get(c)
            if nxt is not None:
                state, length = nxt, length + 1
            out.append(length)
        return out


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def anchors(h: np.ndarray, window: int = WINDOW, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hash, first window start, last window start) of the anchors of one document's word hashes."""
    n = len(h) - window + 1
    if n <= 0:
        return (np.zeros(0, np.uint64),) + (np.zeros(0, np.int64),) * 2
    m = len(h) - gram + 1
    g = np.zeros(m, np.uint64)
    for j in range(gram):
        g = g * np.uint64(0x9E3779B97F4A7C15) + h[j : j + m]
    g = _mix(g)
    span = window - gram + 1
    # leftmost minimum over spans, by doubling: best[i] covers g[i : i + width]
    best, width = np.arange(m), 1
    while width * 2 <= span:
        a, b = best[: len(best) - width], best[width:]
        best, width = np.where(g[b] < g[a], b, a), width * 2
    a, b = best[:n], best[span - width : span - width + n]
    pick = np.where(g[b] < g[a], b, a)
    first = np.flatnonzero(np.concatenate([[True], pick[1:] != pick[:-1]]))
    return g[pick[first]], first, np.append(first[1:], n) - 1


def _words_hashed(words: list[bytes], known: dict[bytes, int]) -> np.ndarray:
    if len(known) > _WORDS:
        known.clear()
    out = list(map(known.get, words))
    if None in out:
        digest = xxhash.xxh3_64_intdigest
        for i, x in enumerate(out):
            if x is None:
                out[i] = known[words[i]] = digest(words[i])
    return np.array(out, np.uint64)


def repeated_windows(docs: DataFrame, key: str = "doc_id", text: str = "text", window: int = WINDOW, gram: int = GRAM, shard: int = SHARD) -> tuple[DataFrame, DataFrame]:
    """Keyed documents (d, uid, text and all columns) and their removed windows (d, uid, a, b): starts a to b.

    A null key ranks after every other: its windows can be removed but remove none.
    """
    spark = docs.sparkSession
    parts = n_parts(spark)
    keyed = docs.withColumns({"__d": F.coalesce(F.col(key).cast("long"), F.lit(LAST)), "__uid": F.xxhash64(key, text)})
    src = keyed.select("__d", "__uid", F.col(text).alias("__text"))

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[bytes, int] = {}
        for batch in batches:
            out: list[list] = [[], [], [], [], []]
            for d, u, t in zip(batch.column("__d").to_pylist(), batch.column("__uid").to_pylist(), text_column(batch, "__text")):
                words = t.encode().split()
                if len(words) < window:
                    continue
                h, lo, hi = anchors(_words_hashed(words, known), window, gram)
                for o, x in zip(out, (np.full(len(h), d), np.full(len(h), u), h.view(np.int64), lo.astype(np.int32), hi.astype(np.int32))):
                    o.append(x)
            if out[0]:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(o)) for o in out], names=["d", "uid", "h", "lo", "hi"])

    marks = stage(src.mapInArrow(find, "d long, uid long, h long, lo int, hi int"), "anchors")
    often = marks.groupBy("h").agg(F.min("d").alias("d0"), F.max("d").alias("d1"), F.count("*").alias("n")).filter("d0 != d1").select("h", F.ceil(F.col("n") / shard).cast("int").alias("m"))
    often = stage(often, "shared")  # read back, so that the join deals both sides anew and hot anchors can be split
    shared = marks.join(often, "h").groupBy("d", "uid").agg(F.collect_list(F.struct("h", "lo", "hi", "m")).alias("spans"))
    with_text = shared.join(src, (F.col("d") == F.col("__d")) & (F.col("uid") == F.col("__uid"))).select("d", "uid", "spans", "__text")

    def contexts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in range(0, batch.num_rows, 100):
                part = batch.slice(r, 100)
                out: list[list] = [[], [], [], [], [], []]
                for d, u, spans, t in zip(*(part.column(c).to_pylist() for c in ("d", "uid", "spans", "__text"))):
                    words = t.encode().split()
                    for s in spans:
                        for o, x in zip(out, (s["h"], (u ^ s["h"]) % s["m"], s["m"], d, u, s["lo"])):
                            o.append(x)
                        out.append(b" ".join(words[s["lo"] : s["hi"] + window]))
                rows = out[6:]
                types = (pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int32())
                yield pa.RecordBatch.from_arrays([pa.array(o, t) for o, t in zip(out[:6], types)] + [pa.array(rows, pa.binary())], names=["h", "c", "m", "d", "uid", "lo", "words"])

    cells = with_text.mapInArrow(contexts, "h long, c int, m int, d long, uid long, lo int, words binary")
    cells = cells.repartition(parts, "h", "c").sortWithinPartitions("h", "c", "d")

    def match(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        types = (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int64())
        names = ["h", "d", "uid", "a", "b", "h1", "h2"]
        out: list[list] = [[] for _ in types]

        def put(*row):
            for o, x in zip(out, row):
                o.append(x)

        def flush() -> pa.RecordBatch:
            batch = pa.RecordBatch.from_arrays([pa.array(o, t) for o, t in zip(out, types)], names=names)
            for o in out:
                o.clear()
            return batch

        for cols, found in runs(batches, ["h", "c"], least=1):
            for lo, hi in found:
                h, many = int(cols["h"][lo]), cols["m"][lo] > 1
                if hi - lo == 1 and not many:
                    continue
                auto = SuffixAutomaton()
                seen: set[bytes] = set()
                fresh: list[bytes] = []  # seen, but not yet in the automaton: copies alone never need one
                waiting: list[bytes] = []
                at_d = None
                for r in range(lo, hi):
                    d, u, s, raw = int(cols["d"][r]), int(cols["uid"][r]), int(cols["lo"][r]), cols["words"][r]
                    if d != at_d:
                        for x in waiting:
                            if x not in seen:
                                seen.add(x)
                                fresh.append(x)
                        waiting, at_d = [], d
                    if raw in seen:
                        put(h, d, u, s, s + raw.count(b" ") + 1 - window, None, None)
                        continue
                    words = raw.split()
                    n = len(words) - window + 1
                    waiting.append(raw)
                    hit = [False] * n
                    if seen:
                        for x in fresh:
                            auto.add(x.split())
                        fresh = []
                        hit = [x >= window for x in auto.statistics(words)[window - 1 :]]
                    i = 0
                    while i < n:
                        if hit[i]:
                            j = i
                            while j + 1 < n and hit[j + 1]:
                                j += 1
                            put(h, d, u, s + i, s + j, None, None)
                            i = j
                        elif many:
                            x = xxhash.xxh128_intdigest(b" ".join(words[i : i + window]))
                            put(h, d, u, s + i, s + i, (x >> 64) - (1 << 63), (x & (1 << 64) - 1) - (1 << 63))
                        i += 1
                    if len(out[0]) > 20_000:
                        yield flush()
            yield flush()

    seen = stage(cells.mapInArrow(match, "h long, d long, uid long, a int, b int, h1 long, h2 long"), "matches")
    first = seen.filter("h1 is not null")
    least = first.groupBy("h1", "h2").agg(F.min("d").alias("d0"), F.max("d").alias("d1")).filter("d0 != d1").select("h1", "h2", "d0")
    least = stage(least, "first-seen")
    later = first.join(least, ["h1", "h2"]).filter("d > d0").select("d", "uid", "a", "b")
    return keyed, seen.filter("h1 is null").select("d", "uid", "a", "b").union(later)


def remove_repeats(docs: DataFrame, key: str = "doc_id", text: str = "text", window: int = WINDOW, gram: int = GRAM, shard: int = SHARD) -> DataFrame:
    """All columns of ``docs`` with ``text`` reduced to the kept words, and n_words, n_removed, spans.

    ``spans`` lists the maximal removed word ranges [from, to). Words are runs of bytes other than
    ASCII white space; kept words are joined by one space. Null text: no words. Rows that repeat a
    key have equal rank, so they do not remove each other's windows; texts shorter than a window
    are never cut. An empty table gives an empty result. Clashing extra columns are replaced.
    """
    docs = docs.drop(*[c for c in ("n_words", "n_removed", "spans") if c in docs.columns and c != text])
    keyed, gone = repeated_windows(docs, key, text, window, gram, shard)
    ranges = gone.groupBy("d", "uid").agg(F.collect_list(F.struct("a", "b")).alias("__gone"))
    ranges = ranges.select(F.col("d").alias("__rd"), F.col("uid").alias("__ru"), "__gone")
    joined = keyed.join(ranges, (F.col("__d") == F.col("__rd")) & (F.col("__uid") == F.col("__ru")), "left").drop("__d", "__uid", "__rd", "__ru")
    names = docs.columns

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (b.slice(lo, 500) for b in batches for lo in range(0, b.num_rows, 500)):
            kept, total, removed, spans = [], [], [], []
            for t, g in zip(text_column(batch, text), batch.column("__gone").to_pylist()):
                words = t.encode().split()
                merged: list[list[int]] = []
                for a, b in sorted((r["a"], r["b"] + window) for r in g or []):
                    if merged and a <= merged[-1][1]:
                        merged[-1][1] = max(b, merged[-1][1])
                    else:
                        merged.append([a, b])
                out, at = [], 0
                for a, b in merged:
                    out += words[at:a]
                    at = b
                out += words[at:]
                kept.append(b" ".join(out).decode())
                total.append(len(words))
                removed.append(len(words) - len(out))
                spans.append([{"start": a, "stop": b} for a, b in merged])
            cols = [pa.array(kept, pa.string()) if c == text else batch.column(c) for c in names]
            kind = pa.list_(pa.struct([("start", pa.int32()), ("stop", pa.int32())]))
            yield pa.RecordBatch.from_arrays([*cols, pa.array(total, pa.int64()), pa.array(removed, pa.int64()), pa.array(spans, kind)], names=[*names, "n_words", "n_removed", "spans"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    return joined.mapInArrow(cut, f"{fields}, n_words long, n_removed long, spans array<struct<start:int,stop:int>>")


def op5_suffix_automata(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Repeated 50-word windows removed from all ``documents``; digests per document."""
    out = remove_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "n_words", "n_removed", F.sha2(F.col("text").cast("binary"), 256).alias("kept_sha256"))
