"""Toxicity scores from the nearest labelled examples.

Labelled examples are TF-IDF vectors in a block-max inverted index: postings are in example order,
those of frequent terms cut into blocks that keep the largest weight of each term. The blocks with the
highest score bounds are opened first; then all whose bound can still reach the k-th best similarity found,
and no others, so the k nearest are exact. Their labels vote with weights that fall with
distance, and isotonic regression over leave-one-out votes turns a vote into a probability.

Terms are all words that two examples have. Document frequencies are counted over the whole corpus.
A term's idf is stretched by 1 + G / ``UNIT``, G being the likelihood-ratio statistic of the term
and the label in the examples, whichever label it speaks for: texts are mostly alike in words that
say nothing on toxicity, and without the stretch neighbours are found by those (README has figures
of both). ``UNIT`` 0 switches it off. The fit uses at most ``sample`` examples of each label (those
with the least hashes of their id) and ``terms`` terms, which bounds the index that is broadcast.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import forget_tables, stage, table, text_column

SAMPLE, TERMS, NEIGHBOURS, BLOCK = 2000, 200_000, 15, 128
#: The statistic that doubles a term's weight (about one in 50,000 terms exceeds it by chance).
UNIT = 18.0
#: Terms with the longest postings are kept as rows over all examples.
WIDE = 1024
#: Texts scored together, by number and by characters.
ROWS, CHARS = 128, 4_000_000
_WORD = re.compile(r"\w+")


def terms_of(text: str) -> list[str]:
    """Terms of a text, in order."""
    return _WORD.findall(text.lower())


def _spans(ptr: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions ptr[i]..ptr[i + 1] of every i of ``at``, and which of ``at`` each belongs to."""
    n = ptr[at + 1] - ptr[at]
    own = np.repeat(np.arange(len(at)), n)
    return np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n - ptr[at], n), own


class BlockMaxIndex:
    """Exact top-k cosine over sparse unit vectors, many queries at a time.

    ``vectors`` is (row, term, weight) arrays with rows ascending. The postings of rare terms are
    short and read whole; those of the ``wide`` most frequent terms are cut into blocks with maxima. A
    block is opened if its best rare part and its maxima together can reach the score to beat.
    """

    def __init__(self, n: int, vectors: tuple[np.ndarray, np.ndarray, np.ndarray], n_terms: int, block: int = BLOCK, probe: int = 2, wide: int = WIDE):
        self.n, self.block, self.probe, self.n_terms = n, block, probe, n_terms
        self.blocks = -(-n // block)
        rows, terms, weights = vectors
        order = np.argsort(terms, kind="stable")
        self.ids, self.weights = rows[order].astype(np.int32), weights[order]
        self.ptr = np.concatenate([[0], np.cumsum(np.bincount(terms, minlength=n_terms))]).astype(np.int64)
        self.wide = np.sort(np.argsort(-np.diff(self.ptr), kind="stable")[:wide])
        self.opened = self.asked = 0
        self._rows = None

    def __getstate__(self) -> dict:
        return self.__dict__ | {"_rows": None}

    def _blocks(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Slot of each term among the wide ones or -1, their weights by block and example, their block maxima."""
        if self._rows is None:
            slot = np.full(self.n_terms, -1, np.int64)
            slot[self.wide] = np.arange(len(self.wide))
            full = np.zeros((self.blocks, len(self.wide), self.block))
            at, own = _spans(self.ptr, self.wide)
            full[self.ids[at] // self.block, own, self.ids[at] % self.block] = self.weights[at]
            self._rows = slot, full, np.ascontiguousarray(full.max(axis=2).T)
        return self._rows

    def top(self, queries: tuple[np.ndarray, np.ndarray, np.ndarray], size: int, k: int, leave_out: np.ndarray | None = None) -> list[list[tuple[int, float]]]:
        """Up to ``k`` (example, cosine) with cosine above 0 per query, best first; ties go to the smaller number."""
        if not self.blocks or not len(queries[0]):
            return [[] for _ in range(size)]
        rows, terms, weights = queries
        slot, full, caps = self._blocks()
        wide = slot[terms] >= 0
        q = np.zeros((size, len(self.wide)))
        q[rows[wide], slot[terms[wide]]] = weights[wide]
        block, width = self.block, self.blocks * self.block
        at, own = _spans(self.ptr, terms[~wide])
        score = np.asarray(np.bincount(rows[~wide][own] * width + self.ids[at], self.weights[at] * weights[~wide][own], size * width), float).reshape(size, self.blocks, block)
        bound = q @ caps + score.max(axis=2)
        each = np.arange(size)

        def read(mask: np.ndarray) -> None:
            """Add the wide terms' part to the (query, block) that ``mask`` names, which makes them exact."""
            for b in np.flatnonzero(mask.any(axis=0)).tolist():
                ask = np.flatnonzero(mask[:, b])
                score[ask, b] += q[ask] @ full[b] if 2 * len(ask) < size else (q @ full[b])[ask]
            if leave_out is not None:
                score[each, leave_out // block, leave_out % block] = 0.0
            self.opened += int(mask.sum())

        probe = min(self.probe, self.blocks)
        best = np.argpartition(-bound, probe - 1, axis=1)[:, :probe]  # the most promising blocks give the score to beat
        begun = np.zeros((size, self.blocks), bool)
        begun[each[:, None], best] = True
        read(begun)
        some, j = score[each[:, None], best].reshape(size, -1), min(k, probe * block)
        least = np.partition(some, -j, axis=1)[:, -j]
        rest = ~begun & (bound > 0) & (bound >= least[:, None] - 1e-9)
        read(rest)
        score[~(begun | rest)] = 0.0
        self.asked += size * self.blocks
        flat, j = score.reshape(size, width), min(k, width)
        least = np.maximum(np.partition(flat, -j, axis=1)[:, -j], 1e-12)
        row, hit = np.nonzero(flat >= least[:, None] - 1e-12)
        s = np.round(flat[row, hit], 12)
        row, hit, s = row[s > 0], hit[s > 0], s[s > 0]
        order = np.lexsort((hit, -s, row))
        cut = np.searchsorted(row, np.arange(size + 1))
        hit, s = hit[order].tolist(), s[order].tolist()
        return [list(zip(hit[a : min(a + k, b)], s[a : min(a + k, b)])) for a, b in zip(cut, cut[1:])]


def isotonic(x: np.ndarray, y: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Weighted non-decreasing fit by pooling neighbours: knots and values."""
    order = np.argsort(x, kind="stable")
    pools: list[list[float]] = []  # value, weight, least x, largest x
    for i in order.tolist():
        pools.append([y[i], w[i], x[i], x[i]])
        while len(pools) > 1 and (pools[-2][0] >= pools[-1][0] or pools[-2][3] == pools[-1][2]):
            a, b = pools[-2], pools.pop()
            n = a[1] + b[1]
            pools[-1] = [(a[0] * a[1] + b[0] * b[1]) / n, n, a[2], b[3]]
    knots = np.array([v for p in pools for v in (p[2], p[3])])
    values = np.array([p[0] for p in pools for _ in (0, 1)])
    return knots, values


class NeighbourModel:
    """Terms and their weights, indexed examples, labels and the calibration curve.

    ``counts`` is (row, term, occurrences) of the examples, rows ascending.
    """

    def __init__(self, terms: list[str], stretch: np.ndarray, idf: np.ndarray, names: list[int], counts: tuple[np.ndarray, np.ndarray, np.ndarray], labels: list[int], totals: dict[int, int], k: int = NEIGHBOURS):
        self.terms, self.idf, self.k = {t: i for i, t in enumerate(terms)}, idf * stretch, k
        n = len(names)
        rows, at, w = self.vectors(*counts, n)
        # examples of alike content go into the same blocks: by their heaviest term, then by id
        heaviest = np.full(n, -1, np.int64)
        order = np.lexsort((at, -w, rows))
        first = order[np.flatnonzero(np.diff(rows[order], prepend=-1))]
        heaviest[rows[first]] = at[first]
        order = np.array([i for i in np.lexsort((names, heaviest)).tolist() if heaviest[i] >= 0], np.int64)
        place = np.full(n, -1, np.int64)
        place[order] = np.arange(len(order))
        moved = np.lexsort((at, place[rows]))
        rows, at, w = place[rows][moved], at[moved], w[moved]
        self.names = [names[i] for i in order.tolist()]
        self.labels = np.array([labels[i] for i in order.tolist()], float)
        seen = [sum(y == c for y in labels) for c in (0, 1)]
        per = [totals.get(c, 0) / max(1, seen[c]) for c in (0, 1)]  # a sampled example stands for so many
        self.weight = np.array([per[labels[i]] for i in order.tolist()], float)
        self.index = BlockMaxIndex(len(order), (rows, at, w), len(terms))
        prior = (totals.get(1, 0) + 0.5) / (totals.get(0, 0) + totals.get(1, 0) + 1.0)
        bare = [labels[i] for i in np.flatnonzero(heaviest < 0).tolist()]
        self.bare = (per[1] * sum(bare) + prior) / (sum(per[c] for c in bare) + 1.0)
        votes = []
        cut = np.searchsorted(rows, np.arange(len(order) + 1))
        for lo in range(0, len(order), ROWS):
            hi = min(lo + ROWS, len(order))
            a, b = cut[lo], cut[hi]
            votes += [self.vote(x) for x in self.index.top((rows[a:b] - lo, at[a:b], w[a:b]), hi - lo, k, np.arange(lo, hi))]
        self.index._rows = None  # workers make their own
        self.knots, self.values = isotonic(np.array([*votes, 0.0, 1.0]), np.array([*self.labels, 0.0, 1.0]), np.array([*self.weight, 1.0, 1.0]))

    def vectors(self, rows: np.ndarray, at: np.ndarray, n: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Unit vectors of term counts."""
        w = (1 + np.log(n)) * self.idf[at]
        norm = np.sqrt(np.bincount(rows, w * w, size))
        return rows, at, w / norm[rows]

    def vote(self, near: list[tuple[int, float]]) -> float:
        """Share of label 1 among the neighbours, weighted by 1 / distance and by what each stands for."""
        a = b = 0.0
        for i, s in near:
            w = self.weight[i] / (1.0 - min(s, 1.0) + 0.05)
            a += w * self.labels[i]
            b += w
        return a / b if b else self.bare

    def score(self, counts: tuple[np.ndarray, np.ndarray, np.ndarray], size: int) -> list[tuple[float, list[tuple[int, float]]]]:
        """Probability of label 1 and the neighbours of every text."""
        found = self.index.top(self.vectors(*counts, size), size, self.k)
        return [(float(np.clip(np.interp(self.vote(x), self.knots, self.values), 0, 1)) if x else self.bare, x) for x in found]


def held_out(key: Column) -> Column:
    return F.crc32(key.cast("string").cast("binary")) % 5 == 0


def _slices(texts: list[str]) -> Iterator[tuple[int, int]]:
    """(lo, hi) of runs of texts of bounded number and characters; a longer text is a run of its own."""
    lo = chars = 0
    for i, t in enumerate(texts):
        if i > lo and (i - lo >= ROWS or chars + len(t) > CHARS):
            yield lo, i
            lo, chars = i, 0
        chars += len(t)
    if texts:
        yield lo, len(texts)


def _counts(texts: list[str], at: dict[str, int]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, term, occurrences) of the known terms of every text, rows ascending."""
    got = [[i for i in map(at.get, terms_of(t)) if i is not None] for t in texts]
    n, wide = [len(x) for x in got], max(1, len(at))
    key = np.repeat(np.arange(len(texts)), n) * wide + np.fromiter(chain.from_iterable(got), np.int64, sum(n))
    key.sort()
    first = np.flatnonzero(np.diff(key, prepend=-1))
    return key[first] // wide, key[first] % wide, np.diff(np.append(first, len(key)))


def fit(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "toxic", sample: int = SAMPLE, terms: int = TERMS, neighbours: int = NEIGHBOURS, unit: float = UNIT) -> NeighbourModel:
    """Fit on labelled rows that are not held out; document frequencies come from all ``docs``.

    A key with several labels counts as label 1 if one of them is; of a key's texts the least is taken.
    """
    spark = docs.sparkSession
    marked = labels.select(F.col(key).alias("k"), F.col(label).cast("int").alias("y")).filter(F.col("k").isNotNull() & F.col("y").isin(0, 1) & ~held_out(F.col("k")))
    marked = marked.groupBy("k").agg(F.max("y").alias("y"))
    totals = {r.y: r.n for r in marked.groupBy("y").agg(F.count("*").alias("n")).collect()}
    picked = [marked.filter(F.col("y") == y).orderBy(F.xxhash64("k"), "k").limit(sample) for y in (0, 1)]
    chosen = [(r.k, r.y) for p in picked for r in p.collect()]  # at most 2 x sample ids
    vocabulary, stretch, names, y = [], np.ones(0), [], []
    counts = (np.zeros(0, np.int64),) * 3
    if chosen:
        few = spark.createDataFrame(chosen, "k long, y int")
        rows = docs.select(F.col(key).cast("long").alias("k"), F.col(text).alias("t")).join(F.broadcast(few), "k")
        rows = stage(rows.groupBy("k").agg(F.max("y").alias("y"), F.min("t").alias("t")), "examples")
        vocabulary, stretch = choose_terms(rows, terms, unit)
        names, y, counts = _examples(rows, {t: i for i, t in enumerate(vocabulary)})
    n_docs, df = document_frequencies(docs, text, {t: i for i, t in enumerate(vocabulary)})
    return NeighbourModel(vocabulary, stretch, np.log((n_docs + 1.0) / (df + 1.0)) + 1.0, names, counts, y, totals, neighbours)


def _examples(rows: DataFrame, at: dict[str, int]) -> tuple[list[int], list[int], tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Ids, labels and term counts of the examples, by id; the examples are at most 2 x sample."""
    known = rows.sparkSession.sparkContext.broadcast(at)

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = text_column(batch, "t")
            for lo, hi in _slices(texts):
                row, term, n = _counts(texts[lo:hi], known.value)
                cut = np.searchsorted(row, np.arange(hi - lo + 1)).astype(np.int32)
                lists = [pa.ListArray.from_arrays(pa.array(cut), pa.array(x.astype(np.int32))) for x in (term, n)]
                yield pa.RecordBatch.from_arrays([batch.column("k").slice(lo, hi - lo), batch.column("y").slice(lo, hi - lo), *lists], names=["k", "y", "ids", "n"])

    t = rows.select("k", "y", "t").mapInArrow(read, "k long, y int, ids array<int>, n array<int>").toArrow().sort_by("k")
    ids, n = (t.column(c).combine_chunks() for c in ("ids", "n"))
    known.destroy()
    row = np.repeat(np.arange(t.num_rows), ids.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64))
    return t.column("k").to_pylist(), t.column("y").to_pylist(), (row, ids.flatten().to_numpy().astype(np.int64), n.flatten().to_numpy().astype(np.int64))


def choose_terms(rows: DataFrame, most: int = TERMS, unit: float = UNIT) -> tuple[list[str], np.ndarray]:
    """Words of two or more of the examples (y, t), strongest first, and how far each is stretched.

    Counted where the examples are; beyond ``most`` words those that say least on the label go.
    """
    totals = {r.y: r.n for r in rows.groupBy("y").agg(F.count("*").alias("n")).collect()}
    n1, n0 = float(totals.get(1, 0)), float(totals.get(0, 0))

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 200):
                part = batch.slice(lo, 200)
                sets = [sorted(set(terms_of(s))) for s in text_column(part, "t")]
                y = np.repeat(part.column("y").to_numpy(), [len(s) for s in sets])
                yield pa.RecordBatch.from_arrays([pa.array([x for s in sets for x in s], pa.string()), pa.array(y, pa.int32())], names=["term", "y"])

    seen = rows.select("y", "t").mapInArrow(split, "term string, y int").groupBy("term").agg(F.sum("y").cast("double").alias("a"), (F.count("*") - F.sum("y")).cast("double").alias("b"))
    a, b, n = F.col("a"), F.col("b"), n1 + n0

    def part(o, e):
        return F.when(o > 0, 2 * o * F.log(o * n / e)).otherwise(0.0)

    g = part(a, n1 * (a + b)) + part(n1 - a, n1 * (n - a - b)) + part(b, n0 * (a + b)) + part(n0 - b, n0 * (n - a - b)) if n1 and n0 else F.lit(0.0)
    best = seen.filter(a + b >= 2).withColumn("g", F.round(F.greatest(g, F.lit(0.0)), 6)).orderBy(F.desc("g"), "term").limit(most).select("term", "g").toArrow()
    g = best.column("g").to_numpy()
    return best.column("term").to_pylist(), 1.0 + g / unit if unit else np.ones(len(g))


def document_frequencies(docs: DataFrame, text: str, at: dict[str, int]) -> tuple[int, np.ndarray]:
    """Rows of ``docs`` and, per term, how many contain it: one pass, one partial count per task."""
    known = docs.sparkSession.sparkContext.broadcast(at)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget_tables()
        n_terms = len(known.value)
        df = np.zeros(n_terms + 1, np.int64)
        for batch in batches:
            texts = text_column(batch, "t")
            df[-1] += len(texts)
            for lo, hi in _slices(texts):
                df[:-1] += np.bincount(_counts(texts[lo:hi], known.value)[1], minlength=n_terms)[:n_terms]
        some = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(df[some])], names=["t", "n"])

    found = docs.select(F.col(text).alias("t")).mapInArrow(count, "t long, n long").groupBy("t").agg(F.sum("n").alias("n")).toArrow()
    known.destroy()
    df = np.zeros(len(at) + 1)
    df[found.column("t").to_numpy()] = found.column("n").to_numpy()
    return int(df[-1]), df[:-1]


def score(docs: DataFrame, model: NeighbourModel, key: str = "doc_id", text: str = "text", threshold: float = 0.5) -> DataFrame:
    """All columns of ``docs`` plus score, predicted and evidence (the nearest examples).

    Null and empty texts, and texts without a known term, get the rate of label 1 among such
    examples. Equal texts get equal scores; of equally near examples that of the smaller number
    counts. Clashing extra columns are replaced. An empty table gives an empty result.
    """
    docs = docs.drop(*[c for c in ("score", "predicted", "evidence") if c in docs.columns and c not in (key, text)])
    names = docs.columns
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        kind = pa.list_(pa.struct([("example", pa.int64()), ("label", pa.int32()), ("cosine", pa.float64())]))
        for batch in batches:
            texts = text_column(batch, text)
            for lo, hi in _slices(texts):
                once = {t: i for i, t in enumerate(dict.fromkeys(texts[lo:hi]))}
                found = m.score(_counts(list(once), m.terms), len(once))
                found = [(p, [{"example": m.names[i], "label": int(m.labels[i]), "cosine": c} for i, c in near[:3]]) for p, near in found]
                got = [found[once[t]] for t in texts[lo:hi]]
                part = batch.slice(lo, hi - lo)
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in names), pa.array([p for p, _ in got], pa.float64()), pa.array([int(p >= threshold) for p, _ in got], pa.int32()), pa.array([e for _, e in got], kind)], names=[*names, "score", "predicted", "evidence"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    return docs.mapInArrow(run, f"{fields}, score double, predicted int, evidence array<struct<example:long,label:int,cosine:double>>")


def op1_nearest_examples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Toxicity of all ``documents``; learns from labels that are not held out."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = fit(docs, table(spark, sf_dir, "labels").select("doc_id", "toxic"))
    return score(docs, model).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted", "evidence")
