"""Benchmark decontamination with SimHash windows, built from DataFrame functions only.

1. Words are maximal runs of letters and digits, lower-cased; shingles are five words.
2. Positions of a document whose shingle occurs in an item are counted for every item-sized window,
   wherever in the item the shingles stand. A (window, item) pair goes on if the window holds so many
   of them that the similarity can be reached; all others are below it, so no window is lost.
3. Windows and items get 64-bit SimHash fingerprints (each shingle counts as often as it occurs).
   The fingerprints are cut into ``radius + 1`` blocks: two within the radius agree on a block, so
   an equi-join on (item, block, value) finds all of them among the pairs of step 2, and the bit
   count removes the rest. Pairs of one size that step 2 rules out are not met at all.
4. Candidates are verified exactly: weighted Jaccard similarity of the shingle multisets.

An item of fewer than five words has no shingles; it matches a document of exactly its words.
Joins carry (document, position), not words; words are joined in for the windows that are left. The
benchmark side is broadcast if its shingles are few enough, else joined by shuffle.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import sheltered, stage, table

SHINGLE, SIMILARITY, RADIUS = 5, 0.8, 22
#: Benchmark shingles up to which their table is broadcast (about 100 MB of hash table).
BROADCAST_ROWS = 1_000_000


def words_of(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda x: x != "")


def _shingles(words: Column, k: int) -> Column:
    """Shingles as strings, repeats included; none for fewer than ``k`` words."""
    at = F.sequence(F.lit(1), F.size(words) - (k - 1))
    return F.when(F.size(words) >= k, F.transform(at, lambda i: F.concat_ws(" ", F.slice(words, i, k)))).otherwise(F.array().cast("array<string>"))


def simhash(shingles: Column) -> Column:
    """Bit b is set if more than half of the shingles' hashes have it set."""
    hashes = F.transform(shingles, lambda s: F.xxhash64(s))

    def bit(b: Column) -> Column:
        ones = F.size(F.filter(hashes, lambda h: F.call_function("getbit", h, b.cast("int")) == 1))
        return F.when(2 * ones > F.size(hashes), F.call_function("shiftleft", F.lit(1).cast("long"), b.cast("int"))).otherwise(F.lit(0).cast("long"))

    return F.aggregate(F.sequence(F.lit(0), F.lit(63)), F.lit(0).cast("long"), lambda acc, b: acc.bitwiseOR(bit(b)))


def _blocks(fp: Column, radius: int) -> Column:
    n = radius + 1
    cuts = [64 * i // n for i in range(n + 1)]
    return F.array(*[F.struct(F.lit(i).alias("block"), F.shiftrightunsigned(fp, a).bitwiseAND(F.lit((1 << (b - a)) - 1)).cast("int").alias("value")) for i, (a, b) in enumerate(zip(cuts, cuts[1:]))])


def _common(a: Column, b: Column) -> Column:
    """Size of the intersection of two multisets given as arrays."""
    times = lambda xs, x: F.size(F.filter(xs, lambda y: y == x))
    return F.aggregate(F.array_distinct(a), F.lit(0), lambda acc, x: acc + F.least(times(a, x), times(b, x)))


def _word_hashes(words: Column, k: int) -> Column:
    """A hash of every run of ``k`` words, from hashes of the words."""
    each = F.transform(words, lambda x: F.xxhash64(x))

    def runs(of: Column) -> Column:
        return F.transform(F.sequence(F.lit(0), F.size(of) - k), lambda i: F.xxhash64(*[F.get(of, i + j) for j in range(k)]))

    # one-element array: the word hashes are worked out once per row, not once per run
    return F.when(F.size(words) >= k, F.flatten(F.transform(F.array(each), runs))).otherwise(F.array().cast("array<bigint>"))


def leaks(docs: DataFrame, items: DataFrame, key: str = "doc_id", text: str = "text", item_key: str = "item_id", item_text: str = "text", shingle: int = SHINGLE, similarity: float = SIMILARITY, radius: int = RADIUS) -> DataFrame:
    """(key, uid, item, start, similarity): windows of documents that are near-copies of items.

    ``start`` is the window's first word. Items without words and null texts match nothing; an item
    of fewer than ``shingle`` words matches documents of just those words, with similarity 1. A
    document shorter than an item is one window.
    """
    it = items.select(F.col(item_key).alias("item"), words_of(F.col(item_text)).alias("w")).filter(F.size("w") > 0).dropDuplicates(["item", "w"])
    short = it.filter(F.size("w") < shingle)
    it = it.filter(F.size("w") >= shingle)
    it = it.select("item", F.size("w").alias("size"), _word_hashes(F.col("w"), shingle).alias("sigs"), _shingles(F.col("w"), shingle).alias("of"))
    it = stage(it.withColumn("item_fp", simhash(F.col("of"))), "items")
    grams = it.select("item", "size", F.explode(F.array_distinct("sigs")).alias("sig")).distinct()
    few = grams.count() <= BROADCAST_ROWS
    maybe = F.broadcast if few else (lambda x: x)

    d = docs.select(F.col(key).alias("key"), F.xxhash64(key, text).alias("uid"), words_of(F.col(text)).alias("w"))
    at = d.select("key", "uid", F.size("w").alias("n"), F.posexplode(_word_hashes(F.col("w"), shingle)).alias("i", "sig"))
    hits = at.join(maybe(grams), "sig").groupBy("key", "uid", "item", "size", "n").agg(F.array_sort(F.collect_set("i")).alias("p"))
    # a window of ``have`` shingles needs this many that occur in the item, for c / (of + have - c) >= similarity
    hits = hits.withColumn("have", F.least("size", "n") - (shingle - 1))
    hits = hits.withColumn("need", F.greatest(F.lit(1), F.ceil((F.col("size") - (shingle - 1) + F.col("have")) * (similarity / (1 + similarity)) - 1e-9).cast("int")))
    hits = hits.filter(F.size("p") >= F.col("need"))
    close = F.filter(F.sequence(F.lit(0), F.size("p") - F.col("need")), lambda k: F.get("p", k + F.col("need") - 1) - F.get("p", k) < F.col("have"))
    last = F.greatest(F.lit(0), F.col("n") - F.col("size"))
    starts = F.transform(close, lambda k: F.sequence(F.greatest(F.lit(0), F.get("p", k + F.col("need") - 1) - F.col("have") + 1), F.least(F.get("p", k), last)))
    pairs = stage(hits.select("key", "uid", "item", "size", F.explode(F.array_distinct(F.flatten(starts))).alias("start")), "pairs")

    # every window once: its words, shingles and fingerprint
    wanted = pairs.groupBy("key", "uid").agg(F.collect_set(F.struct("start", "size")).alias("of")).select(F.col("key").alias("k2"), F.col("uid").alias("u2"), "of")
    cut = d.join(stage(wanted, "wanted"), (F.col("uid") == F.col("u2")) & F.col("key").eqNullSafe(F.col("k2")))
    cut = cut.dropDuplicates(["key", "uid"]).select("key", "uid", "w", F.inline("of"))
    wins = cut.select("key", "uid", "size", "start", _shingles(F.slice("w", F.col("start") + 1, F.col("size")), shingle).alias("have"))
    wins = stage(wins.withColumn("fp", simhash(F.col("have"))), "windows")

    on = ["uid", "size", "start"]
    fps = wins.select(F.col("key").alias("k2"), *on, "fp")
    probe = pairs.join(fps, on).filter(F.col("key").eqNullSafe(F.col("k2"))).select("key", *on, "item", "fp", F.inline(_blocks(F.col("fp"), radius)))
    index = it.select(F.col("item").alias("i2"), F.col("size").alias("s2"), "item_fp", F.inline(_blocks(F.col("item_fp"), radius))).withColumnsRenamed({"block": "b2", "value": "v2"})
    agree = F.col("item").eqNullSafe(F.col("i2")) & (F.col("size") == F.col("s2")) & (F.col("block") == F.col("b2")) & (F.col("value") == F.col("v2"))
    near = probe.join(maybe(index), agree).filter(F.bit_count(F.col("fp").bitwiseXOR(F.col("item_fp"))) <= radius)
    near = near.groupBy("key", *on, "item", "item_fp").agg(F.count("*").alias("blocks"))
    both = near.join(wins.select(F.col("key").alias("k2"), *on, "have"), on).filter(F.col("key").eqNullSafe(F.col("k2"))).drop("k2")
    texts = it.select(F.col("item").alias("i2"), F.col("size").alias("s2"), F.col("item_fp").alias("f2"), "of")
    both = both.join(maybe(texts), F.col("item").eqNullSafe(F.col("i2")) & (F.col("size") == F.col("s2")) & (F.col("item_fp") == F.col("f2")))
    same = _common(F.col("of"), F.col("have"))
    both = both.withColumn("same", same).withColumn("similarity", F.col("same") / (F.size("of") + F.size("have") - F.col("same")))
    found = both.filter(F.col("similarity") >= similarity).select("key", "uid", "item", "start", "similarity")
    tiny = d.filter(F.size("w") < shingle).join(maybe(short.withColumnRenamed("w", "v")), F.col("w") == F.col("v"))
    return found.union(tiny.select("key", "uid", "item", F.lit(0), F.lit(1.0)).distinct())


def decontaminate(docs: DataFrame, items: DataFrame, key: str = "doc_id", text: str = "text", **opts) -> DataFrame:
    """All columns of ``docs`` plus contaminated, n_items, best_item and best_similarity.

    The best item is that of the highest similarity, then the least id; null and 0.0 where there is
    none. Rows equal in key and text get equal answers; clashing extra columns are replaced. Empty
    tables on either side leave every row clean.
    """
    docs = docs.drop(*[c for c in ("contaminated", "n_items", "best_item", "best_similarity") if c in docs.columns and c not in (key, text)])
    docs, restored = sheltered(docs, key, text)
    found = leaks(docs, items, key, text, **opts).groupBy("key", "uid", "item").agg(F.max("similarity").alias("similarity"))
    best = F.min_by("item", F.struct(-F.col("similarity"), "item"))
    found = found.groupBy("key", "uid").agg(F.count("*").alias("n_items"), best.alias("best_item"), F.max("similarity").alias("best_similarity"))
    found = found.withColumnsRenamed({"key": "__k", "uid": "__u"})
    out = docs.withColumn("__uid", F.xxhash64(key, text)).join(found, (F.col("__uid") == F.col("__u")) & F.col(key).eqNullSafe(F.col("__k")), "left").drop("__uid", "__k", "__u")
    return restored(out).withColumns({"contaminated": F.col("n_items").isNotNull(), "n_items": F.coalesce("n_items", F.lit(0).cast("long")), "best_similarity": F.coalesce("best_similarity", F.lit(0.0))})


def op7_simhash_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Benchmark leaks of all ``documents``, one row per document."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = leaks(docs, table(spark, sf_dir, "benchmark").select("item_id", "text"))
    found = found.groupBy("key", "uid", "item").agg(F.max("similarity").alias("s")).groupBy("key", "uid").agg(F.count("*").alias("n"), F.min_by("item", F.struct(-F.col("s"), "item")).alias("best"), F.max("s").alias("s"))
    out = docs.select("doc_id", F.xxhash64("doc_id", "text").alias("u")).join(found, (F.col("u") == F.col("uid")) & F.col("doc_id").eqNullSafe(F.col("key")), "left")
    return out.select("doc_id", F.col("n").isNotNull().alias("contaminated"), F.coalesce("n", F.lit(0).cast("long")).alias("n_items"), F.col("best").alias("best_item"), F.round(F.coalesce("s", F.lit(0.0)), 6).alias("best_similarity"))


#: The same answer by comparing every window that holds a shingle of an item, without fingerprints.
OP7_SQL = r"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+'), lambda x: x <> '') AS w FROM documents WHERE text IS NOT NULL),
b AS (SELECT DISTINCT item_id, list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+'), lambda x: x <> '') AS w FROM benchmark WHERE text IS NOT NULL),
ds AS (SELECT doc_id, unnest(range(len(w) - 4)) AS i, w FROM d WHERE len(w) >= 5),
dg AS (SELECT doc_id, i, len(w) AS n, array_to_string(w[i + 1 : i + 5], ' ') AS g FROM ds),
bs AS (SELECT item_id, unnest(range(len(w) - 4)) AS j, w FROM b WHERE len(w) >= 5),
bg AS (SELECT item_id, j, len(w) AS m, array_to_string(w[j + 1 : j + 5], ' ') AS g FROM bs),
bc AS (SELECT item_id, g, m, count(*) AS c FROM bg GROUP BY ALL),
hit AS (SELECT doc_id, item_id, m, n, i FROM dg JOIN bc USING (g)),
al AS (SELECT DISTINCT doc_id, item_id, m, unnest(range(greatest(0, i - m + 5), least(i, greatest(0, n - m)) + 1)) AS s FROM hit),
wc AS (SELECT al.doc_id, al.item_id, al.s, dg.g, count(*) AS c FROM al JOIN dg ON dg.doc_id = al.doc_id AND dg.i >= al.s AND dg.i <= al.s + al.m - 5 GROUP BY ALL),
wn AS (SELECT doc_id, item_id, s, sum(c) AS n FROM wc GROUP BY ALL),
bn AS (SELECT item_id, sum(c) AS n FROM bc GROUP BY ALL),
cm AS (SELECT wc.doc_id, wc.item_id, wc.s, sum(least(wc.c, bc.c)) AS c FROM wc JOIN bc USING (item_id, g) GROUP BY ALL),
sm AS (SELECT doc_id, item_id, max(cm.c::DOUBLE / (wn.n + bn.n - cm.c)) AS sim FROM cm JOIN wn USING (doc_id, item_id, s) JOIN bn USING (item_id) GROUP BY ALL HAVING sim >= 0.8
    UNION SELECT doc_id, item_id, 1.0::DOUBLE FROM d JOIN b ON d.w = b.w WHERE len(d.w) BETWEEN 1 AND 4),
f AS (SELECT doc_id, count(*) AS n, arg_min(item_id, struct_pack(a := -sim, b := item_id)) AS best, max(sim) AS s FROM sm GROUP BY doc_id)
SELECT documents.doc_id, f.n IS NOT NULL AS contaminated, coalesce(f.n, 0)::BIGINT AS n_items, f.best AS best_item, round(coalesce(f.s, 0.0), 6) AS best_similarity
FROM documents LEFT JOIN f USING (doc_id)
"""
