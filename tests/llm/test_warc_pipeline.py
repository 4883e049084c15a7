"""op6, and the pipeline against a brute-force version of its decisions."""

import os
import random
import re

import pytest
from pyspark.sql import functions as F

from bagjoin.llm import bpe, decontaminate, lines, simhash, warc
from bagjoin.llm.common import new_folder, table
from tests.llm.test_near_duplicates import groups
from tests.llm.test_text_operators import brute_leaks, brute_lines, brute_toxicity


def test_records():
    raw = warc.record("http://x/\r\ny", "é".encode())
    head, payload = warc.parse_record(raw)
    assert payload == "é".encode() and head["WARC-Target-URI"] == "http://x/ y"
    with pytest.raises(ValueError):
        warc.parse_record(raw[:-8])
    with pytest.raises(ValueError):
        warc.parse_record(raw.replace("é".encode(), b"ab"))


def test_audit_descends_to_the_damage(spark, sf):
    pages = spark.read.parquet(f"{sf}/pages.parquet").union(spark.createDataFrame([(None, None, None), (1, "u", ""), (1, "u", ""), (2, "v", "x" * 300_000)], "page_id long, url string, html string"))
    a, b = new_folder(spark, "wa"), new_folder(spark, "wb")
    index = warc.write_warc(pages.repartition(5), a)
    warc.copy_replica(index, a, b)
    assert index.count() == pages.count()
    one = warc.MerkleTree(warc.leaf_hashes(index, a), fanout=3)
    two = warc.MerkleTree(warc.leaf_hashes(index, b), fanout=3)
    assert one.root() == two.root() and warc.compare_replicas(one, two).count() == 0
    rows = sorted(index.collect(), key=lambda r: (r.file, r.i))
    for r in rows[3], rows[20]:
        path = f"{b}/{r.name}".replace("file://", "")
        with open(path, "r+b") as f:
            f.seek(r.offset + r.length // 2)
            c = f.read(1)
            f.seek(-1, 1)
            f.write(bytes([c[0] ^ 1]))
    os.remove(f"{b}/{rows[-1].name}".replace("file://", ""))
    two = warc.MerkleTree(warc.leaf_hashes(index, b), fanout=3)
    want = {(r.file, r.i) for r in (rows[3], rows[20])} | {(r.file, r.i) for r in rows if r.name == rows[-1].name}
    assert {(r.file, r.i) for r in warc.compare_replicas(one, two).collect()} == want
    damaged = warc.leaf_hashes(index, b, payloads=True).filter("payload_sha256 IS NULL")
    assert {(r.file, r.i) for r in damaged.collect()} == want


def test_empty_archive(spark):
    index = warc.write_warc(spark.createDataFrame([], "page_id long, url string, html string"), new_folder(spark, "w"))
    assert index.count() == 0
    t = warc.MerkleTree(warc.leaf_hashes(index, new_folder(spark, "w")))
    assert t.root() is None and warc.compare_replicas(t, t).count() == 0


def test_pipeline_equals_brute_force(spark, sf):
    pipeline = pytest.importorskip("corpus_pipeline")
    docs = table(spark, sf, "documents")
    texts = {r.doc_id: r.text for r in docs.collect()}
    scores, _ = brute_toxicity(texts, {r.doc_id: r.toxic for r in table(spark, sf, "labels").collect()})
    rows = {d: t for d, t in texts.items() if scores[d] < 0.5}
    kept = {}
    for d, _, gone, text in brute_lines(list(rows.items()), lines.THRESHOLD, lines.MIN_CHARS, lines.within_edits):
        if not gone or text.strip(" \t\r\n\f\x0b"):
            kept[d] = text
    ids = sorted(kept)
    sets = [brute_shingles(kept[d]) for d in ids]
    g = groups(len(ids), lambda a, b: sets[a] == sets[b] or len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]))
    kept = {d: kept[d] for i, d in enumerate(ids) if g[i] == i}
    items = [(r.item_id, r.text) for r in table(spark, sf, "benchmark").collect()]
    leaked = brute_leaks(list(kept.items()), items)
    want = {d for d in kept if d not in leaked}
    got = pipeline.run(spark, sf)
    assert {r.doc_id for r in got.select("doc_id").collect()} == want
    assert got.count() == len(want)


def test_stages_keep_columns_and_take_odd_rows(spark, sf):
    pipeline = pytest.importorskip("corpus_pipeline")
    docs = table(spark, sf, "documents")
    odd = spark.createDataFrame([(None, None, None, None, None), (1, None, "en", "x", 0), (-1, "", "en", "x", 0), (-1, "", "en", "x", 0), (-2, "a " * 40_000, "en", "x", 80_000)], docs.schema)
    for name, step in pipeline.STAGES:
        for src in (docs.union(odd), docs.limit(0)):
            out = step(spark, src, sf)
            if name != pipeline.STAGES[-1][0]:
                assert out.columns == docs.columns
            out.count()


def test_modules_name_no_python_in_native_operator():
    with open(decontaminate.__file__) as f:
        assert not re.search(r"udf|mapIn|applyIn|pandas|pyarrow|\.rdd", f.read())
    assert simhash.MASK == (1 << 64) - 1


def brute_shingles(t):
    w = [x.lower() for x in (t or "").split()]
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def test_near_dedup_equals_brute_jaccard(spark):
    pipeline = pytest.importorskip("corpus_pipeline")
    r = random.Random(6)
    rows = []
    for _ in range(40):
        base = [f"w{r.randrange(5000)}" for _ in range(r.choice([4, 12, 60, 200]))]
        rows.append(base)
        for rate in (0.0, 0.01, 0.02, 0.03):
            rows.append([x if r.random() >= rate else f"n{r.randrange(5000)}" for x in base])
    rows = [(i, " ".join(w), "en", "x", 0) for i, w in enumerate(rows)] + [(900, "", "en", "x", 0), (901, None, "en", "x", 0)]
    sets = [brute_shingles(x[1]) for x in rows]
    g = groups(len(rows), lambda a, b: sets[a] == sets[b] or len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]))
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    got = sorted(x.doc_id for x in pipeline.near_dedup(spark, docs, "").select("doc_id").collect())
    assert got == [rows[i][0] for i in range(len(rows)) if g[i] == i]


def test_working_names_of_the_input_survive(spark, sf):
    pipeline = pytest.importorskip("corpus_pipeline")
    path = pytest.importorskip("public_tokenizers").path("word_bpe_49k.json")
    names = ("__uid", "__d", "__n", "__text", "__k", "__rd")
    docs = spark.createDataFrame([(i, f"line number {i} of some length\nshared line of some length", "en", "x", 0) for i in range(4)], "doc_id long, text string, lang string, source string, n_chars long")
    for j, c in enumerate(names):
        docs = docs.withColumn(c, F.lit(j))
    items = spark.createDataFrame([(1, "not there at all in any text")], "item_id long, text string")
    for out in (lines.dedup_lines(docs), decontaminate.decontaminate(docs, items), bpe.encode_documents(docs, path), pipeline.near_dedup(spark, docs, sf)):
        assert [[r[c] for c in names] for r in out.collect()] == [list(range(6))] * 4


def test_copy_with_damage(spark, sf):
    pages = spark.read.parquet(f"{sf}/pages.parquet")
    a, b = new_folder(spark, "wa"), new_folder(spark, "wb")
    index = warc.write_warc(pages.repartition(3), a)
    warc.copy_replica(index, a, b, F.col("page_id") % 9 == 2)
    one, two = (warc.MerkleTree(warc.leaf_hashes(index, x), fanout=4) for x in (a, b))
    bad = warc.compare_replicas(one, two).join(index, ["file", "i"])
    assert {r.page_id for r in bad.collect()} == {r.page_id for r in pages.collect() if r.page_id % 9 == 2}
    assert all((r.start, r.stop) == (r.offset, r.offset + r.length) for r in bad.collect())
    got = warc.op6_merkle_fixity(spark, sf).collect()
    assert {r.page_id for r in got if not r.intact} == {r.page_id for r in pages.collect() if r.page_id % warc.OF == warc.DAMAGED}
    assert all(r.range_found for r in got)


def test_line_dedup_keeps_documents_of_short_lines(spark):
    pipeline = pytest.importorskip("corpus_pipeline")
    head = "a header line that many documents share"
    rows = [(1, head + "\nfirst text of some length here"), (2, head + "\nshort\nown lines"), (3, head), (4, head + "\n \t\n"), (5, "x"), (6, None), (7, "")]
    docs = spark.createDataFrame([(i, t, "en", "x", 0) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    got = {r.doc_id: r.text for r in pipeline.line_dedup(spark, docs, "").collect()}
    assert got == {1: rows[0][1], 2: "short\nown lines", 5: "x", 6: None, 7: ""}
