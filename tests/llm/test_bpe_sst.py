"""op2 and op4 against the tokenizers library."""

import hashlib
import random
import zlib

import numpy as np
import pytest

P = pytest.importorskip("public_tokenizers")
tokenizers = pytest.importorskip("tokenizers")
from bagjoin.llm import bpe, sst  # noqa: E402
from bagjoin.llm.common import WordTable, new_folder  # noqa: E402

PATH = P.path("word_bpe_49k.json")
TEXTS = [
    "", "   ", None, "Don't we'll  I'VE 123 x", "½ ² é é ΑΣ ΣΑΣ İstanbul ǅ ß ſ", "<|endoftext|>x<|startoftext|> <|endof <|ENDOFTEXT|>",
    "日本語テキスト 👩‍👧 aaaaaaaaaaaaaaaaaaa", "a\x1cb \x85  ​　x", "a" * 3000, "ab" * 2000 + "!" * 999, "́abc", "\x00\x01 \x7f", "the cat the cat",
]


@pytest.fixture(scope="module")
def lib():
    return tokenizers.Tokenizer.from_file(PATH)


def test_automaton_equals_library(lib):
    m = bpe.compiled(PATH)
    r = random.Random(4)
    more = ["".join(r.choice("abcdeé '’.,!1\n<|>ß中") for _ in range(r.randrange(80))) for _ in range(400)]
    for t in [x for x in TEXTS if x is not None] + more:
        want = lib.encode(t, add_special_tokens=False).ids
        assert m.encode(t) == want
        assert m.decode(want) == lib.decode(want, skip_special_tokens=False)


def test_characters_that_the_libraries_class_differently(lib):
    m = bpe.compiled(PATH)
    r = random.Random(9)
    odd = [c for c in m._like]
    some = [chr(c) for c in r.sample(odd, min(len(odd), 300))] + ["\U0001df3e", "\U000323ec", "\U0003df67", "\U00010d50", "a", "1", "!", "é", " "]
    for _ in range(400):
        t = "".join(r.choice(some) for _ in range(r.randrange(1, 8)))
        assert m.encode(t) == lib.encode(t, add_special_tokens=False).ids, ascii(t)


def test_merge_gadget_on_a_small_vocabulary():
    """Merging one symbol with itself runs left to right, and a token may not follow what it would merge with."""
    vocab = {s: i for i, s in enumerate(["a", "b", "a</w>", "b</w>", "aa", "aab", "aaaa"])}
    m = bpe.TokenAutomaton(vocab, [("a", "a"), ("aa", "b"), ("aa", "aa")])
    names = {i: s for s, i in vocab.items()}
    code = lambda w: [names[i] for i in m.encode_words([w.encode()])[0]]
    assert code("aaab") == ["aa", "a", "b</w>"]
    assert code("aaaaab")[:2] == ["aaaa", "a"]
    assert not m.allowed(np.array([vocab["a"]]), np.array([vocab["aa"]]))[0]
    assert m.allowed(np.array([vocab["aa"]]), np.array([vocab["a"]]))[0]


def test_documents_and_shards(spark, lib):
    rows = [(i, t, "kept", 7) for i, t in enumerate(TEXTS)] + [(3, TEXTS[3], "copy", 7), (None, "no id", None, None), (-5, "below zero", "x", 1)]
    df = spark.createDataFrame(rows, "doc_id long, text string, ids_sha256 string, extra long")
    got = bpe.encode_documents(df, PATH, keep_ids=True).collect()
    assert len(got) == len(rows)
    for r in got:
        ids = lib.encode(r.text or "", add_special_tokens=False).ids
        assert (r.n_tokens, r.ids) == (len(ids), ids)
        assert r.ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(lib.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    for width in (2, 4):
        manifest = sst.write_shards(df, new_folder(spark, "t"), PATH, parts=3, width=width)
        back = sst.read_shards(spark, manifest).orderBy("start").collect()
        order = sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or ""))
        at = 0
        for r, g in zip(order, back, strict=True):
            ids = lib.encode(r[1] or "", add_special_tokens=False).ids + [2]
            assert (g.doc_id, g.start, g.n_tokens, g.ids_crc32) == (r[0], at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
            at += len(ids)
        readers = [sst.open_shard(m["path"]) for m in manifest]
        assert sum(len(r.get(3)) for r in readers) == 2
        assert all(not r.get(10**12) for r in readers)
        assert sum(len(r.get(None)) for r in readers) == 1


def test_empty_tables(spark):
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert bpe.encode_documents(empty, PATH).count() == 0
    assert sst.read_shards(spark, sst.write_shards(empty, new_folder(spark, "t"), PATH)).count() == 0


def test_many_blocks_and_damage(tmp_path):
    path = tmp_path / "x.sst"
    with open(path, "wb") as f:
        w = sst.ShardWriter(f, 2)
        for i in range(-3000, 3000):
            w.add(sst.key_of(i), np.arange(i % 50, dtype="<u2").tobytes())
        w.close()
        with pytest.raises(ValueError):
            w.add(sst.key_of(-9999), b"")
    r = sst.open_shard(f"file://{path}")
    assert len(r.blocks) > 2 and r.docs == 6000
    assert [i for i, _ in r] == list(range(-3000, 3000))
    assert len(r.get(49)[0]) == 49 and r.get(5000) == []
    raw = bytearray(path.read_bytes())
    raw[100] ^= 1
    path.write_bytes(bytes(raw))
    with pytest.raises(ValueError):
        list(sst.open_shard(f"file://{path}"))


def test_word_table_generations():
    calls = []
    t = WordTable(lambda ws: calls.extend(ws) or [w.upper() for w in ws], limit=3)
    for words in (["a", "b", "a"], ["c", "d"], ["a", "e"], ["f", "g", "h"], ["a", "z"]):
        assert t.lookup([words, []]) == [[w.upper() for w in words], []]
    assert calls.count("a") == 1
