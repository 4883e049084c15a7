"""op3 and op10 against brute force."""

import random
import re

import numpy as np
import xxhash

from bagjoin.llm import embeddings, jaccard, simhash
from bagjoin.llm.components import components


def brute_fingerprint(t, k=4):
    t = "".join(c.lower() if "A" <= c <= "Z" else c for c in t or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", t)
    if not w:
        return 0
    hs = [xxhash.xxh64_intdigest(" ".join(w[i : i + k]).encode(), 42) for i in range(max(1, len(w) - k + 1))]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def groups(n, linked):
    up = list(range(n))

    def f(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in range(n):
        for b in range(a):
            if linked(a, b):
                up[max(f(a), f(b))] = min(f(a), f(b))
    return [f(x) for x in range(n)]


def test_fingerprints():
    for t in ["", None, "One two", "A b c d", "ÀÉ b\x0bc\td e f g", "x " * 500, "İ ẞ ǅ z q"]:
        assert simhash.fingerprint(t) == brute_fingerprint(t)


def test_bk_tree():
    r = random.Random(1)
    base = r.getrandbits(64)
    xs = [base ^ sum(1 << p for p in r.sample(range(64), r.randrange(12))) for _ in range(300)]
    t = simhash.BKTree()
    for x in xs:
        t.add(x & simhash.MASK)
    for q in xs[:50]:
        assert sorted(set(t.within(q, 4))) == sorted({x for x in xs if (x ^ q).bit_count() <= 4})


def test_links_for_every_number_of_equal_blocks(spark):
    r = random.Random(2)
    seeds = [r.getrandbits(64) for _ in range(15)]
    xs = sorted({s ^ sum(1 << p for p in r.sample(range(64), r.randrange(7))) for s in seeds for _ in range(12)} | {0, 1, simhash.MASK})
    want = groups(len(xs), lambda a, b: (xs[a] ^ xs[b]).bit_count() <= 4)
    df = spark.createDataFrame([(simhash._signed(x),) for x in xs], "fp long")
    for equal, chunk in ((1, 5), (2, 1500)):
        edges = [(e.a & simhash.MASK, e.b & simhash.MASK) for e in simhash.links(df, 4, chunk, equal).collect()]
        assert all((a ^ b).bit_count() <= 4 for a, b in edges)
        pairs = {frozenset(e) for e in edges}
        assert groups(len(xs), lambda a, b: frozenset((xs[a], xs[b])) in pairs) == want


def test_near_duplicate_documents(spark, sf):
    extra = [(None, "one text without id"), (None, None), (9001, None), (9002, ""), (9003, "one text without id"), (9003, "one text without id"), (9004, "w " * 30000)]
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").union(spark.createDataFrame(extra, "doc_id long, text string"))
    rows = docs.collect()
    fps = [brute_fingerprint(r.text) for r in rows]
    g = groups(len(rows), lambda a, b: (fps[a] ^ fps[b]).bit_count() <= 4)
    least = {}
    for r, x in zip(rows, g):
        if r.doc_id is not None:
            least[x] = min(least.get(x, r.doc_id), r.doc_id)
    want = sorted(((r.doc_id if r.doc_id is not None else -1), f, least[x]) for r, f, x in zip(rows, fps, g))
    got = simhash.near_duplicates(docs.selectExpr("*", "'x' AS fp", "1 AS component_id")).collect()
    assert sorted(((r.doc_id if r.doc_id is not None else -1), r.fp & simhash.MASK, r.component_id) for r in got) == want
    assert simhash.near_duplicates(docs.limit(0)).count() == 0


def test_components_of_paths_and_stars(spark):
    r = random.Random(3)
    edges = [(i, i + 1) for i in range(60)] + [(100, 100 + i) for i in range(30)] + [(500, 500), (None, 3), (7, 6)] + [(r.randrange(200, 300), r.randrange(200, 300)) for _ in range(70)]
    up = {}

    def f(x):
        while up.setdefault(x, x) != x:
            x = up[x]
        return x

    for a, b in edges:
        if a is not None and a != b:
            x, y = f(a), f(b)
            up[max(x, y)] = min(x, y)
    got = {x.node: x.component for x in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {x: f(x) for x in up}


def test_embeddings_against_brute_force(spark):
    rng = np.random.default_rng(5)
    rows, vid = [], 0
    for label in (0, 1):
        base = rng.normal(size=(60, 24))
        for v in base:
            for _ in range(rng.integers(1, 4)):
                x = v + rng.normal(size=24) * rng.choice([0, 0.05, 0.2])
                rows.append((vid, [float(a) for a in x.astype(np.float32)], label))
                vid += 1
    rows += [(vid, rows[0][1], 0), (vid + 1, rows[0][1], 1), (vid + 2, rows[0][1], None), (vid + 3, None, 0), (vid + 4, [0.0] * 24, 0), (vid + 5, [float("nan")] * 24, 0), (vid + 6, [None] + [1.0] * 23, 0), (vid + 7, [], 0), (vid + 8, [1.0, 0.0], 0), (vid + 9, [float("inf")] * 24, 0), (vid + 10, [1e30] * 24, 0), (vid + 11, [1e-30] * 24, 0)]
    ok = [i for i, (_, x, lab) in enumerate(rows) if lab is not None and x and None not in x and np.isfinite(x).all() and any(x)]

    def linked(a, b):
        if a not in ok or b not in ok or rows[a][2] != rows[b][2] or len(rows[a][1]) != len(rows[b][1]):
            return False
        x, y = np.array(rows[a][1]) / np.abs(rows[a][1]).max(), np.array(rows[b][1]) / np.abs(rows[b][1]).max()
        return x @ y / np.sqrt((x @ x) * (y @ y)) >= 0.93

    want = {i: sum(linked(i, j) for j in range(len(rows)) if j != i) for i in range(len(rows))}
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    got = {r.vec_id: r for r in embeddings.near_vectors(df.selectExpr("*", "'z' AS kept", "0 AS rep")).collect()}
    assert len(got) == len(rows)
    assert all(got[i].n_links <= want[i] for i in want)
    assert sum(r.n_links for r in got.values()) >= 0.95 * sum(want.values())
    assert all(got[i].n_links == 0 and got[i].component_id == i and got[i].kept for i in range(len(rows)) if i not in ok)
    g = groups(len(rows), linked)
    assert np.mean([got[i].component_id == g[i] for i in range(len(rows))]) >= 0.95
    assert all(r.kept == (r.component_id == r.vec_id) for r in got.values())
    assert embeddings.near_vectors(df.limit(0)).count() == 0


def test_cap_code_lists_every_filter():
    code = embeddings.CapCode(16, 20, 0.45, blocks=2, seed=3)
    rng = np.random.default_rng(1)
    for _ in range(20):
        x = rng.normal(size=16)
        x /= np.linalg.norm(x)
        y = code.rotation @ x
        all_ = (code.words[0] @ y[:8])[:, None] + (code.words[1] @ y[8:])[None, :]
        assert code.decode(x) == np.flatnonzero(all_.reshape(-1) >= 0.45).tolist()


def test_best_filters_are_those_of_a_cap():
    rng = np.random.default_rng(4)
    xs = rng.normal(size=(30, 24))
    xs /= np.linalg.norm(xs, axis=1, keepdims=True)
    for blocks in (2, 3):
        code = embeddings.CapCode(24, 9, 0.0, blocks, seed=3)
        for x, got in zip(xs, code.best(xs, 12)):
            y = code.rotation @ x
            all_ = np.zeros(1)
            for (a, b), w in zip(zip(code.cuts, code.cuts[1:]), code.words):
                all_ = (all_[:, None] + (w @ y[a:b])[None, :]).reshape(-1)
            assert sorted(got.tolist()) == np.sort(np.argsort(-all_)[:12]).tolist()


def test_filters_keep_their_recall_as_labels_grow():
    for n in (500, 10_000, 300_000, 3_000_000):
        f = embeddings.filters_for(n, 64, 0.93)
        rng = np.random.default_rng(n)
        u, v = rng.normal(size=(2, 2000, 64))
        u /= np.linalg.norm(u, axis=1, keepdims=True)
        v -= (v * u).sum(axis=1, keepdims=True) * u
        v /= np.linalg.norm(v, axis=1, keepdims=True)
        a, b = f.of(u), f.of(0.93 * u + np.sqrt(1 - 0.93**2) * v)
        assert a.shape[1] > 0
        assert sum(not set(x) & set(y) for x, y in zip(a.tolist(), b.tolist())) <= 10, n


def test_vectors_of_large_labels_are_linked(spark):
    rng = np.random.default_rng(9)
    x = rng.normal(size=(1500, 64))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    y = rng.normal(size=x.shape)
    y -= (y * x).sum(axis=1, keepdims=True) * x
    y /= np.linalg.norm(y, axis=1, keepdims=True)
    z = 0.9301 * x + np.sqrt(1 - 0.9301**2) * y
    df = spark.createDataFrame([(i, v, 0) for i, v in enumerate(np.vstack([x, z]).tolist())], "vec_id long, embedding array<double>, label int")
    assert embeddings.near_vectors(df).filter("n_links = 0").count() <= 8


def test_similar_pairs_of_sets():
    r = random.Random(4)
    for _ in range(60):
        sets = [np.array(sorted(r.sample(range(30), r.randrange(0, 20))), np.uint64) for _ in range(12)]
        p, q = jaccard.similar_pairs(sets, 0.6, chunk=7)
        assert set(zip(p.tolist(), q.tolist())) == {(i, j) for i in range(12) for j in range(i) if jaccard.jaccard(sets[i], sets[j]) >= 0.6}


def test_group_around_a_text_that_is_not_the_least(spark):
    """Copies that are similar to one text but not to each other: linked through it, whatever its id."""
    r = random.Random(1)
    base = [f"w{i}" for i in range(100)]
    rows = [(i, " ".join(x if j // 3 != i else f"n{i}x{j}" for j, x in enumerate(base))) for i in range(30)] + [(30, " ".join(base)), (31, " ".join(r.sample(base, 100)))]
    got = jaccard.similar_groups(spark.createDataFrame(rows, "doc_id long, text string"), "doc_id")
    assert {x.doc_id: x.component_id for x in got.collect()} == {**{i: 0 for i in range(31)}, 31: 31}
