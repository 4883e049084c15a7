"""op1, op5, op7, op8 and op9 against brute force."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter
from html.parser import HTMLParser

import numpy as np
import pytest

from bagjoin.llm import decontaminate, html, lines, substrings, toxicity
from bagjoin.llm.common import Bucketed


# op5
def brute_windows(rows, w):
    first, out = {}, []
    split = [re.findall(r"[^\x20\x09-\x0D]+", t or "") for _, t in rows]
    rank = lambda d: d if d is not None else 1 << 62
    for (d, _), ws in zip(rows, split):
        for i in range(len(ws) - w + 1):
            k = tuple(ws[i : i + w])
            first[k] = min(first.get(k, rank(d)), rank(d))
    for (d, _), ws in zip(rows, split):
        gone = [False] * len(ws)
        for i in range(len(ws) - w + 1):
            if first[tuple(ws[i : i + w])] < rank(d):
                gone[i : i + w] = [True] * w
        out.append((d, len(ws), sum(gone), " ".join(x for x, g in zip(ws, gone) if not g)))
    return sorted(out, key=str)


@pytest.mark.parametrize("shard", [3, 1000])
def test_repeated_windows(spark, shard):
    r = random.Random(shard)
    v = "a b c d e f g é".split()
    base = [[r.choice(v) for _ in range(30)] for _ in range(4)]
    rows = [(i, " ".join([r.choice(v) for _ in range(r.randrange(9))] + r.choice(base)[r.randrange(8) : r.randrange(9, 30)] + [r.choice(v)] * r.randrange(12))) for i in range(50)]
    rows += [(50, None), (51, ""), (None, " ".join(base[0])), (52, " ".join(base[0])), (52, " ".join(base[0])), (53, "a\x0b b\tc " * 10), (54, "q " * 3000)]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 AS n_words", "'s' AS spans", "2 AS d", "3 AS uid")
    got = substrings.remove_repeats(df, window=7, gram=3, shard=shard)
    assert sorted(((x.doc_id, x.n_words, x.n_removed, x.text) for x in got.collect()), key=str) == brute_windows(rows, 7)
    assert all(sum(s.stop - s.start for s in x.spans) == x.n_removed for x in got.collect())
    assert substrings.remove_repeats(df.limit(0)).count() == 0


def test_suffix_automaton_statistics():
    r = random.Random(3)
    for _ in range(200):
        seqs = [[r.randrange(3) for _ in range(r.randrange(12))] for _ in range(3)]
        q = [r.randrange(3) for _ in range(12)]
        a = substrings.SuffixAutomaton()
        for s in seqs:
            a.add(s)
        for i, n in enumerate(a.statistics(q)):
            assert n == max(k for k in range(i + 2) if k == 0 or any(q[i + 1 - k : i + 1] == s[b : b + k] for s in seqs for b in range(len(s) - k + 1)))


# op9
def edits(a, b):
    p = list(range(len(b) + 1))
    for i, x in enumerate(a):
        q = [i + 1]
        for j, y in enumerate(b):
            q.append(min(p[j] + (x != y), p[j + 1] + 1, q[j] + 1))
        p = q
    return p[-1]


def test_banded_edit_distance():
    r = random.Random(5)
    for _ in range(4000):
        a, b = ("".join(r.choice("ab") for _ in range(r.randrange(9))) for _ in "xy")
        for k in (0, 1, 2, 3):
            assert lines.within_edits(a, b, k) == (edits(a, b) <= k)


def brute_lines(rows, k, least, near=lambda a, b, k: edits(a, b) <= k):
    every = [((d, i), x.strip(" \t\r\f\x0b")) for d, t in rows for i, x in enumerate((t or "").split("\n")) if t is not None]
    every = [(p, x) for p, x in every if len(x) >= least]
    first = {}
    for p, x in sorted(every):
        first.setdefault(x, p)
    texts = list(first)
    up = {x: x for x in texts}

    def f(x):
        while up[x] != x:
            x = up[x]
        return x

    for i, a in enumerate(texts):
        for b in texts[:i]:
            if abs(len(a) - len(b)) <= k and f(a) != f(b) and near(a, b, k):
                up[f(a)] = f(b)
    best = {}
    for x in texts:
        best[f(x)] = min(best.get(f(x), first[x]), first[x])
    gone = {p for p, x in every if best[f(x)] != p}
    return sorted((d, 0 if t is None else len(t.split("\n")), sum((d, i) in gone for i in range(len((t or "").split("\n")))), None if t is None else "\n".join(x for i, x in enumerate(t.split("\n")) if (d, i) not in gone)) for d, t in rows)


@pytest.mark.parametrize("k", [0, 2])
def test_line_dedup(spark, k):
    r = random.Random(k)
    base = ["".join(r.choice("abcdé") for _ in range(r.randrange(6, 15))) for _ in range(10)]

    def mutate(x):
        for _ in range(r.randrange(3)):
            p, c = r.randrange(len(x) + 1), r.choice("abcd")
            x = r.choice([x[:p] + c + x[p:], x[:p] + x[p + 1 :], x[:p] + c + x[p + 1 :]])
        return x

    rows = [(i, None if i == 7 else "\n".join(r.choice(["", "x", " "]) + mutate(r.choice(base)) for _ in range(r.randrange(6)))) for i in range(40)]
    rows += [(40, ""), (41, "\n\n"), (42, "z" * 50_000 + "\r\n" + "z" * 50_000), (43, "same line here\nsame line here ")]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "9 AS n_lines", "'r' AS removed", "1 AS line")
    got = lines.dedup_lines(df, threshold=k, min_chars=6)
    assert sorted((x.doc_id, x.n_lines, x.n_removed, x.text) for x in got.collect()) == brute_lines(rows, k, 6)
    assert "line" in got.columns
    assert lines.dedup_lines(df.limit(0)).count() == 0


def test_cells_of_a_hot_signature_lose_no_pair(spark):
    rows = [(i, f"common beginning {i:04d} end", 25) for i in range(40)]
    df = spark.createDataFrame(rows, "lid long, line string, n int")
    for cell in (3, 600):
        edges = {(e.a, e.b) for e in lines.line_links(df, 1, cell).collect()}
        up = list(range(40))

        def f(x):
            while up[x] != x:
                x = up[x]
            return x

        for a, b in edges:
            up[f(a)] = f(b)
        assert len({f(i) for i in range(40)}) == 1


# op7
def words(t):
    return [x for x in re.split(r"[^\w]+|_", (t or "").lower()) if x]


def brute_leaks(docs, items):
    out = {}
    for d, t in docs:
        w = words(t)
        for i, x in items:
            v = words(x)
            if len(v) < 5 or len(w) < 5:
                if v and v == w:
                    out.setdefault(d, {})[i] = 1.0
                continue
            want = [tuple(v[j : j + 5]) for j in range(len(v) - 4)]
            best = 0.0
            for s in range(max(1, len(w) - len(v) + 1)):
                win = w[s : s + len(v)]
                have = [tuple(win[j : j + 5]) for j in range(len(win) - 4)]
                both = sum(min(want.count(g), have.count(g)) for g in set(want))
                best = max(best, both / (len(want) + len(have) - both))
            if best >= 0.8:
                out.setdefault(d, {})[i] = best
    return out


def test_decontamination(spark):
    r = random.Random(8)
    v = [f"w{i}" for i in range(200)]
    items = [(i, " ".join(r.choice(v) for _ in range(r.randrange(12, 60)))) for i in range(12)] + [(90, "too short item"), (91, None), (92, "rep rep rep rep rep rep rep rep")]
    docs = []
    for i in range(60):
        w = [r.choice(v) for _ in range(r.randrange(80))]
        if i % 3 == 0:
            p = r.choice(items[:12])[1].split()
            for _ in range(r.randrange(3)):
                p[r.randrange(len(p))] = r.choice(v)
            if r.random() < 0.5:
                p.insert(r.randrange(len(p)), "extra")
            w[len(w) // 2 : len(w) // 2] = [x.upper() + r.choice(["", ",", "!"]) for x in p]
        docs.append((i, "  ".join(w)))
    docs += [(60, None), (61, ""), (None, items[0][1]), (62, items[0][1]), (62, items[0][1]), (63, "rep " * 20), (65, "Too short; ITEM!"), (66, "too short items"), (67, "a too short item"), (64, " ".join(v) * 40 + " " + items[1][1])]
    want = brute_leaks(docs, items)
    df = spark.createDataFrame(docs, "doc_id long, text string").selectExpr("*", "'q' AS best_item", "5 AS item", "6 AS start")
    it = spark.createDataFrame(items, "item_id long, text string")
    got = decontaminate.decontaminate(df, it)
    for x in got.collect():
        w = want.get(x.doc_id, {})
        assert x.contaminated == bool(w), x
        assert x.n_items == len(w)
        if w:
            assert math.isclose(x.best_similarity, max(w.values()))
            assert x.best_item == min(i for i, s in w.items() if s == max(w.values()))
    assert got.count() == len(docs)
    assert not decontaminate.decontaminate(df, it.limit(0)).filter("contaminated").count()
    assert decontaminate.decontaminate(df.limit(0), it).count() == 0


def test_decontamination_finds_items_in_another_order(spark):
    r = random.Random(3)
    w = [f"w{i}" for i in range(2000)]
    a, b = r.sample(w, 20), r.sample(w, 40)
    noise = [r.choice(w) for _ in range(200)]
    items = [(1, " ".join(a + b)), (2, " ".join(r.sample(w, 30)))]
    docs = [(1, " ".join(noise[:90] + b + a + noise[90:])), (2, " ".join(b + a)), (3, " ".join(b + a + noise)), (4, " ".join(noise + b + a)), (5, " ".join(noise + a + noise[:60] + b)), (6, " ".join(noise))]
    want = brute_leaks(docs, items)
    assert set(want) == {1, 2, 3, 4}
    got = decontaminate.decontaminate(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"))
    for x in got.collect():
        assert x.contaminated == (x.doc_id in want)
        assert math.isclose(x.best_similarity, max(want.get(x.doc_id, {0: 0.0}).values()))


def test_decontamination_plan_has_no_python(spark, sf):
    plan = decontaminate.op7_simhash_windows(spark, sf)._jdf.queryExecution().toString()
    assert not re.search("Python|Pandas|Arrow|MapIn", plan)


# op1
def flat(vs):
    rows = [(i, t, w) for i, v in enumerate(vs) for t, w in sorted(v.items())]
    return tuple(np.array([r[j] for r in rows], k) for j, k in enumerate((np.int64, np.int64, float)))


@pytest.mark.parametrize("wide", [0, 3, 50])
def test_block_max_index_is_exact(wide):
    r = random.Random(2)
    for _ in range(30):
        vs = [{t: r.random() for t in r.sample(range(12), r.randrange(1, 5))} for _ in range(300)]
        vs = [{t: w / math.sqrt(sum(x * x for x in v.values())) for t, w in v.items()} for v in vs]
        index = toxicity.BlockMaxIndex(300, flat(vs), 12, 8, wide=wide)
        asked = [vs[3], {}, vs[77], vs[77]]
        got = index.top(flat(asked), 4, 7)
        for q, g in zip(asked, got):
            want = sorted((-round(sum(q[t] * v.get(t, 0) for t in q), 12), i) for i, v in enumerate(vs))[:7]
            assert [(i, round(s, 9)) for i, s in g] == [(i, round(-s, 9)) for s, i in want if s < 0]
        alone = index.top(flat(asked), 4, 300, np.array([3, 0, 77, 0]))
        assert 3 not in dict(alone[0]) and 77 not in dict(alone[2]) and 77 in dict(alone[3])
    few = toxicity.BlockMaxIndex(300, flat([{0: 1.0}] * 8 + [{1: 1.0}] * 292), 2, 8)
    assert [i for i, _ in few.top(flat([{0: 1.0}]), 1, 5)[0]] == [0, 1, 2, 3, 4] and few.opened < few.asked
    assert toxicity.BlockMaxIndex(0, flat([]), 2).top(flat([{0: 1.0}]), 1, 5) == [[]]


def brute_toxicity(docs, labels):
    """Scores of {id: text} by plain cosine over all examples; every labelled document is an example."""
    split = {d: Counter(re.findall(r"\w+", (t or "").lower())) for d, t in docs.items()}
    y = {d: v for d, v in labels.items() if v is not None and d in docs and zlib.crc32(str(d).encode()) % 5}
    count = {c: Counter(t for d in y if y[d] == c for t in split[d]) for c in (0, 1)}
    n = [sum(v == c for v in y.values()) for c in (0, 1)]
    df = Counter(t for x in split.values() for t in x)

    def stretch(t):
        g = 0.0
        for c in (0, 1):
            for seen, of in ((count[c][t], count[0][t] + count[1][t]), (n[c] - count[c][t], sum(n) - count[0][t] - count[1][t])):
                g += 2 * seen * math.log(seen * sum(n) / (n[c] * of)) if seen else 0.0
        return 1 + round(max(g, 0.0), 6) / toxicity.UNIT

    weight = {t: (math.log((len(docs) + 1) / (df[t] + 1)) + 1) * stretch(t) for t in set(count[0]) | set(count[1]) if count[0][t] + count[1][t] >= 2}
    unit = {}
    for d, x in split.items():
        v = {t: (1 + math.log(k)) * weight[t] for t, k in x.items() if t in weight}
        norm = math.sqrt(sum(w * w for w in v.values()))
        unit[d] = {t: w / norm for t, w in v.items()}
    near = {}
    for d, v in unit.items():
        near[d] = sorted(((sum(w * unit[e].get(t, 0.0) for t, w in v.items()), e) for e in y if unit[e]), reverse=True)

    bare = [y[d] for d in y if not unit[d]]
    bare = (sum(bare) + (n[1] + 0.5) / (sum(n) + 1)) / (len(bare) + 1)

    def vote(found):
        if not found:
            return bare
        w = [1 / (1 - min(s, 1) + 0.05) for s, _ in found]
        return sum(a * y[e] for a, (_, e) in zip(w, found)) / sum(w)

    top = lambda found: [(s, e) for s, e in found if s > 0][: toxicity.NEIGHBOURS]
    fit = sorted([(vote(top([x for x in near[d] if x[1] != d])), y[d]) for d in y if unit[d]] + [(0.0, 0), (1.0, 1)])
    pools = []
    for v, t in fit:
        pools.append([t, 1, v, v])
        while len(pools) > 1 and (pools[-2][0] >= pools[-1][0] or pools[-2][3] == pools[-1][2]):
            (p, i, a, _), (q, j, _, b) = pools[-2:]
            pools[-2:] = [[(p * i + q * j) / (i + j), i + j, a, b]]
    xs, ys = [v for p in pools for v in p[2:]], [p[0] for p in pools for _ in "ab"]
    return {d: float(np.interp(vote(top(near[d])), xs, ys)) if top(near[d]) else bare for d in docs}, {d: top(near[d])[:1] for d in docs}


def test_query_equals_plain_cosine_votes(spark, sf):
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    labels = {r.doc_id: r.toxic for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    want, best = brute_toxicity(docs, labels)
    got = toxicity.op1_nearest_examples(spark, sf).collect()
    assert len(got) == len(docs)
    assert sum(bool(x.evidence) for x in got) >= 0.95 * sum(bool((t or "").strip()) for t in docs.values())
    for x in got:
        assert x.held_out == (zlib.crc32(str(x.doc_id).encode()) % 5 == 0) and x.predicted == (x.score >= 0.5)
        assert bool(x.evidence) == bool(best[x.doc_id])
        if x.evidence:
            assert math.isclose(x.evidence[0].cosine, best[x.doc_id][0][0], abs_tol=1e-9)
    # of equally near examples either may be taken, which the curve can turn into another score
    assert sum(not math.isclose(x.score, want[x.doc_id], abs_tol=1e-6) for x in got) <= 0.01 * len(got)


def test_toxicity_learns_and_leaves_out(spark):
    r = random.Random(1)
    bad, plain = ["vile", "rotten", "vileness"], [f"word{i}" for i in range(150)]
    docs, labels = [], []
    for i in range(600):
        toxic = i % 5 == 1
        w = [r.choice(plain) for _ in range(40)]
        if toxic:
            for _ in range(3):
                w[r.randrange(40)] = r.choice(bad)
        docs.append((i, " ".join(w), "toxic label words do not matter"))
        if i % 2:
            labels.append((i, int(toxic)))
    docs += [(1000, None, ""), (1001, "", ""), (1002, "unknown", ""), (None, "vile rotten vile", ""), (1003, "vile rotten vile", ""), (1003, "vile rotten vile", ""), (1004, "word1 " * 50_000, "")]
    df = spark.createDataFrame(docs, "doc_id long, text string, score string")
    lab = spark.createDataFrame(labels + [(77777, 1), (None, 1), (5, None)], "doc_id long, toxic int")
    model = toxicity.fit(df.drop("score"), lab)
    held = {i for i, _ in labels if zlib.crc32(str(i).encode()) % 5 == 0}
    assert not held & set(model.names)
    got = toxicity.score(df, model).collect()
    assert len(got) == len(docs) and all(0 <= x.score <= 1 and x.predicted == (x.score >= 0.5) for x in got)
    test = [(x.predicted, dict(labels)[x.doc_id]) for x in got if x.doc_id in held]
    assert sum(p == y for p, y in test) >= 0.95 * len(test)
    assert all(x.predicted == 1 and x.evidence for x in got if x.text == "vile rotten vile")
    assert all(x.predicted == 0 for x in got if x.doc_id in (1000, 1001, 1002, 1004))
    none = toxicity.fit(df.drop("score"), lab.limit(0))
    assert all(0 <= x.score <= 1 for x in toxicity.score(df, none).collect())
    assert toxicity.score(df.limit(0), model).count() == 0


# op8
def test_blocks_of_pages():
    page = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var t="</p>";</script></head><body><header>H</header>
    <nav><ul><li>a<li>b</ul></nav><!-- x --><div class="ad-box">AD</div><article><h1>Head &amp; line</h1><p><b>One <i>two</b> three<br>four&nbsp;five
    <p>caf&eacute; &#x41;&#66; a &lt; b<form>F</form><ul><li>x<li>y</ul><section class="comments"><p>C</p></section><aside>S</aside></article><div id=cookie-notice>N</div><footer>F</footer>"""
    assert html.blocks_of(page) == (["Head & line", "One two three four five", "café AB a < b", "x", "y"], True)
    assert html.blocks_of(None) == ([], False) and html.blocks_of("") == ([], False)
    assert html.blocks_of("<p>a<p>b</p>c < d <") == (["a", "b", "c < d <"], False)
    assert html.blocks_of("<article></article><p>x")[0] == []
    assert html.blocks_of("<main><p title='a>b'>x</main>") == (["x"], True)
    assert html.blocks_of("<script>never closed <p>x") == ([], False)


def test_names_beside_the_article_need_all_parts():
    for name in ("banner-story", "share-price", "search-results-study", "notice-period", "headerless", "menuhin"):
        assert html.blocks_of(f"<article><p>a</p><div class='{name}'><p>kept</p></div></article>")[0] == ["a", "kept"], name
        assert html.blocks_of(f"<div id={name}>kept</div>")[0] == ["kept"], name
    assert html.blocks_of("<section id='social-history'><p>kept</section>")[0] == ["kept"]
    assert html.blocks_of("<article class='related-story'><header class='entry-header'><h1>T</h1></header><p>x</article>") == (["T", "x"], True)
    assert html.blocks_of("<article class='comments related'><p>x</article>") == (["x"], True)
    for name in ("comment-list", "ad-box", "site-footer", "sidebar-left", "cookie-banner", "newsletter_signup", "nav menu2"):
        assert html.blocks_of(f"<article><p>a</p><div class='x {name}'><p>gone</p></div></article>")[0] == ["a"], name


def test_suffix_array_finds_every_repeat():
    r = random.Random(1)
    for _ in range(150):
        s = [[r.randrange(3) for _ in range(r.randrange(14))] for _ in range(r.randrange(1, 5))]
        want = {}
        for i, x in enumerate(s):
            for a in range(len(x) - 2):
                want.setdefault(tuple(x[a : a + 3]), []).append((i, a))
        want = {(*p, len({i for i, _ in at})) for at in want.values() for p in at if len({i for i, _ in at}) > 1}
        page, start, group, pages = html.repeated_windows([np.array(x, np.int64) for x in s], 3)
        assert set(zip(page.tolist(), start.tolist(), pages.tolist())) == want
        assert all((g == h) == (s[p][a : a + 3] == s[q][b : b + 3]) for p, a, g in zip(page, start, group) for q, b, h in zip(page, start, group))
        x = np.array([r.randrange(3) for _ in range(20)])
        order, lcp = html.suffix_array(x)
        assert order.tolist() == sorted(range(20), key=lambda i: x[i:].tolist())
        assert all(n == next((k for k in range(20 - max(a, b)) if x[a + k] != x[b + k]), 20 - max(a, b)) for n, a, b in zip(lcp[1:].tolist(), order, order[1:]))


def test_host_boilerplate(spark):
    r = random.Random(2)
    word = lambda n: " ".join(f"u{r.random():.12f}" for _ in range(n))
    top, end = "welcome to the great site of many words and links", "all rights reserved by the owner of the great site"
    quote, call = "a passage of ten words that some of the articles quote", "please support our work by sending us a small gift"
    own = {i: word(32) for i in range(40)}
    pages = [(i, f"http://h.example/{i}", f"<body><div>{top}</div><p>{own[i]}</p><div>{end}</div>") for i in range(40)]
    want = dict(own)
    for i in range(100, 140):  # marked articles: a quote on some, a call on all
        want[i] = word(32) + (f"\n{quote}" if i % 3 == 0 else "")
        pages.append((i, f"https://M.example:80/{i}", f"<main><p>{want[i].replace(chr(10), '<p>')}<p>{call}</main><div>{top}</div>"))
    copied = word(40)
    for i in range(200, 203):  # near-copies of one article, unmarked
        pages.append((i, f"http://c.example/{i}", f"<p>{copied}<p>{i} only"))
        want[i] = f"{copied}\n{i} only"
    pages += [(90, None, None), (91, "x", ""), (92, "http://other.example/", f"<div>{top}</div>"), (3, "http://h.example/3", pages[3][2]), (93, "http://k.example/", "<article><p>kept</article>"), (94, "http://k.example/2", "<article><p>kept</article>"), (95, "http://h.example/95", "<p>" + "long " * 30_000)]
    want |= {90: "", 91: "", 92: top, 93: "kept", 94: "kept", 95: ("long " * 30_000).strip()}
    df = spark.createDataFrame(pages, "page_id long, url string, html string").selectExpr("*", "1 AS text", "2 AS host", "3 AS n")
    for shard in (400, 7):
        got = html.extract_text(df, shard_pages=shard).collect()
        assert len(got) == len(pages)
        for x in got:
            assert x.text == want[x.page_id] and x.n_chars == len(x.text), (shard, x.page_id)
            assert x.n_boilerplate == (20 if x.page_id < 40 else 10 if 100 <= x.page_id < 140 else 0)
    assert html.extract_text(df.limit(0)).count() == 0


class Article(HTMLParser):
    """Blocks inside article elements, read by the standard library's parser."""

    def __init__(self):
        super().__init__()
        self.depth, self.blocks, self.buf = 0, [], []

    def flush(self):
        t = " ".join("".join(self.buf).split())
        self.buf = []
        if t and self.depth:
            self.blocks.append(t)

    def handle_starttag(self, tag, attrs):
        if tag == "br":
            self.buf.append(" ")
        elif tag not in ("b", "i", "a", "em", "span"):
            self.flush()
        self.depth += tag == "article"

    def handle_endtag(self, tag):
        if tag not in ("b", "i", "a", "em", "span"):
            self.flush()
        self.depth -= tag == "article"

    def handle_data(self, data):
        if self.depth:
            self.buf.append(data)


def test_page_texts_equal_another_reading(spark, sf):
    pages = spark.read.parquet(f"{sf}/pages.parquet").collect()
    want = {}
    for p in pages:
        a = Article()
        a.feed(p.html or "")
        a.close()
        a.flush()
        want[p.page_id] = "\n".join(a.blocks)
    assert {x.page_id: x.text for x in html.op8_host_suffix_array(spark, sf).collect()} == want


def test_digests_are_of_kept_text(spark, sf):
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    got = substrings.op5_suffix_automata(spark, sf).collect()
    want = {d: (n, g, hashlib.sha256(k.encode()).hexdigest()) for d, n, g, k in brute_windows(list(docs.items()), 50)}
    assert {x.doc_id: (x.n_words, x.n_removed, x.kept_sha256) for x in got} == want


def test_bucketed_rows_are_joined_without_moving_them(spark):
    import glob
    import os

    df = spark.range(200).selectExpr("id % 50 AS k", "repeat('x', 30) AS t").groupBy("k").agg({"t": "first"}).withColumnRenamed("first(t)", "t")
    stored = Bucketed(df, ["k"], "few")
    folder = stored.path.removeprefix("file://")
    assert len(glob.glob(folder + "/*.parquet")) <= 4
    probe = spark.range(3).withColumnRenamed("id", "k")
    plan = probe.join(stored.rows.hint("merge"), "k")._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and "Bucketed: true" in plan
    assert probe.join(stored.rows, "k").count() == 3
    stored.drop()
    assert not os.path.exists(folder) and not spark.catalog.tableExists(stored.name)
