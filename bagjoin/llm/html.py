"""Main text of web pages: structure, and host suffix arrays over every page.

A page is read once into blocks. Elements that never hold the article (menus, page headers and
footers, sidebars, notices, adverts, forms, scripts, reader comments) are left out with all that
they contain. A class or id counts only if all of its parts say so (``comment-list``, ``site-footer``;
not ``share-price``), and the ``header`` of an article belongs to it. If the page marks its article
(``article``, ``main``, role or itemprop), the blocks inside are its text, else all blocks.

The blocks of all pages go through their host's suffix array: the token streams of the host's
distinct pages are concatenated, and substrings of ``min_tokens`` or more that stand on distinct
pages are found from neighbouring suffixes. Those on a large enough share of the host's pages are
boilerplate, whose tokens are removed; unique runs stay. The share is ``SHARE`` of the pages, and for
text in a marked article ``SHARE_MARKED`` of at least ``LEAST_MARKED`` pages: a passage that some
articles quote is text. Pages with equal blocks are one page, and a page of which hardly anything
would be left (``COPY``) keeps its text, as near-copies of an article repeat all of it.

The array is sorted to the depth of ``min_tokens``, as longer repeats are unions of such windows. A
host of many pages is cut into shards; a window on the share of the host's pages is on that share
of some shard's, so each shard names its candidates and these are counted over all shards.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from html import unescape

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import grouped, n_parts, stage, table, text_column

VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
DROP = frozenset("head nav footer aside form script style noscript template iframe svg math button select textarea dialog menu object canvas audio video noembed noframes title".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark meter nobr output progress q rp rt ruby s samp small span strike strong sub sup time tt u var wbr img".split())
CLOSES = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"})}
#: Words of class, id and role values that mark what is not the article.
ASIDE = frozenset("ad ads advert adverts advertisement advertising sponsor sponsored promo promotion sidebar comment comments commentlist replies respond disqus cookie cookies consent gdpr notice notices notification alert banner menu nav navbar navigation breadcrumb breadcrumbs footer header masthead sharing social related recommended recommendations newsletter subscribe subscription signup login popup modal overlay toolbar pagination pager widget complementary contentinfo search".split())
#: Words that may stand beside them in a compound name.
BESIDE = frozenset("site page main global top bottom left right primary secondary side list area section container wrapper wrap box block bar inner outer slot unit form link links button buttons item items posts panel skip share message policy thread reader user id text content".split())
MAIN_ROLE = re.compile(r"\b(?:role\s*=\s*[\"']?main\b|itemprop\s*=\s*[\"']?articleBody\b)", re.I)
NAMED = re.compile(r"\b(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
HIDDEN = re.compile(r"\bhidden(?=[\s=>]|$)|\baria-hidden\s*=\s*[\"']?true|display\s*:\s*none", re.I)
TOKEN = re.compile(r"<!--(?:-?>|.*?(?:--!?>|\Z))|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|\Z)", re.S)
#: A tag with an odd quote in it: up to the next ">".
LOOSE = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)([^>]*)(?:>|\Z)")


def _is_aside(attrs: str) -> bool:
    """Does a class, id or role name something beside the article? All parts of a name must say so."""
    for m in NAMED.finditer(attrs):
        for word in (m[1] or m[2] or m[3] or "").lower().split():
            parts = [p.rstrip("0123456789") for p in re.split(r"[-_:]+", word)]
            parts = [p for p in parts if p]
            if any(p in ASIDE for p in parts) and all(p in ASIDE or p in BESIDE for p in parts):
                return True
    return False


def blocks_of(html: str | None) -> tuple[list[str], bool]:
    """Blocks of a page in order, and whether its article was marked."""
    s = html or ""
    stack: list[str] = []
    drop_at = main_at = -1  # depth at which a dropped element or the article began
    buf: list[str] = []
    outer: list[str] = []
    inner: list[str] = []
    marked = False
    pos, n = 0, len(s)

    def flush() -> None:
        if buf:
            t = " ".join(unescape("".join(buf)).split())
            buf.clear()
            if t:
                (inner if main_at >= 0 else outer).append(t)

    def cut(depth: int) -> None:
        nonlocal drop_at, main_at
        del stack[depth:]
        if drop_at >= depth:
            drop_at = -1
        if main_at >= depth:
            main_at = -1

    while pos < n:
        lt = s.find("<", pos)
        if lt < 0:
            lt = n
        if lt > pos and drop_at < 0:
            buf.append(s[pos:lt])
        if lt == n:
            break
        m = TOKEN.match(s, lt) or LOOSE.match(s, lt)
        if m is None:
            if s.startswith("</", lt):  # a bogus comment
                end = s.find(">", lt)
                pos = n if end < 0 else end + 1
            else:
                if drop_at < 0:
                    buf.append("<")
                pos = lt + 1
            continue
        pos = m.end()
        if m.re is TOKEN and m[2] is None:
            continue
        name, attrs = m[2].lower(), m[3] or ""
        if m[1]:
            if name in INLINE:
                for i in range(len(stack) - 1, -1, -1):
                    if stack[i] == name:
                        if drop_at == i:
                            cut(i)
                        else:
                            del stack[i]
                            drop_at -= drop_at > i
                            main_at -= main_at > i
                        break
                    if stack[i] not in INLINE:
                        break
                continue
            if drop_at < 0:
                flush()
            for i in range(len(stack) - 1, -1, -1):
                if stack[i] == name:
                    cut(i)
                    break
            continue
        if name == "br":
            if drop_at < 0:
                buf.append(" ")
            continue
        if name not in INLINE:
            if drop_at < 0:
                flush()
            if stack and name not in VOID:
                shut, fence = CLOSES.get(name, (None, None))
                for i in range(len(stack) - 1, -1, -1):
                    if stack[i] == "p" and name not in RAW or shut and stack[i] in shut:
                        cut(i)
                        break
                    if stack[i] not in INLINE and (not shut or stack[i] in fence):
                        break
        if name in VOID:
            continue
        if name in RAW:
            end = re.compile(rf"</{name}(?=[\s/>]|\Z)", re.I).search(s, pos)
            if end is None:
                break
            gt = s.find(">", end.start())
            pos = n if gt < 0 else gt + 1
            continue
        if attrs.endswith("/") and name not in INLINE and name in ("svg", "math"):
            continue
        stack.append(name)
        if drop_at < 0:
            is_main = name in ("article", "main") or bool(attrs) and MAIN_ROLE.search(attrs) is not None
            if name in DROP or name == "header" and main_at < 0 or attrs and (HIDDEN.search(attrs) or name not in ("body", "html") and not is_main and not (name == "header" and main_at >= 0) and _is_aside(attrs)):
                drop_at = len(stack) - 1
            elif is_main and main_at < 0:
                main_at = len(stack) - 1
                marked = True
    if drop_at < 0:
        flush()
    return (inner, True) if marked else (outer, False)


def suffix_array(x: np.ndarray, depth: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Suffix array of integer tokens by prefix doubling, and the LCP of neighbours from the rounds' ranks.

    With ``depth`` suffixes are sorted by their first tokens only, a power of two that is at least
    ``depth``, and longer common prefixes are cut to that.
    """
    n = len(x)
    rank = np.unique(x, return_inverse=True)[1].astype(np.int64)
    ranks, k = [rank], 1
    while True:
        nxt = np.full(n, -1, np.int64)
        nxt[: n - k] = rank[k:] if k < n else nxt[:0]
        order = np.lexsort((nxt, rank))
        new = np.zeros(n, np.int64)
        new[order[1:]] = np.cumsum((rank[order[1:]] != rank[order[:-1]]) | (nxt[order[1:]] != nxt[order[:-1]]))
        rank = new
        k *= 2
        if n == 0 or rank[order[-1]] == n - 1 or k >= n or depth and k >= depth:
            break
        ranks.append(rank)
    ranks.append(rank)
    lcp = np.zeros(n, np.int64)
    a, b = order[:-1].copy(), order[1:].copy()
    for level in range(len(ranks) - 1, -1, -1):  # equal ranks of width 2**level extend the common prefix
        r, step = ranks[level], 1 << level
        ok = (a < n) & (b < n)
        same = np.zeros(len(a), bool)
        same[ok] = r[a[ok]] == r[b[ok]]
        lcp[1:][same] += step
        a[same] += step
        b[same] += step
    return order, lcp


def repeated_windows(streams: list[np.ndarray], width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(page, start, group, pages) of all ``width``-token windows that stand on two pages or more.

    ``group`` numbers equal windows, ``pages`` counts the pages that a group is on.
    """
    sizes = np.array([len(s) for s in streams], np.int64)
    none = (np.zeros(0, np.int64),) * 4
    if not sizes.sum():
        return none
    x = np.concatenate([y for i, s in enumerate(streams) for y in (s, np.array([-1 - i]))])  # no common prefix spans pages
    at = np.concatenate([[0], np.cumsum(sizes + 1)])
    page = np.repeat(np.arange(len(streams)), sizes + 1)
    order, lcp = suffix_array(x, width)
    group = np.cumsum(lcp < width) - 1
    p = page[order]
    whole = order + width <= at[p + 1] - 1
    group, p, order = group[whole], p[whole], order[whole]
    seen = np.unique(group * len(streams) + p) // len(streams)
    pages = np.bincount(seen, minlength=int(group.max()) + 1 if len(group) else 0)
    many = pages[group] > 1
    group, p, order = group[many], p[many], order[many]
    return p, order - at[p], group, pages[group]


#: Share of a host's distinct pages from which a repeated run is boilerplate, and least number of pages.
SHARE, LEAST = 0.5, 2
#: The same for runs inside a marked article.
SHARE_MARKED, LEAST_MARKED = 0.8, 10
#: Shards are dealt in so many passes, so that only part of the blocks is in shuffle files at a time.
PASSES = 2
#: A page that would lose this share of its tokens repeats a copy of its article and keeps all.
COPY = 0.8


def _enough(n: int, marked: bool) -> int:
    """Pages that a run must stand on, of ``n``, to be boilerplate."""
    share, least = (SHARE_MARKED, LEAST_MARKED) if marked else (SHARE, LEAST)
    return max(least, int(np.ceil(share * n)))


def _digests(words: list[str], starts: np.ndarray, width: int) -> list[bytes]:
    return [xxhash.xxh128_digest(" ".join(words[i : i + width])) for i in starts.tolist()]


def _cover(n: int, starts: np.ndarray, width: int) -> np.ndarray:
    """Which of ``n`` tokens the windows at ``starts`` cover."""
    edge = np.zeros(n + 1, np.int64)
    np.add.at(edge, starts, 1)
    np.add.at(edge, starts + width, -1)
    return np.cumsum(edge[:-1]) > 0


def _strip(blocks: list[str], starts: np.ndarray, width: int) -> tuple[str, int]:
    """Text without the tokens of the windows at ``starts``, and how many went; a copy keeps all."""
    if not len(starts):
        return "\n".join(blocks), 0
    split = [b.split(" ") for b in blocks]
    gone = _cover(sum(map(len, split)), starts, width)
    if gone.mean() >= COPY:
        return "\n".join(blocks), 0
    kept, at = [], 0
    for ws in split:
        kept.append(" ".join(w for w, g in zip(ws, gone[at : at + len(ws)].tolist()) if not g))
        at += len(ws)
    return "\n".join(t for t in kept if t), int(gone.sum())


def _new_pages(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The rows that differ from the one before in host, shard or page; input is sorted by these."""
    last = None
    for batch in batches:
        seen = list(zip(*(batch.column(c).to_pylist() for c in ("host", "shard", "uid"))))
        yield batch.filter(pa.array([x != y for x, y in zip(seen, [last, *seen])], pa.bool_()))
        last = seen[-1] if seen else last


def extract_text(pages: DataFrame, key: str = "page_id", url: str = "url", html: str = "html", min_tokens: int = 8, shard_pages: int = 400) -> DataFrame:
    """(key, url, text, n_chars, n_boilerplate) of every page; text is empty where nothing is left.

    n_boilerplate counts the tokens that the host's array took out of the page's blocks. Null html
    counts as empty; a null or odd url is of the host without a name. Rows with the same host and
    blocks are one page and get the same text. An empty table gives an empty result.
    """
    spark = pages.sparkSession
    src = pages.select(pages[key].alias("key"), pages[url].alias("url"), pages[html].alias("html"))
    host = F.lower(F.regexp_extract(F.coalesce("url", F.lit("")), r"^[a-zA-Z][\w+.-]*://([^/?#:]*)", 1))
    src = src.select("key", "url", "html", host.alias("host"))
    kind = dict(src.dtypes)["key"]

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        met: set[bytes] = set()  # a page that a task has parsed before takes no part again
        for batch in batches:
            for lo in range(0, batch.num_rows, 500):
                part = batch.slice(lo, 500)
                blocks, marked, uid, new = [], [], [], []
                for s, name in zip(text_column(part, "html"), part.column("host").to_pylist()):
                    b, m = blocks_of(s)
                    blocks.append(b)
                    marked.append(m)
                    uid.append(xxhash.xxh128_digest("\n".join([str(m), *b])))
                    page = xxhash.xxh128_digest(uid[-1] + name.encode())
                    new.append(page not in met)
                    met.add(page)
                yield pa.RecordBatch.from_arrays([part.column("key"), part.column("url"), part.column("host"), pa.array(uid, pa.binary()), pa.array(new, pa.bool_()), pa.array(marked, pa.bool_()), pa.array(blocks, pa.list_(pa.string()))], names=["key", "url", "host", "uid", "new", "marked", "blocks"])

    parsed = stage(src.mapInArrow(parse, f"key {kind}, url string, host string, uid binary, new boolean, marked boolean, blocks array<string>"), "parsed")
    once = parsed.filter("new")
    large = once.select("host", "uid").distinct().groupBy("host").agg(F.count("*").alias("n")).filter(F.col("n") > shard_pages)
    large = stage(large, "large-hosts")
    salt = F.coalesce(F.pmod(F.xxhash64("uid"), F.ceil(F.col("n") / shard_pages)).cast("int"), F.lit(-1))

    def arrays(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """(host, uid, starts) of the pages of hosts of one shard that lose windows; (host, found) of the others."""
        for t in grouped(_new_pages(batches), ["host", "shard"]):
            pages_, name, n = t.num_rows, t.column("host")[0].as_py(), t.column("n")[0].as_py()
            marked = np.array(t.column("marked").to_pylist(), bool)
            ids: dict[str, int] = {}
            words = [[w for b in bs for w in b.split(" ")] for bs in t.column("blocks").to_pylist()]
            page, start, group, seen = repeated_windows([np.array([ids.setdefault(w, len(ids)) for w in ws], np.int64) for ws in words], min_tokens)
            # a shard of a large host asks for the share alone; the least number of pages is that of the host
            need = np.array([_enough(pages_, m) if n is None else max(1, int(np.ceil(s * pages_))) for m, s in ((False, SHARE), (True, SHARE_MARKED))])
            hit = seen >= need[marked[page].astype(int)]
            page, start, group = page[hit], start[hit], group[hit]
            rows = []
            if n is None:
                uids = t.column("uid").to_pylist()
                rows = [(name, uids[i], np.sort(start[page == i]).tolist(), None) for i in np.unique(page).tolist()]
            else:
                first = np.unique(group, return_index=True)[1]
                rows = [(name, None, None, _digests(words[i], np.array([a]), min_tokens)[0]) for i, a in zip(page[first].tolist(), start[first].tolist())]
            kinds = (pa.string(), pa.binary(), pa.list_(pa.int32()), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array([r[j] for r in rows], k) for j, k in enumerate(kinds)], names=["host", "uid", "starts", "h"])

    found = None
    for i in range(PASSES):
        some = once.select("host", "uid", "marked", "blocks").join(large, "host", "left").withColumn("shard", salt).filter(F.pmod(F.xxhash64("host", "shard"), F.lit(PASSES)) == i)
        some = some.repartition(n_parts(spark), "host", "shard").sortWithinPartitions("host", "shard", "uid").select("host", "uid", "marked", "n", "shard", "blocks")
        some = stage(some.mapInArrow(arrays, "host string, uid binary, starts array<int>, h binary"), "repeats")
        found = some if found is None else found.union(some)
    # a candidate stands on a share of its shard's pages, so a shard has at most a page's length / SHARE of them
    maybe = found.filter("h is not null").select("host", "h").distinct().groupBy("host").agg(F.collect_list("h").alias("maybe")).join(large, "host")
    maybe = stage(maybe, "candidates")

    def present(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            names, ns, us, hs = [], [], [], []
            for name, n, uid, bs, ask in zip(*(batch.column(c).to_pylist() for c in ("host", "n", "uid", "blocks", "maybe"))):
                words = [w for b in bs for w in b.split(" ")]
                got = set(ask).intersection(_digests(words, np.arange(max(0, len(words) - min_tokens + 1)), min_tokens))
                names += [name] * len(got)
                ns += [n] * len(got)
                us += [uid] * len(got)
                hs += got
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(ns, pa.int64()), pa.array(us, pa.binary()), pa.array(hs, pa.binary())], names=["host", "n", "uid", "h"])

    counted = once.select("host", "uid", "blocks").join(maybe, "host").select("host", "n", "uid", "blocks", "maybe").mapInArrow(present, "host string, n long, uid binary, h binary")
    counted = counted.distinct().groupBy("host", "n", "h").agg(F.count("*").alias("seen"))
    free, closed = (F.col("seen") >= F.greatest(F.lit(least), F.ceil(F.col("n") * F.lit(share))) for share, least in ((SHARE, LEAST), (SHARE_MARKED, LEAST_MARKED)))
    sure = counted.filter(free | closed).groupBy("host").agg(F.collect_list(F.struct("h", free.alias("free"), closed.alias("closed"))).alias("sure"))
    sure = stage(sure, "boilerplate")
    own = stage(found.filter("uid is not null").select("host", "uid", "starts"), "windows")

    def strip(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, gone = [], []
            for mark, bs, hits, known in zip(*(batch.column(c).to_pylist() for c in ("marked", "blocks", "starts", "sure"))):
                want = {k["h"] for k in known or [] if k["closed" if mark else "free"]}
                if want:
                    words = [w for b in bs for w in b.split(" ")]
                    hits = [i for i, h in enumerate(_digests(words, np.arange(max(0, len(words) - min_tokens + 1)), min_tokens)) if h in want]
                text, lost = _strip(bs, np.array(hits or [], np.int64), min_tokens)
                texts.append(text)
                gone.append(lost)
            yield pa.RecordBatch.from_arrays([batch.column("key"), batch.column("url"), pa.array(texts, pa.string()), pa.array(gone, pa.int32())], names=["key", "url", "text", "n_boilerplate"])

    out = parsed.select("key", "url", "host", "uid", "marked", "blocks").join(own, ["host", "uid"], "left").join(sure, "host", "left")
    out = out.select("key", "url", "marked", "blocks", "starts", "sure").mapInArrow(strip, f"key {kind}, url string, text string, n_boilerplate int")
    return out.select(F.col("key").alias(key), F.col("url").alias(url), "text", F.length("text").cast("long").alias("n_chars"), "n_boilerplate")


def op8_host_suffix_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Main text of all ``pages``, and how much their hosts' suffix arrays took out."""
    return extract_text(table(spark, sf_dir, "pages").select("page_id", "url", "html"))
