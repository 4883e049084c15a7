"""Multiway products by one grid shuffle and local level-order tries (M7b-M7e, M14).

Every variable is hashed into a number of shares; a row goes to all cells that agree with the
variables it has, so the rows that join meet in exactly one cell, after one shuffle of each input.
In a cell the inputs become sorted arrays, and the join binds one variable at a time: every input
that has the variable offers its next value by a galloping search until all offers agree.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from ..model import W, Factor


def is_integral(factors: list[Factor]) -> bool:
    return all(t in ("bigint", "int", "smallint", "tinyint") for f in factors for c, t in f.df.dtypes if c != W)


def is_cyclic(scopes: Iterable[Iterable[str]]) -> bool:
    """Does ear removal leave anything?"""
    edges = [set(s) for s in scopes]
    while True:
        n = sum(map(len, edges)) + len(edges)
        for e in edges:
            for v in list(e):
                if sum(v in x for x in edges) == 1:
                    e.discard(v)
        edges = [e for i, e in enumerate(edges) if e and not any(e <= x and (e != x or i > j) for j, x in enumerate(edges) if i != j)]
        if sum(map(len, edges)) + len(edges) == n:
            return bool(edges)


def shares(vars: tuple[str, ...], sizes: list[tuple[tuple[str, ...], int]], cells: int) -> dict[str, int]:
    """Shares per variable whose product is at most ``cells`` and that send the fewest rows."""
    options = [n for n in (1, 2, 3, 4, 6, 8, 12, 16, 24, 32, 48, 64) if n <= cells]
    best, pick = None, {v: 1 for v in vars}
    if len(vars) > 6:  # too many to try: raise the share that costs the least, step by step
        while True:
            now = np.prod(list(pick.values()))
            grow = [v for v in vars if now // pick[v] * pick[v] * 2 <= cells]
            if not grow:
                return pick
            cost = lambda p: sum(n * np.prod([p[v] for v in vars if v not in s], initial=1) for s, n in sizes)
            v = min(grow, key=lambda v: (cost(pick | {v: pick[v] * 2}), v))
            pick[v] *= 2
    for p in itertools.product(options, repeat=len(vars)):
        n = int(np.prod(p))
        if n > cells or n * 2 <= cells and max(p) < options[-1] and n * 2 < cells:
            continue
        share = dict(zip(vars, p))
        cost = sum(k * int(np.prod([share[v] for v in vars if v not in s], initial=1)) for s, k in sizes)
        if best is None or (cost, p) < best:
            best, pick = (cost, p), share
    return pick


def gallop(run: np.ndarray, lo: int, hi: int, y: int) -> int:
    """First position in run[lo:hi] with a value of at least y: doubling steps, then a binary search."""
    step, at = 1, lo
    while at + step < hi and run[at + step] < y:
        at += step
        step *= 2
    return at + int(np.searchsorted(run[at : min(hi, at + step + 1)], y))


class LocalTrie:
    """Sorted columns of a factor with the sibling runs of every level.

    ``values[j]`` are the distinct values of level j under their parents, ``child[j]`` the range of
    each in the level below, and at the last level the weights follow the values.
    """

    def __init__(self, columns: list[np.ndarray], weights: np.ndarray):
        order = np.lexsort(columns[::-1]) if columns else np.arange(len(weights))
        cols = [c[order] for c in columns]
        self.weights = weights[order]
        n = len(self.weights)
        cut = np.zeros(n, bool)
        if n:
            cut[0] = True
        self.values: list[np.ndarray] = []
        starts: list[np.ndarray] = []
        for c in cols:
            cut = cut.copy()
            cut[1:] |= c[1:] != c[:-1]
            at = np.flatnonzero(cut)
            self.values.append(c[at])
            starts.append(at)
        self.child: list[np.ndarray] = []
        for up, low in zip(starts, starts[1:]):
            self.child.append(np.append(np.searchsorted(low, up), len(low)))

    def top(self) -> tuple[int, int]:
        return 0, len(self.values[0]) if self.values else 0

    def below(self, level: int, pos: int) -> tuple[int, int]:
        return int(self.child[level][pos]), int(self.child[level][pos + 1])


class NestedTrie:
    """Pointer trie of dictionaries, the layout that level-order tries replace."""

    def __init__(self, columns: list[np.ndarray], weights: np.ndarray):
        self.root: dict = {}
        for *key, last, w in zip(*(c.tolist() for c in columns), weights.tolist()):
            node = self.root
            for k in key:
                node = node.setdefault(k, {})
            node[last] = w

    def rows(self) -> Iterator[tuple]:
        def walk(node, key):
            for k in sorted(node):
                if isinstance(node[k], dict):
                    yield from walk(node[k], (*key, k))
                else:
                    yield (*key, k, node[k])

        yield from walk(self.root, ())


def agree(runs: list[np.ndarray], spans: list[tuple[int, int]]) -> Iterator[tuple[int, list[int]]]:
    """Values common to all sorted runs, with their positions: everyone catches up with the largest offer (M7d)."""
    at = [lo for lo, _ in spans]
    if any(lo >= hi for lo, hi in spans):
        return
    top = max(int(r[a]) for r, a in zip(runs, at))
    while True:
        for i, (r, (_, hi)) in enumerate(zip(runs, spans)):
            if r[at[i]] < top:
                at[i] = gallop(r, at[i], hi, top)
                if at[i] >= hi:
                    return
        offers = [int(r[a]) for r, a in zip(runs, at)]
        if min(offers) == max(offers):
            yield offers[0], list(at)
            at[0] += 1
            if at[0] >= spans[0][1]:
                return
            top = int(runs[0][at[0]])
        else:
            top = max(offers)


def join_tries(order: list[str], scopes: list[tuple[str, ...]], tries: list[LocalTrie]) -> Iterator[tuple[tuple[int, ...], float]]:
    """Depth-first multiway join with an explicit stack; emits (values in ``order``, weight) (M7e)."""
    holds = [[(i, s.index(v)) for i, s in enumerate(scopes) if v in s] for v in order]

    def offers(depth: int, spans: list[tuple[int, int]]):
        return agree([tries[i].values[j] for i, j in holds[depth]], [spans[i] for i, _ in holds[depth]])

    spans = [t.top() for t in tries]
    if any(lo >= hi for lo, hi in spans):
        return
    one = 1
    stack = [(offers(0, spans), spans, one)]
    key: list[int] = []
    while stack:
        it, spans, w = stack[-1]
        nxt = next(it, None)
        if nxt is None:
            stack.pop()
            if key:
                key.pop()
            continue
        value, at = nxt
        depth = len(stack) - 1
        down, v = list(spans), w
        for (i, j), p in zip(holds[depth], at):
            if j + 1 < len(scopes[i]):
                down[i] = tries[i].below(j, p)
            else:
                v = v * tries[i].weights[p]
        if depth + 1 == len(order):
            yield (*key, value), v
        else:
            key.append(value)
            stack.append((offers(depth + 1, down), down, v))


def join_tries_batched(order: list[str], scopes: list[tuple[str, ...]], tries: list[LocalTrie], rows: int = 1 << 18) -> Iterator[tuple[list[np.ndarray], np.ndarray]]:
    """The same join, many prefixes at a time; yields (a column per variable of ``order``, weights).

    Of the factors that have the next variable the one with the fewest values for a prefix proposes, and the
    others are searched. About ``rows`` proposals are made at a time.
    """
    holds = [[(i, s.index(v)) for i, s in enumerate(scopes) if v in s] for v in order]
    if any(not len(t.weights) for t in tries):
        return
    codes, keys, ends = [], {}, {}
    for own in holds:
        found = np.unique(np.concatenate([tries[i].values[j] for i, j in own]))
        codes.append(found)
        for i, j in own:
            at = np.array([0, len(tries[i].values[0])]) if j == 0 else np.asarray(tries[i].child[j - 1])
            ends[i, j] = at
            keys[i, j] = np.repeat(np.arange(len(at) - 1), np.diff(at)) * len(found) + np.searchsorted(found, tries[i].values[j])

    def extend(depth: int, key: list[np.ndarray], at: dict[int, np.ndarray], w: np.ndarray):
        if depth == len(order):
            yield key, w
            return
        own, m = holds[depth], len(codes[depth])
        spans = [(ends[i, j][at[i]], ends[i, j][at[i] + 1]) for i, j in own]
        least = np.argmin([hi - lo for lo, hi in spans], axis=0)
        for p, (i, j) in enumerate(own):
            mine = np.flatnonzero(least == p)
            lo, hi = spans[p][0][mine], spans[p][1][mine]
            total = np.cumsum(hi - lo)
            a = 0
            while a < len(mine):
                b = max(a + 1, int(np.searchsorted(total, (total[a - 1] if a else 0) + rows, "right")))
                n = hi[a:b] - lo[a:b]
                who = np.repeat(mine[a:b], n)
                pos = {i: np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n) + np.repeat(lo[a:b], n)}
                code = keys[i, j][pos[i]] % m
                for g, h in own:
                    if g != i:
                        want = at[g][who] * m + code
                        pos[g] = np.minimum(np.searchsorted(keys[g, h], want), len(keys[g, h]) - 1)
                        ok = keys[g, h][pos[g]] == want
                        who, code, pos = who[ok], code[ok], {x: y[ok] for x, y in pos.items()}
                if len(who):
                    v = w[who]
                    for g, h in own:
                        if h + 1 == len(scopes[g]):
                            v = v * tries[g].weights[pos[g]]
                    yield from extend(depth + 1, [*[k[who] for k in key], codes[depth][code]], {x: pos[x] if x in pos else y[who] for x, y in at.items()}, v)
                a = b

    kind = np.result_type(*[t.weights.dtype for t in tries])
    yield from extend(0, [], {i: np.zeros(1, np.int64) for i in range(len(tries))}, np.ones(1, kind))


def grid_product(vars: tuple[str, ...], factors: list[Factor], order: list[str] | None = None, cells: int | None = None, batch: int = 1 << 18) -> Factor:
    """The product of integer-valued factors by one shuffle into a grid of cells."""
    order = list(order or vars)
    spark = factors[0].df.sparkSession
    if not is_integral(factors):
        raise ValueError("the grid needs integer variables; encode them with a Domain")
    constants = [f for f in factors if not f.vars]
    factors = [f for f in factors if f.vars]
    scopes = [tuple(v for v in order if v in f.vars) for f in factors]
    cells = cells or int(spark.conf.get("spark.sql.shuffle.partitions"))
    counts = factors[0].df.select(F.lit(0).alias("i"), F.count(F.lit(1)).alias("n"))
    for i, f in enumerate(factors[1:], 1):
        counts = counts.union(f.df.select(F.lit(i).alias("i"), F.count(F.lit(1)).alias("n")))
    sizes = {r.i: r.n for r in counts.collect()}
    share = shares(tuple(order), [(s, sizes[i]) for i, s in enumerate(scopes)], cells)
    kinds = {c: t for f in factors for c, t in f.df.dtypes if c != W}
    w_kind = "double" if any(dict(f.df.dtypes)[W] == "double" for f in factors) else "bigint"
    routed = None
    for i, (f, s) in enumerate(zip(factors, scopes)):
        cell, rows = F.lit(0).cast("bigint"), f.df
        for v in order:
            if share[v] == 1:
                continue
            if v in s:
                where = F.pmod(F.xxhash64(F.col(v).cast("bigint")), F.lit(share[v]))
            else:
                rows = rows.withColumn(f"__{v}", F.explode(F.sequence(F.lit(0), F.lit(share[v] - 1))))
                where = F.col(f"__{v}")
            cell = cell * share[v] + where
        part = rows.select(cell.cast("int").alias("cell"), F.lit(i).cast("smallint").alias("src"), *[(F.col(v).cast("bigint") if v in s else F.lit(None).cast("bigint")).alias(f"k{j}") for j, v in enumerate(order)], F.col(W).cast(w_kind).alias(W))
        routed = part if routed is None else routed.unionByName(part)

    n, place = len(order), {v: j for j, v in enumerate(order)}

    def solve(key, table):
        src = table.column("src").to_numpy()
        cols = [table.column(f"k{j}").combine_chunks() for j in range(n)]
        w = table.column(W).to_numpy()
        tries = []
        for i, s in enumerate(scopes):
            own = np.flatnonzero(src == i)
            tries.append(LocalTrie([cols[place[v]].take(pa.array(own)).to_numpy(zero_copy_only=False).astype(np.int64) for v in s], w[own]))
        kind = pa.float64() if w_kind == "double" else pa.int64()
        parts = [pa.table([pa.array([], pa.int64())] * n + [pa.array([], kind)], names=[*order, W])]
        for found, x in join_tries_batched(order, scopes, tries, batch):
            parts.append(pa.table([pa.array(c.astype(np.int64)) for c in found] + [pa.array(x, kind)], names=[*order, W]))
        return pa.concat_tables(parts)

    fields = ", ".join(f"`{v}` bigint" for v in order)
    out = routed.groupBy("cell").applyInArrow(solve, f"{fields}, {W} {w_kind}")
    out = out.select(*[F.col(v).cast(kinds[v]).alias(v) for v in vars], W)
    for c in constants:
        out = out.crossJoin(c.df.withColumnRenamed(W, "__w")).select(*vars, (F.col(W) * F.col("__w")).alias(W))
    return Factor("bag", tuple(vars), out)
