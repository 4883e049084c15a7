"""Many small bags in few Spark jobs.

A network of a thousand bags cannot afford a job per bag. Factors go into one long table; whole
trees whose predicted size is under a budget are calibrated in one grouped task each, or one level
of bags at a time is multiplied in one job.
"""

from __future__ import annotations

import collections
import functools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import W, Factor, Network
from ..plans.decomposition import Decomposition, decompose
from ..plans.cover import log2_agm
from .local import Listing, calibrate, onto, product

#: log2 of the rows that all bags of a tree may have in one task.
BUDGET = 24.0


class BatchLimitError(ValueError):
    """A tree's bags are too large for one task; use the bag-wise engine."""


def predicted_rows(dec: Decomposition, comp: list[int]) -> float:
    """Bound of the rows of all bags of a tree together; bags of equal shape are bounded once."""
    holds: dict[str, list[Factor]] = {}
    for f in dec.network.factors:
        for v in f.vars:
            holds.setdefault(v, []).append(f)
    seen: dict[tuple, float] = {}
    total = 0.0
    for b in comp:
        place = {v: i for i, v in enumerate(dec.chi[b])}
        met = {f.name: f for v in dec.chi[b] for f in holds[v]}
        known = sorted((tuple(place[v] for v in f.vars if v in place), dec.network.sizes[n]) for n, f in met.items())
        shape = (len(place), tuple(known))
        if shape not in seen:
            seen[shape] = 2.0 ** min(log2_agm(range(len(place)), {i: x for i, x in enumerate(known)}), 1000.0)
        total += seen[shape]
    return total


def _long(items: list[tuple[int, str, Factor]]) -> DataFrame:
    """(unit, src, vals, w) rows of factors."""
    parts = [f.df.select(F.lit(u).alias("unit"), F.lit(n).alias("src"), F.array(*[F.col(v).cast("string") for v in f.vars]).alias("vals"), F.col(W).cast("double").alias(W)) for u, n, f in items]
    return functools.reduce(DataFrame.unionByName, parts)


def _listings(table: pa.Table, scopes: dict[str, list[tuple[str, ...]]]) -> tuple[dict[tuple[str, tuple[str, ...]], Listing], dict[str, list[str]]]:
    """Factors of a unit with codes per variable; values keep their order of appearance per variable."""
    src = np.array(table.column("src").to_pylist(), dtype=object)
    vals, w = table.column("vals").to_pylist(), table.column(W).to_numpy()
    names: dict[str, dict[str, int]] = {}
    out = {}
    for s, uses in scopes.items():
        at = np.flatnonzero(src == s)
        rows = [vals[i] for i in at.tolist()]
        for vars in uses:
            codes = np.zeros((len(at), len(vars)), np.int64)
            for j, v in enumerate(vars):
                book = names.setdefault(v, {})
                codes[:, j] = [book.setdefault(r[j], len(book)) for r in rows]
            out[s, vars] = Listing(vars, codes, w[at])
    return out, {v: list(b) for v, b in names.items()}


def solve_trees(network: Network, templates: dict[str, str] | None = None, dec: Decomposition | None = None, budget: float = BUDGET, measured: bool = False) -> DataFrame:
    """(variable, value, prob) of all variables, and rows (NULL, NULL, log Z) per tree, in one job.

    ``templates`` maps factors to the factor whose rows they repeat under other variable names, so
    that a time-sliced network is stored once. A tree whose bags may have over 2^``budget`` rows raises
    BatchLimitError. The bound ignores messages; ``measured`` lets such a tree run, and its task counts the
    rows of each product before it makes them and fails over the budget.
    """
    templates = templates or {}
    dec = dec or decompose(network, root="centre")
    by = {f.name: f for f in network.factors}
    items, plans = [], {}
    for u, comp in enumerate(dec.components()):
        rows = 0.0 if measured else predicted_rows(dec, comp)
        if rows > 2**budget:
            raise BatchLimitError(f"the bags of tree {u} may have {rows:.3g} rows, over 2^{budget:g}")
        names = [n for b in comp for n in dec.alpha[b]]
        for src in dict.fromkeys(templates.get(n, n) for n in names):
            items.append((u, src, by[src]))
        place = {b: i for i, b in enumerate(comp)}
        plans[u] = ([dec.chi[b] for b in comp], [place.get(dec.parent[b], -1) for b in comp], [[(templates.get(n, n), by[n].vars) for n in dec.alpha[b]] for b in comp])

    def solve(key, table):
        chi, parent, alpha = plans[key[0].as_py()]
        scopes: dict[str, list] = {}
        for own in alpha:
            for s, vars in own:
                scopes.setdefault(s, []).append(vars)
        found, names = _listings(table, scopes)
        missing = [[v for v in c if not any(v in vars for _, vars in own)] for c, own in zip(chi, alpha)]
        ones = {v: Listing((v,), np.arange(len(names[v]))[:, None], np.ones(len(names[v]))) for m in missing for v in m}
        inputs = [[found[s, vars] for s, vars in own] or [ones[v] for v in m] for own, m in zip(alpha, missing)]
        beliefs, log_z = calibrate(chi, parent, inputs, parent.index(-1), 2.0**budget)
        out = [(None, None, log_z)]
        home: dict[str, int] = {}
        for b, f in beliefs.items():
            for v in f.vars:
                if v not in home or len(f.w) < len(beliefs[home[v]].w):
                    home[v] = b
        for v, b in home.items():
            m = onto(beliefs[b], (v,))
            out += [(v, names[v][c], p) for c, p in zip(m.codes[:, 0].tolist(), m.w.tolist())]
        return pa.table({"variable": pa.array([r[0] for r in out], pa.string()), "value": pa.array([r[1] for r in out], pa.string()), "prob": pa.array([r[2] for r in out], pa.float64())})

    return _long(items).groupBy("unit").applyInArrow(solve, "variable string, value string, prob double")


def _alone(factors: list[Factor], free: tuple[str, ...]) -> list[Factor]:
    """Factors with the variables summed out that no other factor of the bag has and that are not asked for."""
    uses = collections.Counter(v for f in factors for v in f.vars)
    return [f.sum_out([v for v in f.vars if uses[v] == 1 and v not in free]) for f in factors]


def run_level(bags: dict[int, list[Factor]], free: dict[int, tuple[str, ...]]) -> DataFrame:
    """(bag, vals, w): the products of many bags summed onto their free variables, as one job.

    Variables of a single factor are summed out before. A bag is dealt into shards by the hash of a variable
    that all its factors have, as rows of different values never meet; where there is none, it is one group.
    """
    bags = {b: _alone(fs, tuple(free[b])) for b, fs in bags.items()}
    scopes = {b: {f"{b}:{i}": [f.vars] for i, f in enumerate(fs)} for b, fs in bags.items()}
    spark = next(f for fs in bags.values() for f in fs).df.sparkSession
    shards = max(1, 4 * int(spark.conf.get("spark.sql.shuffle.partitions")) // len(bags))
    parts, split = [], False
    for b, fs in bags.items():
        common = set.intersection(*[set(f.vars) for f in fs])
        by = next(iter(sorted(common & set(free[b])) + sorted(common)), None)
        split |= by is not None and by not in free[b]  # then shards share results
        for i, f in enumerate(fs):
            shard = F.pmod(F.xxhash64(F.col("vals")[f.vars.index(by)]), F.lit(shards)) if by else F.lit(0).cast("bigint")
            parts.append(_long([(b, f"{b}:{i}", f)]).withColumn("shard", shard))

    def solve(key, table):
        b = key[0].as_py()
        found, names = _listings(table, scopes[b])
        out = onto(product(list(found.values())), tuple(free[b]))
        vals = [[names[v][c] for v, c in zip(out.vars, row)] for row in out.codes.tolist()]
        return pa.table({"bag": pa.array([b] * len(vals), pa.int32()), "vals": pa.array(vals, pa.list_(pa.string())), W: pa.array(out.w, pa.float64())})

    out = functools.reduce(DataFrame.unionByName, parts).groupBy("unit", "shard").applyInArrow(solve, f"bag int, vals array<string>, {W} double")
    return out.groupBy("bag", "vals").agg(F.sum(W).alias(W)) if split else out
