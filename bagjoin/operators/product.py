"""Bag products: pairwise folds and multiway joins by prefix extension."""

from __future__ import annotations

import functools
import math
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.semiring import SUM_PRODUCT, Semiring
from ..model import W, Factor
from .relational import CROSS_LIMIT, CrossProductError, materialise, multiply

PLAIN, PROJECTED, PAIRWISE = 0, 1, 2


def variable_order(vars: tuple[str, ...], factors: list[Factor], free: tuple[str, ...], order: str, domains: dict[str, int] | None = None) -> list[str]:
    """Order in which a bag binds its variables (M7f).

    ``input``: as given; ``free_first``: those kept come first, so that sums can be emitted per
    prefix; ``min_domain``: small domains first. A variable that shares no factor with those before
    it is put off where another choice exists, to avoid cross products.
    """
    want = list(vars)
    if order == "free_first":
        want = [v for v in vars if v in set(free)] + [v for v in vars if v not in set(free)]
    elif order == "min_domain":
        want = sorted(vars, key=lambda v: ((domains or {}).get(v, 0), v))
    out: list[str] = []
    while want:
        near = {v for f in factors if set(f.vars) & set(out) for v in f.vars}
        pick = next((v for v in want if v in near), want[0])
        out.append(pick)
        want.remove(pick)
    return out


def pairwise_product(vars: tuple[str, ...], factors: list[Factor], order: str = "input", semiring: Semiring = SUM_PRODUCT, hint: str | None = None) -> Factor:
    """Fold the factors two at a time (M8). ``greedy`` next takes a factor that shares variables."""
    left = list(factors)
    out = left.pop(0)
    while left:
        i = 0
        if order == "greedy":
            i = max(range(len(left)), key=lambda j: (len(set(left[j].vars) & set(out.vars)), -j))
        out = multiply(out, left.pop(i), hint, semiring)
    return Factor("bag", tuple(vars), out.df.select(*vars, W))


def split_triangle(vars: tuple[str, ...], factors: list[Factor], semiring: Semiring = SUM_PRODUCT) -> Factor:
    """Pairwise joins of a triangle of two-variable factors, with the heavy values of one corner apart (M8).

    A value of the corner is heavy if the second factor has more than sqrt(N) rows of it. Light values go the
    usual way, at most N sqrt(N) rows. There are at most sqrt(N) heavy ones; they meet the rows of the opposite
    factor, at most N sqrt(N) again, and the two factors of the corner then filter by both variables.
    """
    a, b, c = factors
    corner = set(a.vars) & set(b.vars)
    if not all(len(f.vars) == 2 for f in factors) or len(corner) != 1 or set(c.vars) != (set(a.vars) | set(b.vars)) - corner:
        raise ValueError("not a triangle of two-variable factors")
    (v,) = corner
    n = max(f.size() for f in factors)
    heavy = materialise(b.df.groupBy(v).agg(F.count(F.lit(1)).alias("__n")).filter(F.col("__n") > F.lit(math.isqrt(n))).select(v))
    few = F.broadcast(heavy)  # at most sqrt(n) rows
    light = [Factor(f.name, f.vars, f.df.join(few, v, "left_anti")) for f in (a, b)]
    some = [Factor(f.name, f.vars, f.df.join(few, v, "left_semi")) for f in (a, b)]
    wide = Factor(c.name, (*c.vars, v), c.df.crossJoin(few))
    parts = [pairwise_product(vars, [*light, c], "greedy", semiring), pairwise_product(vars, [wide, *some], "greedy", semiring)]
    return Factor("bag", tuple(vars), parts[0].df.unionByName(parts[1].df))


def _cross(a: DataFrame, b: DataFrame, limit: int) -> DataFrame:
    """Cross join behind a check of the sizes."""
    n = a.limit(limit + 1).count()
    if n * b.limit(max(1, limit // max(1, n)) + 1).count() > limit:
        raise CrossProductError(f"a product of unconnected variables would exceed {limit} rows")
    return a.crossJoin(b)


def extend_product(vars: tuple[str, ...], factors: list[Factor], order: list[str] | None = None, semiring: Semiring = SUM_PRODUCT, observe: Callable[[str, DataFrame], DataFrame] | None = None, cross_limit: int = CROSS_LIMIT) -> Factor:
    """Multiway product by prefix extension (M7a): one variable at a time, all factors agreeing.

    Factors that hold the next variable and share none with the prefix only name its possible values,
    and those are applied to the others before anything is enumerated. Of the factors that are
    connected to the prefix, the one with the fewest values for a row of it proposes them and the
    others filter; with one such factor there is nothing to count. So no step exceeds the size bound
    of its variables. The weights of a factor join in when its last variable is bound, which is the
    filter as well.
    """
    order = order or list(vars)
    see = observe or (lambda _, df: df)
    one = F.lit(semiring.one)
    prefix: DataFrame | None = None
    bound: list[str] = []
    for v in order:
        here = [f for f in factors if v in f.vars]
        if not here:
            raise ValueError(f"{v} is in no factor of the bag")
        known = {f.name: [x for x in bound if x in f.vars] for f in here}
        full = {f.name: len(known[f.name]) + 1 == len(f.vars) for f in here}
        level = {f.name: (f.df.select(*known[f.name], v) if full[f.name] else f.df.select(*known[f.name], v).distinct()) for f in here}
        kind = dict(here[0].df.dtypes)[W]
        met = [f for f in here if known[f.name]]
        loose = [f for f in here if not known[f.name]]
        if not met:
            first = min(loose, key=lambda f: (len(f.vars), f.name))
            values = level[first.name]
            for f in loose:
                if f is not first:
                    values = values.join(level[f.name], v, "left_semi")
            prefix = values.withColumn(W, one.cast(kind)) if prefix is None else _cross(prefix, values, cross_limit)
        else:
            for f in met:
                for g in loose:
                    level[f.name] = level[f.name].join(level[g.name], v, "left_semi")
            if len(met) == 1:
                f = met[0]
                prefix = prefix.join(level[f.name], known[f.name])
            else:
                counted = prefix
                for i, f in enumerate(met):
                    counted = counted.join(level[f.name].groupBy(*known[f.name]).agg(F.count(F.lit(1)).alias(f"__c{i}")), known[f.name])
                names = [f"__c{i}" for i in range(len(met))]
                least = F.least(*names)
                pick = functools.reduce(lambda acc, i: F.when(F.col(f"__c{i}") == least, i).otherwise(acc), reversed(range(len(met) - 1)), F.lit(len(met) - 1))
                counted = counted.withColumn("__pick", pick).drop(*names)
                parts = []
                for i, f in enumerate(met):
                    part = counted.filter(F.col("__pick") == i).drop("__pick").join(level[f.name], known[f.name])
                    for g in met:
                        if g is not f and not full[g.name]:
                            part = part.join(level[g.name], [*known[g.name], v], "left_semi")
                    parts.append(part.select(*bound, v, W))
                prefix = functools.reduce(DataFrame.unionByName, parts)
        bound.append(v)
        prefix = see(v, prefix.select(*bound, W))
        for f in here:
            if full[f.name]:
                prefix = prefix.join(f.df.withColumnRenamed(W, "__w"), list(f.vars)).select(*bound, semiring.times(F.col(W), F.col("__w")).alias(W))
    constants = [f for f in factors if not f.vars]
    for f in constants:
        prefix = prefix.crossJoin(f.df.withColumnRenamed(W, "__w")).select(*bound, semiring.times(F.col(W), F.col("__w")).alias(W))
    return Factor("bag", tuple(vars), prefix.select(*vars, W))


def multiway_product(vars: tuple[str, ...], factors: list[Factor], free: tuple[str, ...] = (), impl: str = "auto", order: str = "input", domains: dict[str, int] | None = None, semiring: Semiring = SUM_PRODUCT, cells: int | None = None) -> Factor:
    """Worst-case-optimal product of a bag (M7): ``extend``, ``grid``, or chosen by shape.

    An acyclic set of factors needs no multiway join, so ``auto`` extends; a cyclic one of integer
    variables goes through the grid, which shuffles each row once.
    """
    from .grid import grid_product, is_cyclic, is_integral

    if impl == "auto":
        impl = "grid" if is_cyclic([f.vars for f in factors]) and is_integral(factors) and semiring is SUM_PRODUCT and len(vars) > 3 else "extend"
    bind = variable_order(vars, factors, free, order, domains)
    if impl == "grid":
        return grid_product(vars, factors, order=bind, cells=cells)
    return extend_product(vars, factors, bind, semiring)


def bag_product(vars: tuple[str, ...], factors: list[Factor], free: tuple[str, ...], strategy: int = PLAIN, indicators: list[Factor] = (), impl: str = "auto", order: str = "input", domains: dict[str, int] | None = None, semiring: Semiring = SUM_PRODUCT) -> tuple[Factor, Factor | None]:
    """Product of a bag by its strategy, and its sum onto ``free`` (M6, M7g).

    The sum is None for an empty ``free``, and the product itself if ``free`` is every variable. Where the
    shape allows it, a multiway product is summed prefix by prefix (M7f), and its rows are not shuffled.
    """
    from .summed import fits, summed_product

    if strategy == PAIRWISE:
        out = pairwise_product(vars, list(factors), "greedy", semiring)
    else:
        out = multiway_product(vars, [*factors, *indicators], free, impl, order, domains, semiring)
    if not free:
        return out, None
    if strategy != PAIRWISE and impl != "extend" and fits([*factors, *indicators], free, semiring):
        return out, summed_product([*factors, *indicators], free, domains)
    return out, out.onto(free, semiring)
