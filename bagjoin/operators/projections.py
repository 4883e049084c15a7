"""Indicator projections: look-ahead pruning with the supports of other bags' factors (M9)."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import W, Factor, Network
from ..plans.decomposition import Decomposition
from .relational import materialise, reduce_by


@dataclass(frozen=True)
class ProjectionPolicy:
    """Which projections are worth their cost (M9b). ``ALL_PROJECTIONS`` takes all of them.

    ``skip_below``: leave out factors of the subtree, whose messages already tell as much.
    """

    max_density: float = 0.5
    min_arity: int = 2
    max_per_bag: int | None = 8
    skip_below: bool = True


ALL_PROJECTIONS = ProjectionPolicy(1.0, 1, None, False)


def indicator(factor: Factor, vars: tuple[str, ...], kind: str = "bigint") -> Factor:
    """Distinct tuples of a factor on some of its variables, each of weight one."""
    keep = tuple(v for v in factor.vars if v in set(vars))
    return Factor(f"has_{factor.name}", keep, factor.support(keep).withColumn(W, F.lit(1).cast(kind)))


class ProjectionCache:
    """Projections computed at first use and kept by (factor, variables)."""

    def __init__(self, network: Network, mode: str = "parquet"):
        self.network, self.mode = network, mode
        self.kept: dict[tuple[str, frozenset[str]], Factor] = {}
        self.counts: dict[tuple[str, frozenset[str]], int] = {}

    def get(self, name: str, vars: tuple[str, ...]) -> Factor:
        key = (name, frozenset(vars))
        if key not in self.kept:
            wider = next((p for (n, vs), p in self.kept.items() if n == name and key[1] < vs), None)
            f = self.network.factor(name)
            p = indicator(wider.named(name) if wider else f, vars, dict(f.df.dtypes)[W])
            self.kept[key] = Factor(p.name, p.vars, materialise(p.df, self.mode))
        return self.kept[key]

    def density(self, name: str, vars: tuple[str, ...]) -> float:
        key = (name, frozenset(vars))
        if key not in self.counts:
            f = self.network.factor(name)
            self.counts[key] = self.network.sizes[name] if set(vars) == set(f.vars) else self.get(name, vars).size()
        cells = 1
        for v in vars:
            cells *= self.network.domains[v]
        return self.counts[key] / cells


def candidates(dec: Decomposition, bag: int) -> list[tuple[str, tuple[str, ...]]]:
    """Factors assigned elsewhere that share variables with a bag, with what they share."""
    own = dec.chi[bag]
    out = []
    for f in dec.network.factors:
        if f.name not in dec.alpha[bag]:
            shared = tuple(v for v in own if v in f.vars)
            if shared:
                out.append((f.name, shared))
    return out


def indicators_for(dec: Decomposition, bag: int, cache: ProjectionCache, policy: ProjectionPolicy, below: set[str] = frozenset()) -> list[Factor]:
    """The projections a bag should use, sparsest first; ``below``: factors whose messages already tell as much."""
    found = []
    for name, shared in candidates(dec, bag):
        if policy.skip_below and name in below or len(shared) < policy.min_arity:
            continue
        d = cache.density(name, shared)
        if len(shared) == 1 and d >= 1.0 or d > policy.max_density:
            continue
        found.append((d, name, shared))
    return [cache.get(n, s) for _, n, s in sorted(found)[: policy.max_per_bag]]


def apply_indicators(factors: list[Factor], indicators: list[Factor], mode: str) -> tuple[list[Factor], list[Factor]]:
    """``input``: they join in the product. ``semijoin``: they filter the inputs that hold all their variables (M9d).

    Spark turns the semi-joins into run-time Bloom filters where those pay off.
    """
    if mode == "input":
        return factors, indicators
    left, out = list(indicators), []
    for f in factors:
        for p in indicators:
            if set(p.vars) <= set(f.vars):
                f = reduce_by(f, p)
                if p in left:
                    left.remove(p)
        out.append(f)
    return out, left


def projection_report(dec: Decomposition, cache: ProjectionCache) -> DataFrame:
    """(bag, factor, vars, density) of every candidate."""
    rows = [(b, n, ",".join(s), float(cache.density(n, s))) for b in range(len(dec.chi)) for n, s in candidates(dec, b)]
    return dec.network.spark.createDataFrame(rows, "bag int, factor string, vars string, density double")
