"""Evidence and determined variables before decomposition."""

from __future__ import annotations

import itertools

from pyspark.sql import functions as F

from ..model import W, Factor, InconsistentEvidence, Network
from .relational import materialise, reduce_by


def apply_evidence(network: Network, evidence: dict) -> Network:
    """Filter factors to the observed values and drop the variables.

    Factors that are bound completely stay as constants without variables; their weight is folded
    into Z. A variable of the evidence that no factor has raises KeyError.
    """
    unknown = set(evidence) - set(network.vars)
    if unknown:
        raise KeyError(f"not in the network: {sorted(unknown)}")
    out = []
    for f in network.factors:
        for v in [v for v in f.vars if v in evidence]:
            f = f.where(v, evidence[v])
        out.append(f)
    domains = {v: d for v, d in network.domains.items() if v not in evidence}
    kept = {f.name: network.sizes[f.name] for f, g in zip(out, network.factors) if f is g}
    return Network.of(out, domains, kept | {f.name: f.df.count() for f in out if f.name not in kept}, scale=network.scale)


def singleton_consistency(network: Network, mode: str = "arc", max_rounds: int | None = None, keep: str = "parquet") -> tuple[Network, dict]:
    """Variables with one supported value become evidence.

    ``arc``: factors are reduced by the supports of their neighbours until no count falls.
    ``exact``: supports of the whole product, by calibration with 0/1 weights.
    Returns the smaller network and the values found.
    """
    factors = list(network.factors)
    if mode == "exact":
        from ..functions.semiring import BOOLEAN
        from .infer import InferConfig, infer

        ones = Network.of([Factor(f.name, f.vars, f.df.withColumn(W, F.lit(1).cast("bigint"))) for f in factors], network.domains, network.sizes)
        cal = infer(ones, "pairwise", config=InferConfig(semiring=BOOLEAN, calibration="product"))
        values = cal.variable_marginals(probs=False)
        found = {r.variable: r.value for r in values.groupBy("variable").agg(F.count(F.lit(1)).alias("n"), F.first("value").alias("value")).filter("n = 1").collect()}
    else:
        before = None
        for done in itertools.count():  # rows only go, so this settles
            if done == max_rounds:
                raise RuntimeError(f"not settled after {max_rounds} rounds")
            factors = [Factor(f.name, f.vars, materialise(_reduced(f, factors).df, keep)) for f in factors]
            now = tuple(f.df.count() for f in factors)
            if 0 in now:
                raise InconsistentEvidence("a factor has no supported row")
            if now == before:
                break
            before = now
        found = {}
        for v in network.vars:
            f = next(f for f in factors if v in f.vars)
            two = [r[0] for r in f.df.select(F.col(v).cast("string")).distinct().limit(2).collect()]
            if len(two) == 1:
                found[v] = two[0]
    typed = {}
    for v, x in found.items():
        f = next(f for f in factors if v in f.vars)
        typed[v] = f.df.filter(F.col(v).cast("string") == F.lit(x)).select(v).first()[0]
    reduced = Network.of(factors, network.domains, scale=network.scale) if mode == "arc" else network
    return (apply_evidence(reduced, typed) if typed else reduced), typed


def _reduced(f: Factor, factors: list[Factor]) -> Factor:
    for g in factors:
        if g.name != f.name and set(g.vars) & set(f.vars):
            f = reduce_by(f, g)
    return f
