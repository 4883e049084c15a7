"""Join-graph propagation with a degree bound (B2).

Variables are eliminated in order; the functions of a variable's bucket are grouped so that no group
has more variables than the degree. Groups are the nodes, a group's message goes to the bucket of
its next variable, and groups of one bucket are chained by that variable. Without a split the graph
is a tree and two sweeps are exact; with splits the sweeps repeat and the answer is approximate.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import W, Factor, Network
from ..operators.product import pairwise_product
from ..operators.relational import materialise
from ..plans.decomposition import min_fill_order


@dataclass
class JoinGraph:
    scopes: list[tuple[str, ...]]
    owned: list[list[str]]
    edges: list[tuple[int, int, tuple[str, ...]]]
    exact: bool


def build(network: Network, degree: int, order: list[str] | None = None) -> JoinGraph:
    """Mini-buckets along an elimination order."""
    order = order or min_fill_order([f.vars for f in network.factors])
    rank = {v: i for i, v in enumerate(order)}
    waiting: dict[str, list[tuple[frozenset[str], str | int]]] = {v: [] for v in order}
    for f in network.factors:
        waiting[min(f.vars, key=rank.__getitem__)].append((frozenset(f.vars), f.name))
    scopes, owned, edges, exact = [], [], [], True
    for v in order:
        groups: list[tuple[set[str], list]] = []
        for scope, what in sorted(waiting[v], key=lambda x: (-len(x[0]), str(x[1]))):
            fit = next((g for g in groups if len(g[0] | scope) <= max(degree, len(scope))), None)
            if fit is None:
                groups.append((set(scope), [what]))
            else:
                fit[0].update(scope)
                fit[1].append(what)
        exact &= len(groups) <= 1
        last = None
        for scope, what in groups:
            node = len(scopes)
            scopes.append(tuple(sorted(scope, key=rank.__getitem__)))
            owned.append([w for w in what if isinstance(w, str)])
            for w in what:
                if isinstance(w, int):
                    edges.append((w, node, tuple(x for x in scopes[w] if x in scope)))
            rest = frozenset(scope) - {v}
            if rest:
                waiting[min(rest, key=rank.__getitem__)].append((rest, node))
            if last is not None:
                edges.append((last, node, (v,)))
            last = node
    return JoinGraph(scopes, owned, edges, exact)


def join_graph_propagation(network: Network, degree: int, iterations: int = 1, mode: str = "parquet") -> tuple[DataFrame, bool]:
    """(variable, value, mass, prob) and whether they are exact."""
    g = build(network, degree)
    near: dict[int, list[tuple[int, tuple[str, ...]]]] = {i: [] for i in range(len(g.scopes))}
    for a, b, s in g.edges:
        near[a].append((b, s))
        near[b].append((a, s))
    sent: dict[tuple[int, int], Factor] = {}

    def belief(node: int, skip: int | None = None) -> Factor | None:
        parts = [network.factor(n) for n in g.owned[node]] + [sent[k, node] for k, _ in near[node] if k != skip and (k, node) in sent]
        if not parts:
            return None
        vars = tuple(v for v in g.scopes[node] if any(v in f.vars for f in parts))
        parts = [Factor(f.name, f.vars, f.df.select(*f.vars, F.col(W).cast("double").alias(W))) for f in parts]
        return pairwise_product(vars, parts, "greedy")

    def send(a: int, b: int, sep: tuple[str, ...]) -> None:
        f = belief(a, b)
        if f is None:
            return
        keep = tuple(v for v in sep if v in f.vars)
        m = f.onto(keep)
        top = m.df.agg(F.max(W).alias("__m"))
        df = m.df.crossJoin(F.broadcast(top)).select(*keep, (F.col(W) / F.col("__m")).alias(W))  # one row
        sent[a, b] = Factor(f"{a}>{b}", keep, materialise(df, mode))

    for _ in range(1 if g.exact else max(1, iterations)):
        for a, b, s in sorted(g.edges):
            send(a, b, s)
        for a, b, s in sorted(g.edges, key=lambda e: (-e[1], -e[0])):
            send(b, a, s)
    out = None
    for v in network.vars:
        homes = [i for i, s in enumerate(g.scopes) if v in s]
        f = next(f for f in (belief(i) for i in homes) if f is not None and v in f.vars)
        m = f.onto((v,)).df.select(F.lit(v).alias("variable"), F.col(v).cast("string").alias("value"), F.col(W).alias("mass"))
        out = m if out is None else out.unionByName(m)
    z = out.groupBy("variable").agg(F.sum("mass").alias("__z"))
    return out.join(z, "variable").withColumn("prob", F.col("mass") / F.col("__z")).drop("__z"), g.exact
