"""Arithmetic circuits (B3): compile the elimination once, then evaluate and differentiate.

The surviving rows of a bag's product become product nodes, the entries of its message sum nodes;
leaves are factor entries and value indicators. Rows that are zero never become nodes. Nodes and
edges are DataFrames; evaluation is one join and aggregation per layer.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import W, Factor, Network
from ..operators.product import pairwise_product
from ..operators.relational import materialise
from ..plans.decomposition import Decomposition, decompose


def _id(tag: str, cols: list[str]):
    return F.sha2(F.concat_ws("\x1f", F.lit(tag), *[F.col(c).cast("string") for c in cols]), 256)


@dataclass
class Circuit:
    """nodes (id, layer, op, variable, value, weight) and edges (parent, child)."""

    nodes: DataFrame
    edges: DataFrame
    layers: int
    compile_seconds: float
    mode: str
    times: dict[str, float] = field(default_factory=dict)

    def evaluate(self, evidence: dict | None = None) -> tuple[DataFrame, DataFrame]:
        """((variable, value, mass, prob), (z)) under evidence: values upwards, derivatives downwards."""
        began = time.perf_counter()
        evidence = {k: str(v) for k, v in (evidence or {}).items()}
        on = F.lit(1.0)
        for v, x in evidence.items():
            on = F.when((F.col("variable") == v) & (F.col("value") != x), 0.0).otherwise(on)
        leaf = self.nodes.filter("layer = 0").select("id", F.when(F.col("op") == "indicator", on).otherwise(F.col("weight")).alias("val"))
        values = {0: materialise(leaf, self.mode)}
        known = values[0]
        for layer in range(1, self.layers + 1):
            here = self.nodes.filter(F.col("layer") == layer).select(F.col("id").alias("parent"), "op")
            fed = self.edges.join(here, "parent").join(known.select(F.col("id").alias("child"), "val"), "child")
            agg = fed.groupBy("parent").agg(F.first("op").alias("op"), F.sum("val").alias("s"), F.product("val").alias("p"))
            values[layer] = materialise(agg.select(F.col("parent").alias("id"), F.when(F.col("op") == "sum", F.col("s")).otherwise(F.col("p")).alias("val")), self.mode)
            known = known.unionByName(values[layer])
        z = values[self.layers].select(F.col("val").alias("z"))
        grad = materialise(values[self.layers].select("id", F.lit(1.0).alias("d")), self.mode)
        total = None
        for layer in range(self.layers, 0, -1):
            here = self.nodes.filter(F.col("layer") == layer).select(F.col("id").alias("parent"), "op").join(grad.select(F.col("id").alias("parent"), "d"), "parent")
            fed = self.edges.join(here, "parent").join(known.select(F.col("id").alias("child"), "val"), "child")
            rest = fed.groupBy("parent").agg(F.sum((F.col("val") == 0).cast("int")).alias("zeros"), F.product(F.when(F.col("val") == 0, 1.0).otherwise(F.col("val"))).alias("rest"))
            fed = fed.join(rest, "parent")
            others = F.when(F.col("zeros") == 0, F.col("rest") / F.col("val")).when((F.col("zeros") == 1) & (F.col("val") == 0), F.col("rest")).otherwise(0.0)
            step = fed.select(F.col("child").alias("id"), (F.col("d") * F.when(F.col("op") == "sum", 1.0).otherwise(others)).alias("d"))
            # a child may hang from parents of several layers: what reaches it is summed when its own layer comes
            total = step if total is None else total.unionByName(step)
            total = materialise(total.groupBy("id").agg(F.sum("d").alias("d")), self.mode)
            grad = total
        leaf_d = self.nodes.filter("op = 'indicator'").join(total, "id").join(values[0], "id")
        m = leaf_d.select("variable", "value", (F.col("d") * F.col("val")).alias("mass")).filter("mass > 0")
        zs = m.groupBy("variable").agg(F.sum("mass").alias("__z"))
        out = m.join(zs, "variable").withColumn("prob", F.col("mass") / F.col("__z")).drop("__z")
        self.times["evaluate"] = time.perf_counter() - began
        return out, z


def compile_circuit(network: Network, dec: Decomposition | None = None, mode: str = "parquet") -> Circuit:
    """Trace the up pass into nodes and edges."""
    began = time.perf_counter()
    dec = dec or decompose(network)
    if len(dec.roots) != 1:
        raise ValueError("compile the trees of a forest one by one")
    depth = {b: i for i, bs in enumerate(dec.levels) for b in bs}
    deepest = max(depth.values())
    nodes, edges, up = [], [], {}
    for f in network.factors:
        nodes.append(f.df.select(_id(f"f:{f.name}", list(f.vars)).alias("id"), F.lit(0).alias("layer"), F.lit("entry").alias("op"), F.lit(None).cast("string").alias("variable"), F.lit(None).cast("string").alias("value"), F.col(W).cast("double").alias("weight")))
    home = {}
    for b in sorted(depth, key=lambda b: (-depth[b], b)):
        for v in dec.chi[b]:
            home[v] = b  # the bag nearest to the root that holds it
    for v in network.vars:
        own = None
        for f in network.factors:
            if v in f.vars:
                part = f.df.select(F.col(v).alias(v))
                own = part if own is None else own.union(part)
        own = own.distinct()
        nodes.append(own.select(_id(f"v:{v}", [v]).alias("id"), F.lit(0).alias("layer"), F.lit("indicator").alias("op"), F.lit(v).alias("variable"), F.col(v).cast("string").alias("value"), F.lit(1.0).alias("weight")))
    for level in reversed(dec.levels):
        for b in level:
            inputs = [network.factor(n) for n in dec.alpha[b]] + [up[k] for k in dec.children[b]]
            rows = materialise(pairwise_product(dec.chi[b], inputs, "greedy").df.select(*dec.chi[b]), mode)
            at = 2 * (deepest - depth[b]) + 1
            me = _id(f"b:{b}", list(dec.chi[b]))
            nothing = [F.lit(None).cast("string").alias("variable"), F.lit(None).cast("string").alias("value"), F.lit(None).cast("double").alias("weight")]
            nodes.append(rows.select(me.alias("id"), F.lit(at).alias("layer"), F.lit("product").alias("op"), *nothing))
            for n in dec.alpha[b]:
                edges.append(rows.select(me.alias("parent"), _id(f"f:{n}", list(network.factor(n).vars)).alias("child")))
            for v in dec.chi[b]:
                if home[v] == b:
                    edges.append(rows.select(me.alias("parent"), _id(f"v:{v}", [v]).alias("child")))
            for k in dec.children[b]:
                edges.append(rows.select(me.alias("parent"), _id(f"m:{k}", list(up[k].vars)).alias("child")))
            sep = dec.separator(b) if dec.parent[b] >= 0 else ()
            out = rows.select(*sep).distinct() if sep else rows.limit(1).select(F.lit(1).alias("__one"))
            nodes.append(out.select(_id(f"m:{b}", list(sep)).alias("id"), F.lit(at + 1).alias("layer"), F.lit("sum").alias("op"), *nothing))
            edges.append(rows.select(_id(f"m:{b}", list(sep)).alias("parent"), me.alias("child")))
            if dec.parent[b] >= 0:
                up[b] = Factor(f"up{b}", sep, out.withColumn(W, F.lit(1)))
    all_nodes, all_edges = nodes[0], edges[0]
    for x in nodes[1:]:
        all_nodes = all_nodes.unionByName(x)
    for x in edges[1:]:
        all_edges = all_edges.unionByName(x)
    made = Circuit(materialise(all_nodes, mode), materialise(all_edges, mode), 2 * deepest + 2, 0.0, mode)
    made.compile_seconds = time.perf_counter() - began
    return made
