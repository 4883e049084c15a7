"""SQL front door: MARGINAL a, b FROM net [WHERE c = 1 AND d = 'x'] (O16), and a decomposition UDTF."""

from __future__ import annotations

import json
import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from .model import Network
from .operators.infer import marginal
from .plans.decomposition import bag_tree, min_fill_order

_NETWORKS: dict[str, Network] = {}
_QUERY = re.compile(r"\s*MARGINAL\s+(?P<vars>[\w\s,]+?)\s+FROM\s+(?P<net>\w+)(?:\s+WHERE\s+(?P<where>.+?))?\s*;?\s*$", re.I | re.S)
_TERM = re.compile(r"\s*(\w+)\s*=\s*(?:'((?:[^']|'')*)'|(-?\d+\.\d+)|(-?\d+)|(true|false))\s*$", re.I)


def register_network(name: str, network: Network) -> None:
    _NETWORKS[name.lower()] = network


def sql(spark: SparkSession, text: str) -> DataFrame:
    """A marginal query; anything else goes to Spark."""
    m = _QUERY.match(text)
    if not m:
        return spark.sql(text)
    evidence = {}
    for term in re.split(r"\s+AND\s+", m["where"], flags=re.I) if m["where"] else []:
        t = _TERM.match(term)
        if not t:
            raise ValueError(f"cannot read {term!r}")
        evidence[t[1]] = t[2].replace("''", "'") if t[2] is not None else float(t[3]) if t[3] else int(t[4]) if t[4] else t[5].lower() == "true"
    return marginal(_NETWORKS[m["net"].lower()], [v.strip() for v in m["vars"].split(",")], evidence or None)


@udtf(returnType="bag int, parent int, variables string")
class DecomposeNetwork:
    """Bags of a hypergraph given as JSON: a list of lists of variables."""

    def eval(self, scopes: str):
        edges = [tuple(e) for e in json.loads(scopes)]
        bags, parent = bag_tree(edges, min_fill_order(edges))
        for i, (b, p) in enumerate(zip(bags, parent)):
            yield i, p, ",".join(sorted(b))


def register(spark: SparkSession) -> None:
    """decompose_network, fwd_index and rev_index in SQL."""
    from .functions import index

    spark.udtf.register("decompose_network", DecomposeNetwork)
    index.register(spark)
