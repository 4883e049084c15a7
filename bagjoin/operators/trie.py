"""Level-order tries as tables, and tries from indices."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..model import Factor
from .grid import LocalTrie


def level_order_trie(factor: Factor, order: list[str] | None = None) -> DataFrame:
    """(level, pos, parent_pos, value, child_lo, child_hi) of a factor's trie, values as strings.

    Positions are dense ranks of prefixes. Ranks inside a first value come from a window partitioned
    by it; the offsets of the first values are summed over one row per value, so no window holds the
    factor's rows in one task.
    """
    order = list(order or factor.vars)
    base = factor.df.select(*order).distinct()
    first = order[0]
    levels = []
    per = base.groupBy(first).agg(*[F.count_distinct(*order[: j + 1]).alias(f"n{j}") for j in range(len(order))])
    total = Window.orderBy(first).rowsBetween(Window.unboundedPreceding, -1)  # one row per value of the first variable
    offsets = per.select(first, *[F.coalesce(F.sum(f"n{j}").over(total), F.lit(0)).alias(f"o{j}") for j in range(len(order))])
    ranks = base
    for j in range(len(order)):
        w = Window.partitionBy(first).orderBy(*order[: j + 1])
        ranks = ranks.withColumn(f"r{j}", F.dense_rank().over(w) - 1)
    ranks = ranks.join(offsets, first).select(*order, *[(F.col(f"r{j}") + F.col(f"o{j}")).cast("long").alias(f"p{j}") for j in range(len(order))])
    for j, v in enumerate(order):
        lo, hi = (F.min(f"p{j + 1}"), F.max(f"p{j + 1}")) if j + 1 < len(order) else (F.lit(None).cast("long"), F.lit(None).cast("long"))
        parent = F.first(f"p{j - 1}") if j else F.lit(None).cast("long")
        levels.append(ranks.groupBy(f"p{j}", v).agg(parent.alias("parent_pos"), lo.alias("child_lo"), hi.alias("child_hi")).select(F.lit(j).alias("level"), F.col(f"p{j}").alias("pos"), "parent_pos", F.col(v).cast("string").alias("value"), "child_lo", "child_hi"))
    out = levels[0]
    for x in levels[1:]:
        out = out.unionByName(x)
    return out


def trie_from_index(idx: np.ndarray, weights: np.ndarray, sizes: list[int], kind: str = "reverse") -> LocalTrie:
    """A trie from an index list. The reverse index gives up one variable at a time by modulo, in trie
    order; the forward index needs a division by the product of the later domains for each (M15c)."""
    idx = np.asarray(idx, np.int64)
    cols = []
    if kind == "reverse":
        rest = idx
        for s in sizes:
            rest, code = np.divmod(rest, s)
            cols.append(code)
    else:
        place = int(np.prod(sizes, dtype=object))
        for s in sizes:
            place //= s
            cols.append(idx // place % s)
    return LocalTrie(cols, np.asarray(weights))
