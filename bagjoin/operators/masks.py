"""Marginals of a clique of pair constraints whose product is too long to list.

Pairwise joins list the leading variables. Each of those rows is then extended inside a task, the values of
every later variable that agree with it being the bits of one integer; the last two variables are counted
from their bits and never listed.
"""

from __future__ import annotations

import functools
import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Factor
from .product import pairwise_product

#: Values of a variable must be codes below this.
BITS = 63
#: Rows that a task extends at a time.
ROWS = 1 << 18


def fits(domains: dict[str, int]) -> bool:
    return max(domains.values()) <= BITS


def _masks(factors: list[Factor]) -> dict[tuple[str, str], np.ndarray]:
    """Per ordered pair of variables, the bits of the second's values that agree with each value of the first."""
    parts = []
    for f in factors:
        for x, y in (f.vars, f.vars[::-1]):
            bits = F.bit_or(F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col(y).cast("int")))
            parts.append(f.df.groupBy(F.col(x).alias("v")).agg(bits.alias("bits")).select(F.lit(x).alias("x"), F.lit(y).alias("y"), "v", "bits"))
    out = {p: np.zeros(BITS, np.int64) for f in factors for p in (f.vars, f.vars[::-1])}
    for r in functools.reduce(DataFrame.unionByName, parts).collect():  # at most BITS rows for each of the pairs
        out[r.x, r.y][r.v] = r.bits
    return out


def clique_marginals(vars: tuple[str, ...], factors: list[Factor], lead: int = 4) -> DataFrame:
    """(variable, value, mass) of the product of one constraint per pair of ``vars``, codes 0..62, weights one."""
    if {frozenset(f.vars) for f in factors} != {frozenset(p) for p in itertools.combinations(vars, 2)} or len(factors) != len(vars) * (len(vars) - 1) // 2 or not 2 <= lead <= len(vars) - 2:
        raise ValueError("needs one factor per pair of variables, and two variables after the leading ones")
    spark = factors[0].df.sparkSession
    agree = _masks(factors)
    first = vars[:lead]
    rows = pairwise_product(first, [f for f in factors if set(f.vars) <= set(first)], "greedy").df.select(*first)
    y, z = vars[-2:]
    yz, zy = agree[y, z], agree[z, y]

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mass = {v: np.zeros(BITS, np.int64) for v in vars}

        def count(have: list[np.ndarray], left: dict[str, np.ndarray]) -> None:
            total = np.zeros(len(left[y]), np.int64)
            for code in range(BITS):
                if yz[code]:
                    n = ((left[y] >> code) & 1) * np.bitwise_count(left[z] & yz[code])
                    mass[y][code] += n.sum()
                    total += n
                if zy[code]:
                    mass[z][code] += (((left[z] >> code) & 1) * np.bitwise_count(left[y] & zy[code])).sum()
            for v, values in zip(vars, have):
                for code in np.unique(values).tolist():
                    mass[v][code] += total[values == code].sum()

        def extend(have: list[np.ndarray], left: dict[str, np.ndarray]) -> None:
            if len(left) == 2:
                return count(have, left)
            v = vars[len(have)]
            ends = np.cumsum(np.bitwise_count(left[v]), dtype=np.int64)
            lo = 0
            while lo < len(ends):
                hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + ROWS, "right")))
                at, code = np.nonzero((left[v][lo:hi, None] >> np.arange(BITS)) & 1)
                extend([*[x[lo:hi][at] for x in have], code.astype(np.int8)], {u: x[lo:hi][at] & agree[v, u][code] for u, x in left.items() if u != v})
                lo = hi

        for batch in batches:
            have = [batch.column(v).to_numpy().astype(np.int8) for v in first]
            if batch.num_rows:
                extend(have, {u: functools.reduce(np.bitwise_and, [agree[v, u][x] for v, x in zip(first, have)]) for u in vars[lead:]})
        found = [(v, str(c), n) for v in vars for c, n in enumerate(mass[v].tolist()) if n]
        yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in found], pa.string()), pa.array([r[1] for r in found], pa.string()), pa.array([r[2] for r in found], pa.int64())], names=["variable", "value", "mass"])

    dealt = rows.repartition(4 * int(spark.conf.get("spark.sql.shuffle.partitions")))
    return dealt.mapInArrow(solve, "variable string, value string, mass bigint").groupBy("variable", "value").agg(F.sum("mass").alias("mass"))
