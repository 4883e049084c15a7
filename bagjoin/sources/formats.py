"""Public text formats of graphical models: .uai and .fg.

Both hold whole truth tables or listings in one text; they are parsed and written on the driver and
meant for networks of the size that such files have.
"""

from __future__ import annotations

import itertools
import math

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..model import W, Factor, Network


def _network(spark: SparkSession, sizes: list[int], tables: list[tuple[list[int], list[tuple[tuple[int, ...], float]]]]) -> Network:
    factors = []
    for i, (scope, rows) in enumerate(tables):
        vars = [f"x{v}" for v in scope]
        schema = ", ".join([*(f"{v} long" for v in vars), f"{W} double"])
        factors.append(Factor(f"f{i}", tuple(vars), spark.createDataFrame([(*k, w) for k, w in rows if w > 0], schema)))
    seen = {v for s, _ in tables for v in s}
    for v in range(len(sizes)):
        if v not in seen:
            factors.append(Factor(f"uniform_x{v}", (f"x{v}",), spark.range(sizes[v]).select(F.col("id").alias(f"x{v}"), F.lit(1.0).alias(W))))
    return Network.of(factors, {f"x{v}": n for v, n in enumerate(sizes)})


#: These formats are read and written by the driver: largest file, and most entries of a factor.
MAX_BYTES, MAX_ENTRIES = 64 << 20, 1_000_000


def _text(spark: SparkSession, path: str) -> str:
    size = spark.read.format("binaryFile").load(path).agg(F.sum("length")).first()[0] or 0
    if size > MAX_BYTES:
        raise ValueError(f"{path} has {size} bytes; keep large factors as tables (Factor.read)")
    return "\n".join(r.value for r in spark.read.text(path, wholetext=True).collect())


def read_uai(spark: SparkSession, path: str) -> Network:
    """Markov or Bayes network: sizes, scopes, then tables with the last variable fastest."""
    words = _text(spark, path).split()
    if words[0] not in ("MARKOV", "BAYES"):
        raise ValueError(f"unknown preamble {words[0]!r}")
    it = iter(words[1:])
    n = int(next(it))
    sizes = [int(next(it)) for _ in range(n)]
    scopes = []
    for _ in range(int(next(it))):
        scopes.append([int(next(it)) for _ in range(int(next(it)))])
    tables = []
    for s in scopes:
        cells = int(next(it))
        if cells != math.prod(sizes[v] for v in s):
            raise ValueError("a table does not have one entry per cell")
        tables.append((s, list(zip(itertools.product(*(range(sizes[v]) for v in s)), (float(next(it)) for _ in range(cells))))))
    return _network(spark, sizes, tables)


def _coded(network: Network, most: int = MAX_ENTRIES) -> tuple[list[str], dict[str, dict]]:
    """Variables and the numbers of their values; refuses factors of more than ``most`` rows."""
    for f in network.factors:
        if f.df.limit(most + 1).count() > most:
            raise ValueError(f"{f.name} has over {most} rows; keep large factors as tables")
    vars = list(network.vars)
    codes = {}
    for v in vars:
        values = set()
        for g in network.factors:
            if v in g.vars:
                values |= {r[0] for r in g.df.select(v).distinct().collect()}
        codes[v] = {x: i for i, x in enumerate(sorted(values))}
    return vars, codes


def write_uai(network: Network, path: str, max_cells: int = MAX_ENTRIES) -> None:
    """Truth tables; refuses factors over ``max_cells``. Values are numbered in their order."""
    vars, codes = _coded(network)
    at = {v: i for i, v in enumerate(vars)}
    lines = ["MARKOV", str(len(vars)), " ".join(str(len(codes[v])) for v in vars), str(len(network.factors))]
    lines += [" ".join(map(str, [len(f.vars), *(at[v] for v in f.vars)])) for f in network.factors]
    for f in network.factors:
        cells = math.prod(len(codes[v]) for v in f.vars)
        if cells > max_cells:
            raise ValueError(f"{f.name} has {cells} cells")
        got = {tuple(codes[v][x] for v, x in zip(f.vars, r)): r[-1] for r in f.df.select(*f.vars, W).collect()}
        lines += ["", str(cells), " ".join(repr(float(got.get(k, 0.0))) for k in itertools.product(*(range(len(codes[v])) for v in f.vars)))]
    network.spark.createDataFrame([("\n".join(lines),)], "value string").coalesce(1).write.mode("overwrite").text(path)


def read_fg(spark: SparkSession, path: str) -> Network:
    """Factor graph listing: per factor its variables, sizes and non-zero entries, the first variable fastest."""
    lines = [x.split("#")[0].split() for x in _text(spark, path).splitlines()]
    words = iter([w for x in lines for w in x])
    sizes: dict[int, int] = {}
    tables = []
    for _ in range(int(next(words))):
        scope = [int(next(words)) for _ in range(int(next(words)))]
        dims = [int(next(words)) for _ in scope]
        sizes |= dict(zip(scope, dims))
        rows = []
        for _ in range(int(next(words))):
            i, w = int(next(words)), float(next(words))
            key = []
            for d in dims:
                i, c = divmod(i, d)
                key.append(c)
            rows.append((tuple(key), w))
        tables.append((scope, rows))
    return _network(spark, [sizes.get(v, 1) for v in range(max(sizes, default=-1) + 1)], tables)


def write_fg(network: Network, path: str, max_entries: int = MAX_ENTRIES) -> None:
    """Non-zero entries only, numbered by the reverse index; refuses factors of over ``max_entries`` rows."""
    vars, codes = _coded(network, max_entries)
    at = {v: i for i, v in enumerate(vars)}
    out = [str(len(network.factors)), ""]
    for f in network.factors:
        dims = [len(codes[v]) for v in f.vars]
        rows = []
        for r in f.df.select(*f.vars, W).collect():
            place, i = 1, 0
            for v, d, x in zip(f.vars, dims, r):
                i += codes[v][x] * place
                place *= d
            rows.append((i, float(r[-1])))
        out += [str(len(f.vars)), " ".join(str(at[v]) for v in f.vars), " ".join(map(str, dims)), str(len(rows)), *[f"{i} {w!r}" for i, w in sorted(rows)], ""]
    network.spark.createDataFrame([("\n".join(out),)], "value string").coalesce(1).write.mode("overwrite").text(path)
