"""Binary grids of embedding signs, with full and thinned edges and one wide factor."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..functions.discretise import sign_bit
from ..model import Factor, Network
from ..sources.tables import table


def edge_list(rows: int, cols: int) -> list[tuple[tuple[int, int], tuple[int, int]]]:
    out = []
    for r in range(rows):
        for c in range(cols):
            if c + 1 < cols:
                out.append(((r, c), (r, c + 1)))
            if r + 1 < rows:
                out.append(((r, c), (r + 1, c)))
    return out


def network(spark: SparkSession, sf_dir: str, rows: int, cols: int, full_every: int = 16, wide_factor: bool = False) -> tuple[Network, dict[str, str]]:
    """(network, templates). Cell (r, c) reads dimension (cols * r + c) mod 64. Every ``full_every``-th
    edge keeps the whole co-occurrence table, the others only equal signs. Edges of the same two
    dimensions and kind share one table."""
    e = table(spark, sf_dir, "embeddings", "embedding")
    var = lambda p: f"v{p[0]:02d}_{p[1]:02d}"
    dim = lambda p: (cols * p[0] + p[1]) % 64
    factors, templates, sizes, first = [], {}, {}, {}
    for n, (a, b) in enumerate(edge_list(rows, cols)):
        full = full_every > 0 and n % full_every == 0
        x, y = dim(a), dim(b)
        key = (x, y, full)
        name = f"e{n:04d}"
        if key not in first:
            f = Factor.counts(name, e.select(sign_bit(F.element_at("embedding", x + 1)).alias(var(a)), sign_bit(F.element_at("embedding", y + 1)).alias(var(b))), (var(a), var(b)))
            if not full:
                f = Factor(name, f.vars, f.df.filter(F.col(var(a)) == F.col(var(b))))
            first[key] = f
        else:
            f = Factor(name, (var(a), var(b)), first[key].rename(dict(zip(first[key].vars, (var(a), var(b))))).df)
        factors.append(f)
        templates[name], sizes[name] = first[key].name, 4 if full else 2
    if wide_factor:
        cells = [(0, 0), (0, 1), (1, 0), (1, 1)]
        four = e.select(*[sign_bit(F.element_at("embedding", d)).alias(var(p)) for p, d in zip(cells, (1, 2, 6, 12))])
        factors.append(Factor.counts("wide", four, tuple(map(var, cells))))
        sizes["wide"] = 16
    domains = {var((r, c)): 2 for r in range(rows) for c in range(cols)}
    return Network(tuple(factors), domains, sizes), templates


def small(spark: SparkSession, sf_dir: str, rows: int = 3, cols: int = 3) -> Network:
    return network(spark, sf_dir, rows, cols, full_every=1)[0]


def metadata(rows: int, cols: int, full_every: int = 16, wide_factor: bool = False) -> Network:
    """The same hypergraph and sizes without tables, for the measures."""
    var = lambda p: f"v{p[0]:02d}_{p[1]:02d}"
    edges = edge_list(rows, cols)
    factors = [Factor(f"e{n:04d}", (var(a), var(b)), None) for n, (a, b) in enumerate(edges)]
    sizes = {f.name: 4 if full_every > 0 and n % full_every == 0 else 2 for n, f in enumerate(factors)}
    if wide_factor:
        factors.append(Factor("wide", tuple(map(var, [(0, 0), (0, 1), (1, 0), (1, 1)])), None))
        sizes["wide"] = 16
    return Network(tuple(factors), {var((r, c)): 2 for r in range(rows) for c in range(cols)}, sizes)


def tables(rows: int, cols: int, full_every: int = 16, wide_factor: bool = False) -> dict[str, tuple[tuple[int, ...], bool]]:
    """Per factor the dimensions it reads, and whether it keeps the whole co-occurrence table."""
    dim = lambda p: (cols * p[0] + p[1]) % 64
    out = {f"e{n:04d}": ((dim(a), dim(b)), full_every > 0 and n % full_every == 0) for n, (a, b) in enumerate(edge_list(rows, cols))}
    return out | ({"wide": ((0, 1, 5, 11), True)} if wide_factor else {})


def measured_sizes(spark: SparkSession, sf_dir: str, rows: int, cols: int, full_every: int = 16, wide_factor: bool = False) -> dict[str, int]:
    """Rows of every factor on the embeddings, all counted in one pass: a bit for each combination of signs."""
    found = tables(rows, cols, full_every, wide_factor)
    keys = list(dict.fromkeys(found.values()))
    e = table(spark, sf_dir, "embeddings", "embedding")
    counts = []
    for i, (dims, full) in enumerate(keys):
        signs = [sign_bit(F.element_at("embedding", d + 1)).cast("int") for d in dims]
        code = sum((s * 2**k for k, s in enumerate(signs)), F.lit(0))
        if not full:
            code = F.when(signs[0] == signs[1], code)
        counts.append(F.coalesce(F.bit_count(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("bigint"), code))), F.lit(0)).alias(f"n{i}"))
    got = e.agg(*counts).first()
    return {name: got[keys.index(key)] for name, key in found.items()}
