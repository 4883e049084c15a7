"""Two-pass calibration over a junction tree, and marginals."""

from __future__ import annotations

import math
from collections.abc import Iterable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.semiring import SUM_PRODUCT, Semiring
from ..model import W, Factor, InconsistentEvidence, Network
from ..plans import strategy as st
from ..plans.decomposition import Decomposition, decompose
from .preprocess import apply_evidence
from .product import bag_product
from .projections import ProjectionCache, ProjectionPolicy, apply_indicators, indicators_for
from .relational import hash_product, materialise, multiply, sort_merge_product


@dataclass(frozen=True)
class InferConfig:
    """Options of a run; the defaults suit a cluster, tests use ``materialise='lazy'``."""

    policy: ProjectionPolicy = ProjectionPolicy()
    indicator_mode: str = "input"  # or semijoin
    impl: str = "auto"  # extend, grid
    order: str = "input"  # free_first, min_domain
    calibration: str = "product"  # or quotient: divides the down message by the up message
    down: str = "hash"  # or merge: how the down message meets the child
    layout: str = "columns"  # or forward_list: messages as forward-index lists (M10c)
    materialise: str = "parquet"
    scaled: bool = False  # divide every message by its maximum and carry the logarithm
    semiring: Semiring = SUM_PRODUCT
    rho_limit: float = 1e9
    seed: int = 0
    strategy_mode: str = "cost"


@dataclass
class Calibrated:
    """Bag products whose weights are marginal masses of their bags."""

    dec: Decomposition
    products: dict[int, Factor]
    up: dict[int, Factor]
    choices: dict[int, st.Choice]
    config: InferConfig
    log_scale: float = 0.0
    constants: float = 1
    raw: dict[int, Factor] = field(default_factory=dict)

    def partition_function(self) -> DataFrame:
        """(z) of the whole network: the product over its trees, times bound factors."""
        out = None
        for r in self.dec.roots:
            z = self.products[r].df.agg(self.config.semiring.plus(F.col(W)).alias("z"))
            out = z if out is None else out.crossJoin(z.withColumnRenamed("z", "__z")).select((F.col("z") * F.col("__z")).alias("z"))
        if self.constants != 1:
            out = out.select((F.col("z") * F.lit(self.constants)).alias("z"))
        return out

    def log_z(self) -> float:
        z = self.partition_function().first().z
        if not z:
            raise InconsistentEvidence("no assignment has a positive weight")
        return math.log(z) + self.log_scale

    def _tree_of(self, bag: int) -> int:
        while self.dec.parent[bag] >= 0:
            bag = self.dec.parent[bag]
        return bag

    def marginal(self, vars: Iterable[str]) -> DataFrame:
        """(vars..., mass) from the smallest bag that holds them; mass is that of the bag's tree."""
        vars = tuple(vars)
        b = self.dec.bag_of(vars)
        if b is None:
            raise ValueError(f"no bag holds {vars}; pass them as an extra scope")
        out = self.products[b].onto(vars, self.config.semiring).df.withColumnRenamed(W, "mass")
        for r in self.dec.roots:  # other trees multiply in, so that masses sum to Z
            if r != self._tree_of(b):
                z = self.products[r].df.agg(self.config.semiring.plus(F.col(W)).alias("__z"))
                out = out.crossJoin(z).withColumn("mass", F.col("mass") * F.col("__z")).drop("__z")
        return out.withColumn("mass", F.col("mass") * F.lit(self.constants)) if self.constants != 1 else out

    def variable_marginals(self, vars: Iterable[str] | None = None, probs: bool = True) -> DataFrame:
        """(variable, value, mass, prob) of all variables (M5a): grouping sets per bag, one pass each."""
        want: dict[int, list[str]] = {}
        for v in vars or sorted({v for c in self.dec.chi for v in c}):
            want.setdefault(self.dec.bag_of([v]), []).append(v)
        parts = None
        for b, vs in want.items():
            f = self.products[b].onto(vs, self.config.semiring)
            if len(vs) == 1:
                part = f.df.select(F.lit(vs[0]).alias("variable"), F.col(vs[0]).cast("string").alias("value"), F.col(W).alias("mass"))
            else:
                sets = f.df.groupingSets([[F.col(v)] for v in vs], *vs).agg(F.grouping_id().alias("g"), self.config.semiring.plus(F.col(W)).alias("mass"))
                which, value = F.lit(vs[0]), F.col(vs[0]).cast("string")
                full = (1 << len(vs)) - 1
                for i, v in enumerate(vs):
                    at = F.col("g") == F.lit(full ^ (1 << (len(vs) - 1 - i)))
                    which, value = F.when(at, v).otherwise(which), F.when(at, F.col(v).cast("string")).otherwise(value)
                part = sets.select(which.alias("variable"), value.alias("value"), "mass")
            for r in self.dec.roots:
                if r != self._tree_of(b):
                    z = self.products[r].df.agg(self.config.semiring.plus(F.col(W)).alias("__z"))
                    part = part.crossJoin(z).withColumn("mass", F.col("mass") * F.col("__z")).drop("__z")
            parts = part if parts is None else parts.unionByName(part)
        if self.constants != 1:
            parts = parts.withColumn("mass", F.col("mass") * F.lit(self.constants))
        if not probs:
            return parts
        z = parts.groupBy("variable").agg(F.sum("mass").alias("__z"))
        return parts.join(z, "variable").withColumn("prob", F.col("mass") / F.col("__z")).drop("__z")

    def factor_marginals(self) -> dict[str, DataFrame]:
        """(vars..., mass) per factor, from its bag."""
        return {n: self.marginal(self.dec.network.factor(n).vars) for names in self.dec.alpha for n in names if self.dec.network.factor(n).vars}

    def explain_bags(self) -> DataFrame:
        """(bag, vars, strategy, rows, agm, cells): observed product sizes beside the predictions."""
        from ..plans.measures import agm

        base = self.raw or self.products
        rows = []
        for b in range(len(self.dec.chi)):
            bound = agm(self.dec, b)
            rows.append((b, ",".join(self.dec.chi[b]), self.choices[b].strategy, base[b].df.count(), float(2**bound) if bound < 1000 else math.inf, float(self.dec.cells(b))))
        return self.dec.network.spark.createDataFrame(rows, "bag int, vars string, strategy int, rows long, agm double, cells double")


def _scaled(f: Factor, config: InferConfig) -> tuple[Factor, float]:
    if not config.scaled:
        return f, 0.0
    top = f.df.agg(F.max(W)).first()[0]
    if not top:
        raise InconsistentEvidence("a message is empty")
    return Factor(f.name, f.vars, f.df.withColumn(W, F.col(W) / F.lit(float(top)))), math.log(top)


def _listed(f: Factor, dec: Decomposition, config: InferConfig, encoders: dict) -> Factor:
    """A message through the older layout: one forward index and its weight, decoded at each use."""
    if config.layout != "forward_list" or not f.vars:
        return f
    from ..functions.index import decode_index, forward_index

    sizes = [encoders[v].size() for v in f.vars]
    df = f.df
    for v in f.vars:
        df = encoders[v].encode(df, v)
    df = df.select(forward_index(list(f.vars), sizes).alias("fwd"), W)
    df = df.select(*[c.alias(v) for c, v in zip(decode_index("fwd", sizes), f.vars)], W)
    for v in f.vars:
        df = encoders[v].decode(df, v)
    return Factor(f.name, f.vars, df.select(*f.vars, W))


def message_up(dec: Decomposition, choices: dict[int, st.Choice], config: InferConfig = InferConfig(), cache: ProjectionCache | None = None, encoders: dict | None = None) -> tuple[dict[int, Factor], dict[int, Factor], float]:
    """Leaves to root (M10): every bag's product, its sum to the parent, and the log of the scales taken out."""
    by = {f.name: f for f in dec.network.factors}
    cache = cache or ProjectionCache(dec.network, config.materialise)
    products: dict[int, Factor] = {}
    up: dict[int, Factor] = {}
    below: dict[int, set[str]] = {}
    scale = 0.0
    for level in reversed(dec.levels):
        for b in level:
            kids = dec.children[b]
            inputs = [by[n] for n in dec.alpha[b]] + [up[k] for k in kids]
            below[b] = set(dec.alpha[b]).union(*[below[k] for k in kids]) if kids else set(dec.alpha[b])
            covered = {v for f in inputs for v in f.vars}
            for v in dec.chi[b]:
                if v not in covered:  # only a neighbour holds it: its values come in with weight one
                    f = next(f for f in dec.network.factors if v in f.vars)
                    inputs.append(cache.get(f.name, (v,)))
            extra = []
            if choices[b].strategy == st.PROJECTED:
                extra = indicators_for(dec, b, cache, config.policy, below[b])
                inputs, extra = apply_indicators(inputs, extra, config.indicator_mode)
            sep = dec.separator(b) if dec.parent[b] >= 0 else ()
            free = sep if config.materialise == "lazy" else ()  # a product that is written is read for its sum
            product, total = bag_product(dec.chi[b], inputs, free, choices[b].strategy, extra, config.impl, config.order, dec.network.domains, config.semiring)
            products[b] = Factor(f"bag{b}", product.vars, materialise(product.df, config.materialise))
            if dec.parent[b] >= 0:
                m = products[b].onto(sep, config.semiring) if total is None else total
                m, s = _scaled(_listed(m, dec, config, encoders or {}), config)
                scale += s
                up[b] = Factor(f"up{b}", m.vars, materialise(m.df, config.materialise))
    return products, up, scale


def message_down(dec: Decomposition, products: dict[int, Factor], up: dict[int, Factor], config: InferConfig = InferConfig()) -> tuple[dict[int, Factor], float]:
    """Root to leaves (M11), each child once.

    ``quotient``: the parent's sum on the separator, divided by what the child sent, multiplies the
    child. What the child sent is a factor of that sum, so integers divide without a remainder and stay
    integers. ``product``: the parent's sum without the child's message, so integers stay exact and
    semirings without division work (M11e). Both scale alike.
    """
    out = dict(products)
    product_of = hash_product if config.down == "hash" else sort_merge_product
    if config.calibration == "quotient":
        if config.semiring.divide is None:
            raise ValueError(f"{config.semiring.name} has no division; use calibration='product'")
        for level in dec.levels[1:]:
            for b in level:
                sep = dec.separator(b)
                down = out[dec.parent[b]].onto(sep, config.semiring)
                exact = config.semiring.whole and all(dict(f.df.dtypes)[W] in ("bigint", "int", "smallint", "tinyint") for f in (down, up[b]))
                share = hash_product(down, up[b], "whole" if exact else "div", semiring=config.semiring)
                f = product_of(out[b], share, semiring=config.semiring)
                out[b] = Factor(f.name, f.vars, materialise(f.df, config.materialise))
        return out, 0.0
    down: dict[int, Factor] = {}
    by = {f.name: f for f in dec.network.factors}
    for level in dec.levels:
        for b in level:
            if b in down:
                f = product_of(products[b], down[b], semiring=config.semiring)
                out[b] = Factor(f.name, f.vars, materialise(f.df, config.materialise))
            kids = dec.children[b]
            if not kids:
                continue
            seen = products[b].support()  # the bag's own rows keep the search small and cover every variable
            acc = Factor("down", products[b].vars, seen.withColumn(W, F.lit(config.semiring.one).cast(dict(products[b].df.dtypes)[W])))
            for f in [by[n] for n in dec.alpha[b]] + ([down[b]] if b in down else []):
                acc = multiply(acc, f, semiring=config.semiring)
            rows = acc.df
            if len(kids) > 1:  # every child's message meets the rows once, as a column that this child's sum leaves out
                for i, k in enumerate(kids):
                    got = up[k].df.withColumnRenamed(W, f"__m{i}")
                    rows = rows.join(got, list(up[k].vars)) if up[k].vars else rows.crossJoin(got)
                rows = materialise(rows, config.materialise)
            for i, k in enumerate(kids):
                weight = F.col(W)
                for j in range(len(kids)):
                    weight = weight if j == i else config.semiring.times(weight, F.col(f"__m{j}"))
                m = Factor("down", products[b].vars, rows.select(*products[b].vars, weight.alias(W))).onto(dec.separator(k), config.semiring)
                down[k] = Factor(f"down{k}", m.vars, materialise(m.df, config.materialise))
    return out, 0.0


def infer(network: Network, strategy: str | dict[int, int] = "hybrid", evidence: dict | None = None, config: InferConfig = InferConfig(), extra: Iterable[Iterable[str]] = (), dec: Decomposition | None = None) -> Calibrated:
    """The whole engine (M12): preprocess, decompose, choose, up, down.

    ``strategy``: hybrid, multiway, multiway_proj, pairwise, or a map of bags. ``extra`` scopes get a
    bag of their own if none holds them (M5).
    """
    if evidence:
        network = apply_evidence(network, evidence)
    constants = network.scale
    bound = [f for f in network.factors if not f.vars]
    for f in bound:
        w = f.df.agg(F.sum(W)).first()[0]
        if not w:
            raise InconsistentEvidence(f"{f.name} excludes the evidence")
        constants *= w
    network = Network(tuple(f for f in network.factors if f.vars), network.domains, network.sizes, constants)
    dec = dec or decompose(network, extra=extra)
    if isinstance(strategy, dict):
        choices = {b: st.Choice(strategy[b], "given") for b in range(len(dec.chi))}
    elif strategy == "hybrid":
        choices = st.choose_strategies(dec, config.strategy_mode, config.rho_limit, config.seed)
    else:
        choices = st.fixed(dec, {n: s for s, n in st.NAMES.items()}[strategy])
    encoders = None
    if config.layout == "forward_list":
        from ..model import Domain

        first = {v: f for f in reversed(network.factors) for v in f.vars}
        encoders = {v: Domain.fit(f.df, v) for v, f in first.items()}
    products, up, scale = message_up(dec, choices, config, encoders=encoders)
    out, _ = message_down(dec, products, up, config)
    return Calibrated(dec, out, up, choices, config, scale, constants, products)


def marginal(network: Network, vars: Iterable[str], evidence: dict | None = None, strategy: str = "hybrid", config: InferConfig = InferConfig()) -> DataFrame:
    """(vars..., mass, prob) of any set of variables (M5)."""
    vars = tuple(vars)
    cal = infer(network, strategy, evidence, config, extra=[vars])
    m = cal.marginal(vars)
    return m.crossJoin(m.agg(F.sum("mass").alias("__z"))).withColumn("prob", F.col("mass") / F.col("__z")).drop("__z")


def compare_marginals(a: DataFrame, b: DataFrame, tol: float = 1e-5) -> tuple[float, bool]:
    """Largest difference of probabilities; a value that is missing on one side counts as zero."""
    x = a.select("variable", "value", F.col("prob").alias("p"))
    y = b.select("variable", "value", F.col("prob").alias("q"))
    worst = x.join(y, ["variable", "value"], "full").agg(F.max(F.abs(F.coalesce("p", F.lit(0.0)) - F.coalesce("q", F.lit(0.0))))).first()[0] or 0.0
    return worst, worst <= tol
