"""Factors, domains and networks.

A factor is a DataFrame with one column per variable and a weight ``w``; rows that are absent have
weight zero, and variables are unique keys of a factor. A network is a tuple of factors: its
hypergraph lives on the driver, its rows never do.
"""

from __future__ import annotations

import functools
import operator
from collections.abc import Iterable
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .functions.cleanup import short_lived_shuffles
from .functions.semiring import SUM_PRODUCT, Semiring

W = "w"


class FactorError(ValueError):
    """A table is not a valid factor."""


class InconsistentEvidence(ValueError):
    """No assignment has a positive weight."""


@dataclass(frozen=True)
class Factor:
    """A weighted relation over ``vars``."""

    name: str
    vars: tuple[str, ...]
    df: DataFrame = field(repr=False, compare=False)

    @staticmethod
    def listing(name: str, df: DataFrame, vars: Iterable[str], weight: str | Column | None = None, null_policy: str = "reject", semiring: Semiring = SUM_PRODUCT) -> Factor:
        """Rows of ``df`` summed to one per tuple, zero weights left out (M1, M2).

        ``null_policy``: ``reject`` leaves null keys to ``check``, ``drop`` removes their rows,
        ``as_value`` turns them into the string ``unknown``.
        """
        vars = tuple(vars)
        w = F.lit(1).cast("bigint") if weight is None else (F.col(weight) if isinstance(weight, str) else weight)
        out = df.select(*vars, w.alias(W))
        if null_policy == "drop":
            out = out.dropna(subset=list(vars))
        elif null_policy == "as_value":
            out = out.select(*[F.coalesce(F.col(v).cast("string"), F.lit("unknown")).alias(v) for v in vars], W)
        out = out.groupBy(*vars).agg(semiring.plus(F.col(W)).alias(W))
        return Factor(name, vars, out.filter(semiring.keep(F.col(W))))

    @staticmethod
    def counts(name: str, df: DataFrame, vars: Iterable[str], by: str | None = None) -> Factor:
        """How often each tuple occurs (M1a); ``by``: in partitions of that variable's values, sorted by it."""
        vars = tuple(vars)
        if by:
            df = df.select(*vars).repartition(by)
            return Factor(name, vars, df.groupBy(*vars).agg(F.count(F.lit(1)).alias(W)).sortWithinPartitions(by))
        return Factor(name, vars, df.groupBy(*vars).agg(F.count(F.lit(1)).alias(W)))

    @staticmethod
    def conditional(name: str, df: DataFrame, child: str, parents: Iterable[str], smoothing: float = 0.0) -> Factor:
        """P(child | parents) from counts; ``smoothing`` is added to every observed-domain cell."""
        parents = tuple(parents)
        c = Factor.counts(name, df, (*parents, child)).df
        if smoothing:
            cells = c.select(*parents).distinct().crossJoin(c.select(child).distinct()) if parents else c.select(child)
            c = cells.join(c, [*parents, child], "left").withColumn(W, F.coalesce(F.col(W), F.lit(0)) + F.lit(smoothing))
        total = F.sum(W).over(Window.partitionBy(*parents)) if parents else F.sum(W).over(Window.partitionBy(F.lit(0)))
        return Factor(name, (*parents, child), c.withColumn(W, F.col(W) / total))

    @staticmethod
    def read(spark: SparkSession, name: str, path: str, vars: Iterable[str], fmt: str = "parquet", weight: str | None = None, **options) -> Factor:
        """A factor from any table that Spark reads."""
        return Factor.listing(name, spark.read.format(fmt).options(**options).load(path), vars, weight)

    # constraint networks and near values (O3g, O3h)
    @staticmethod
    def constraint(name: str, a: DataFrame, b: DataFrame, predicate: Column | str) -> Factor:
        """Pairs of two domains that satisfy a predicate, weight one."""
        p = F.expr(predicate) if isinstance(predicate, str) else predicate
        return Factor(name, (*a.columns, *b.columns), a.distinct().join(b.distinct(), p).withColumn(W, F.lit(1).cast("bigint")))

    @staticmethod
    def within(name: str, a: DataFrame, b: DataFrame, delta: int) -> Factor:
        """Pairs of integers that differ by at most ``delta``: an equi-join on bins and a residual check."""
        (x,), (y,) = a.columns, b.columns
        width = delta + 1
        left = a.distinct().withColumn("__bin", F.explode(F.array(*[F.floor(F.col(x) / width) + o for o in (-1, 0, 1)])))
        right = b.distinct().withColumn("__bin", F.floor(F.col(y) / width))
        out = left.join(right, "__bin").filter(F.abs(F.col(x) - F.col(y)) <= delta)
        return Factor(name, (x, y), out.select(x, y, F.lit(1).cast("bigint").alias(W)))

    # time-sliced networks (O3i, O3j)
    @staticmethod
    def transition(name: str, df: DataFrame, key: str, order: list[str], var: str, lag: int = 1, prev: str = "prev", nxt: str = "next") -> Factor:
        """Counts of (previous, next) states per key; the first row of a key has no previous one."""
        w = Window.partitionBy(key).orderBy(*order)
        pairs = df.select(F.lag(var, lag).over(w).alias(prev), F.col(var).alias(nxt)).filter(F.col(prev).isNotNull())
        return Factor.counts(name, pairs, (prev, nxt))

    @staticmethod
    def cooccur(name: str, df: DataFrame, key: str, ts: str, var: str, within: int, a: str = "a", b: str = "b") -> Factor:
        """Counts of ordered pairs of states of one key at most ``within`` seconds apart, earlier first.

        Rows meet by (key, tumbling bucket), so a key's history is never paired as a whole. Times are
        compared to the microsecond.
        """
        span = within * 1_000_000
        base = df.select(F.col(key).alias("k"), F.unix_micros(F.col(ts).cast("timestamp")).alias("t"), F.col(var).alias("v")).withColumn("bucket", F.expr(f"t div {span} - int(t % {span} < 0)"))
        left = base.select("k", F.col("t").alias("t1"), F.col("v").alias(a), F.explode(F.array("bucket", F.col("bucket") + 1)).alias("bucket"))
        right = base.select("k", F.col("t").alias("t2"), F.col("v").alias(b), "bucket")
        pairs = left.join(right, ["k", "bucket"]).filter((F.col("t2") > F.col("t1")) & (F.col("t2") - F.col("t1") <= span))
        return Factor.counts(name, pairs, (a, b))

    # relational helpers
    def rename(self, names: dict[str, str]) -> Factor:
        return Factor(self.name, tuple(names.get(v, v) for v in self.vars), self.df.select(*[F.col(v).alias(names.get(v, v)) for v in self.vars], W))

    def named(self, name: str) -> Factor:
        return replace(self, name=name)

    def where(self, var: str, value) -> Factor:
        """Hard evidence: keep the rows of one value and drop the variable."""
        rest = tuple(v for v in self.vars if v != var)
        return Factor(self.name, rest, self.df.filter(F.col(var) == F.lit(value)).select(*rest, W))

    def where_in(self, var: str, values: list) -> Factor:
        return replace(self, df=self.df.filter(F.col(var).isin(values)))

    def where_between(self, var: str, low, high) -> Factor:
        return replace(self, df=self.df.filter(F.col(var).between(low, high)))

    def nonzero(self) -> Factor:
        return replace(self, df=self.df.filter(F.col(W) > 0))

    def onto(self, vars: Iterable[str], semiring: Semiring = SUM_PRODUCT) -> Factor:
        """Sum every other variable out (O4a, O4c): partial aggregation, then one shuffle."""
        vars = tuple(vars)
        if set(vars) == set(self.vars):
            return Factor(self.name, vars, self.df.select(*vars, W))
        return Factor(self.name, vars, self.df.groupBy(*vars).agg(semiring.plus(F.col(W)).alias(W)))

    def sum_out(self, vars: Iterable[str], semiring: Semiring = SUM_PRODUCT) -> Factor:
        gone = set(vars)
        return self.onto([v for v in self.vars if v not in gone], semiring)

    def support(self, vars: Iterable[str] | None = None) -> DataFrame:
        """Distinct tuples (O4d)."""
        vars = tuple(vars or self.vars)
        out = self.df.select(*vars)
        return out if set(vars) == set(self.vars) else out.distinct()

    def count_support(self, vars: Iterable[str], approximate: bool = False) -> int:
        vars = list(vars)
        if approximate:
            return self.df.agg(F.approx_count_distinct(F.struct(*vars))).first()[0]
        return self.support(vars).count()

    def size(self) -> int:
        return self.df.count()

    def sparsity(self, domains: dict[str, int]) -> float:
        """Rows over cells (M2)."""
        return self.size() / functools.reduce(operator.mul, (domains[v] for v in self.vars), 1)

    def check(self) -> Factor:
        """Raise FactorError on null keys, negative or null weights, or repeated tuples (M1)."""
        bad = functools.reduce(operator.or_, [F.col(v).isNull() for v in self.vars], F.col(W).isNull() | (F.col(W) < 0))
        n, wrong = self.df.agg(F.count(F.lit(1)), F.sum(bad.cast("int"))).first()
        if wrong:
            raise FactorError(f"{self.name}: {wrong} rows with a null or a negative weight")
        if self.vars and self.support(self.vars).distinct().count() != n:
            raise FactorError(f"{self.name}: repeated tuples")
        return self

    def induce_sparsity(self, keep: float, seed: int = 0, domains: dict[str, list] | None = None) -> Factor:
        """About ``keep`` percent of the rows by a portable hash of integer codes, and all diagonal tuples.

        Diagonal rows (i, ..., i), i below the least domain size, are added with weight one where absent.
        """
        from .functions.discretise import portable_hash

        n = min((len(domains[v]) for v in self.vars), default=0) if domains else None
        hit = F.pmod(portable_hash(list(self.vars), seed), F.lit(1000)) < F.lit(int(round(keep * 10)))
        same = functools.reduce(operator.and_, [F.col(v) == F.col(self.vars[0]) for v in self.vars])
        if n is not None:
            same = same & (F.col(self.vars[0]) < n)
        kept = self.df.filter(hit | same)
        if n:
            kind = dict(self.df.dtypes)
            diag = self.df.sparkSession.range(n).select(*[F.col("id").cast(kind[v]).alias(v) for v in self.vars], F.lit(1).cast(kind[W]).alias(W))
            kept = kept.unionByName(diag.join(self.df, list(self.vars), "left_anti"))
        return replace(self, df=kept)

    def to_dense(self, domains: dict[str, DataFrame]) -> DataFrame:
        """Truth table with zeros (O3f); only after a check of its number of cells."""
        cells = functools.reduce(lambda x, y: x.crossJoin(y), [domains[v].select(v) for v in self.vars])
        return cells.join(self.df, list(self.vars), "left").withColumn(W, F.coalesce(F.col(W), F.lit(0)))


@dataclass(frozen=True)
class Domain:
    """Values of a variable with dense codes 0..n-1 in value order."""

    var: str
    df: DataFrame = field(repr=False, compare=False)

    @staticmethod
    def fit(df: DataFrame, col: str, max_values: int = 1_000_000) -> Domain:
        """Codes by value order; for domains that fit one sort task (checked), as codes are only for indices."""
        values = df.select(F.col(col).alias("value")).distinct()
        if values.limit(max_values + 1).count() > max_values:
            raise FactorError(f"{col} has more than {max_values} values; keep it as a key without codes")
        codes = values.select((F.row_number().over(Window.orderBy("value")) - 1).cast("bigint").alias("code"), "value")
        return Domain(col, codes)

    def size(self) -> int:
        return self.df.count()

    def encode(self, df: DataFrame, col: str | None = None) -> DataFrame:
        col = col or self.var
        return df.join(self.df.select(F.col("value").alias(col), F.col("code").alias("__code")), col).withColumn(col, F.col("__code")).drop("__code")

    def decode(self, df: DataFrame, col: str | None = None) -> DataFrame:
        col = col or self.var
        return df.join(self.df.select(F.col("code").alias(col), F.col("value").alias("__value")), col).withColumn(col, F.col("__value")).drop("__value")


@dataclass(frozen=True)
class Network:
    """Factors over shared variables; ``domains`` gives the number of values of each variable."""

    factors: tuple[Factor, ...]
    domains: dict[str, int]
    sizes: dict[str, int]
    scale: float = 1  # weight of factors that evidence has bound completely

    @staticmethod
    def of(factors: Iterable[Factor], domains: dict[str, int] | None = None, sizes: dict[str, int] | None = None, uncovered: dict[str, DataFrame] | None = None, scale: float = 1) -> Network:
        """Count rows and values in one job unless they are given; names must differ.

        ``uncovered`` has the domain of variables in no factor: each gets a uniform factor.
        """
        factors = list(factors)
        for v, d in (uncovered or {}).items():
            factors.append(Factor(f"uniform_{v}", (v,), d.select(v).distinct().withColumn(W, F.lit(1).cast("bigint"))))
        if len({f.name for f in factors}) != len(factors):
            raise FactorError("factor names must differ")
        if domains is None or sizes is None:
            parts = []
            for f in factors:
                parts.append(f.df.select(F.lit("f").alias("kind"), F.lit(f.name).alias("name"), F.count(F.lit(1)).alias("n")))
            by_var: dict[str, list[Factor]] = {}
            for f in factors:
                for v in f.vars:
                    by_var.setdefault(v, []).append(f)
            for v, fs in by_var.items():
                if domains is None or v not in domains:
                    values = functools.reduce(lambda x, y: x.union(y), [f.df.select(F.col(v).cast("string").alias("x")) for f in fs])
                    parts.append(values.select(F.lit("v").alias("kind"), F.lit(v).alias("name"), F.countDistinct("x").alias("n")))
            with short_lived_shuffles(factors[0].df.sparkSession):
                rows = functools.reduce(lambda x, y: x.union(y), parts).collect()  # one number per factor and variable
            sizes = {r.name: r.n for r in rows if r.kind == "f"} | (sizes or {})
            domains = {r.name: r.n for r in rows if r.kind == "v"} | (domains or {})
        return Network(tuple(factors), dict(domains), dict(sizes), scale)

    @property
    def vars(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(v for f in self.factors for v in f.vars))

    def factor(self, name: str) -> Factor:
        return next(f for f in self.factors if f.name == name)

    @property
    def spark(self) -> SparkSession:
        return self.factors[0].df.sparkSession

    def with_unary(self, var: str, weights: dict) -> Network:
        """Soft evidence: one more unary factor."""
        df = self.spark.createDataFrame([(k, float(x)) for k, x in weights.items()], f"{var} {dict(next(f for f in self.factors if var in f.vars).df.dtypes)[var]}, {W} double")
        f = Factor(f"soft_{var}", (var,), df)
        return Network((*self.factors, f), self.domains, self.sizes | {f.name: len(weights)}, self.scale)

    def replaced(self, factors: Iterable[Factor]) -> Network:
        """The same structure with some factors renewed (their sizes are counted again)."""
        new = {f.name: f for f in factors}
        return Network.of([new.get(f.name, f) for f in self.factors], self.domains, {k: v for k, v in self.sizes.items() if k not in new} | {k: f.size() for k, f in new.items()}, scale=self.scale)

    def factor_graph(self) -> DataFrame:
        """Bipartite view (factor, var, pos)."""
        return self.spark.createDataFrame([(f.name, v, i) for f in self.factors for i, v in enumerate(f.vars)], "factor string, var string, pos int")

    def nodes(self) -> DataFrame:
        return self.spark.createDataFrame([(v, self.domains[v]) for v in self.vars], "var string, domain_size long")

    def profile_rows(self) -> list[tuple]:
        out = []
        for f in self.factors:
            cells = functools.reduce(operator.mul, (self.domains[v] for v in f.vars), 1)
            out.append((f.name, len(f.vars), self.sizes[f.name], float(cells), self.sizes[f.name] / cells))
        return out

    def factor_profile(self) -> DataFrame:
        """(factor, arity, n_rows, domain_cells, sparsity) (M2, C11)."""
        return self.spark.createDataFrame(self.profile_rows(), "factor string, arity int, n_rows long, domain_cells double, sparsity double")

    def sparsity_summary(self) -> DataFrame:
        """Median, mean and largest sparsity (O4f)."""
        return self.factor_profile().agg(F.percentile("sparsity", 0.5).alias("median_sparsity"), F.avg("sparsity").alias("mean_sparsity"), F.max("sparsity").alias("max_sparsity"))
