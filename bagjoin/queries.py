"""Registered queries: one per method, variant, baseline, measure and workload, with SQL twins."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .baselines.brute import brute_force
from .baselines.circuit import compile_circuit
from .baselines.dense import dense_junction_tree, domains_of
from .baselines.join_graph import join_graph_propagation
from .functions import discretise, index
from .functions.semiring import BOOLEAN, MAX_PRODUCT
from .model import W, Domain, Factor, Network
from .networks import clique, events, grid, star, supply, text, toy
from .operators import masks
from .operators import relational as rel
from .operators.batch import run_level, solve_trees
from .operators.infer import InferConfig, infer, marginal, message_up
from .operators.preprocess import apply_evidence, singleton_consistency
from .operators.product import extend_product, multiway_product, pairwise_product, split_triangle
from .operators.projections import ALL_PROJECTIONS, ProjectionCache, indicator, projection_report
from .operators.trie import level_order_trie
from .plans import measures
from .plans import strategy as st
from .plans.decomposition import decompose
from .sources.tables import table
from .streaming import factors as stream

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
ALL = ALL_PROJECTIONS
INT = InferConfig(policy=ALL)


def query(sql: str | None = None, name: str | None = None):
    """Register a query under its function's name, with its SQL."""

    def put(f):
        QUERIES[name or f.__name__] = f
        if sql:
            SQL[name or f.__name__] = sql
        return f

    return put


# shared SQL
_CP = "cp AS (SELECT o_custkey, l_partkey, count(*) AS w FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL)"
_CS = "cs AS (SELECT o_custkey, l_suppkey, count(*) AS w FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL)"
_PS = "ps AS (SELECT l_partkey, l_suppkey, count(*) AS w FROM lineitem GROUP BY ALL)"
_PSF = "psf AS (SELECT l_partkey, l_suppkey, l_returnflag, count(*) AS w FROM lineitem GROUP BY ALL)"
_LOOK = f"WITH {_CP}, {_CS}, {_PSF}, bag AS (SELECT o_custkey, l_partkey, l_suppkey, cp.w * cs.w AS w FROM cp JOIN cs USING (o_custkey)), j AS (SELECT o_custkey, l_partkey, l_suppkey, l_returnflag, bag.w * psf.w AS w FROM bag JOIN psf USING (l_partkey, l_suppkey))"
_TOY = """WITH ab AS (SELECT c_mktsegment, c_nationkey, count(*) AS w FROM customer GROUP BY ALL),
ac AS (SELECT c_mktsegment, o_orderpriority, count(*) AS w FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ALL),
bcd AS (SELECT c_nationkey, o_orderpriority, o_orderstatus, count(*) AS w FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ALL),
j AS (SELECT c_mktsegment, c_nationkey, o_orderpriority, o_orderstatus, ab.w * ac.w * bcd.w AS w FROM ab JOIN ac USING (c_mktsegment) JOIN bcd USING (c_nationkey, o_orderpriority)),
z AS (SELECT sum(w) AS z FROM j)"""


def _union(vars: list[str], source: str = "j", prob: bool = True, mass: bool = True) -> str:
    cols = (", sum(w)::BIGINT AS mass" if mass else "") + (f", round(sum(w) / (SELECT sum(w) FROM {source}), 9) AS prob" if prob else "")
    return " UNION ALL ".join(f"SELECT '{v}' AS variable, {v}::VARCHAR AS value{cols} FROM {source} GROUP BY {v}" for v in vars)


_TOY_VARS = ["c_mktsegment", "c_nationkey", "o_orderpriority", "o_orderstatus"]
_LOOK_VARS = ["o_custkey", "l_partkey", "l_suppkey", "l_returnflag"]


def _probs(df: DataFrame, digits: int = 9) -> DataFrame:
    return df.select("variable", "value", F.round("prob", digits).alias("prob"))


def _masses(df: DataFrame) -> DataFrame:
    return df.select("variable", "value", F.col("mass").cast("bigint").alias("mass"))


# triangle and hub (M7, M8; W1, W1s)
_TRI = f"WITH {_CP}, {_CS}, {_PS} SELECT o_custkey, l_partkey, l_suppkey, cp.w * ps.w * cs.w AS mass FROM cp JOIN ps USING (l_partkey) JOIN cs USING (o_custkey, l_suppkey)"
_TRI_VARS = ("o_custkey", "l_partkey", "l_suppkey")


def _triangle(how: str):
    def run(spark, sf_dir):
        n = supply.triangle(spark, sf_dir)
        fs = [Factor(f.name, f.vars, rel.materialise(f.df)) for f in n.factors]
        f = pairwise_product(_TRI_VARS, fs, "greedy") if how == "pairwise" else multiway_product(_TRI_VARS, fs, impl=how)
        return f.df.select(*_TRI_VARS, F.col(W).alias("mass"))

    return run


for _how in ("extend", "grid", "pairwise"):
    query(_TRI, "triangle_pairwise" if _how == "pairwise" else f"triangle_multiway_{_how}")(_triangle(_how))

_HUB = "WITH h AS (SELECT p_partkey AS x, 0 AS y FROM part UNION SELECT 0, p_partkey FROM part) SELECT h1.x AS a, h1.y AS b, h2.y AS c, 1 AS mass FROM h h1 JOIN h h2 ON h1.y = h2.x JOIN h h3 ON h2.y = h3.x AND h3.y = h1.x"


@query(_HUB)
def hub_triangle_multiway(spark, sf_dir):
    n = supply.hub(spark, sf_dir)
    return extend_product(("a", "b", "c"), list(n.factors)).df.select("a", "b", "c", F.col(W).alias("mass"))


@query(_HUB)
def hub_triangle_grid(spark, sf_dir):
    n = supply.hub(spark, sf_dir)
    return multiway_product(("a", "b", "c"), list(n.factors), impl="grid").df.select("a", "b", "c", F.col(W).alias("mass"))


@query(_HUB)
def hub_triangle_pairwise(spark, sf_dir):
    """Pairwise joins; the hub, whose value would make quadratically many rows, goes apart."""
    n = supply.hub(spark, sf_dir)
    return split_triangle(("a", "b", "c"), list(n.factors)).df.select("a", "b", "c", F.col(W).alias("mass"))


# look-ahead network (M9-M12; W2)
@query(f"{_LOOK} SELECT 'plain' AS variant, count(*) AS n_rows FROM bag UNION ALL SELECT 'projected', count(*) FROM bag WHERE EXISTS (SELECT 1 FROM psf WHERE psf.l_partkey = bag.l_partkey AND psf.l_suppkey = bag.l_suppkey)")
def lookahead_bag_sizes(spark, sf_dir):
    n = supply.lookahead(spark, sf_dir)
    own, see = [n.factor("cust_part"), n.factor("cust_supp")], indicator(n.factor("part_supp_flag"), _TRI_VARS)
    out = None
    for name, extra in (("plain", []), ("projected", [see])):
        d = extend_product(_TRI_VARS, own + extra).df.agg(F.count(F.lit(1)).alias("n_rows")).select(F.lit(name).alias("variant"), "n_rows")
        out = d if out is None else out.unionByName(d)
    return out


def _up_message(strategy: str):
    def run(spark, sf_dir):
        n = supply.lookahead(spark, sf_dir, store=True)
        dec = decompose(n, root=decompose(n).bag_of(("l_returnflag",)))
        _, up, _ = message_up(dec, st.fixed(dec, {n: s for s, n in st.NAMES.items()}[strategy]), replace(INT, materialise="lazy"))
        (m,) = up.values()
        return m.df.select("l_partkey", "l_suppkey", F.col(W).alias("mass"))

    return run


query(f"{_LOOK} SELECT l_partkey, l_suppkey, sum(w)::BIGINT AS mass FROM bag GROUP BY ALL", "lookahead_up_message")(_up_message("multiway"))
query(f"{_LOOK} SELECT l_partkey, l_suppkey, sum(w)::BIGINT AS mass FROM bag SEMI JOIN psf USING (l_partkey, l_suppkey) GROUP BY ALL", "lookahead_up_message_projected")(_up_message("multiway_proj"))


@query(f"{_LOOK}, up AS (SELECT DISTINCT l_partkey, l_suppkey FROM bag) SELECT l_partkey, l_suppkey, sum(psf.w)::BIGINT AS mass FROM psf SEMI JOIN up USING (l_partkey, l_suppkey) GROUP BY ALL")
def lookahead_down_message(spark, sf_dir):
    """A pair that one order has is in the bag, as its customer has both; only the others are looked for in it."""
    f, up = supply.part_supp(spark, sf_dir), supply.ordered_pairs(spark, sf_dir)
    sure = rel.materialise(f.df.join(up, ["l_partkey", "l_suppkey"], "left").select(*f.vars, W, F.coalesce("ordered", F.lit(False)).alias("ordered")))
    down = Factor(f.name, f.vars, sure.filter("ordered").select(*f.vars, W))
    if not sure.filter("NOT ordered").isEmpty():  # pairs without an order of their own: someone may have both from others
        rest = Factor(f.name, f.vars, sure.filter("NOT ordered").select(*f.vars, W))
        who = extend_product(("l_partkey", "l_suppkey", "o_custkey"), [indicator(rest, f.vars), supply.cust_part(spark, sf_dir), supply.cust_supp(spark, sf_dir)])
        down = Factor(f.name, f.vars, down.df.unionByName(rel.reduce_by(rest, who.df.select(*f.vars)).df))
    return down.df.select("l_partkey", "l_suppkey", F.col(W).alias("mass"))


@query(f"{_LOOK} {_union(_LOOK_VARS)}")
def lookahead_variable_marginals(spark, sf_dir):
    m = infer(supply.lookahead(spark, sf_dir), "multiway_proj", config=InferConfig(policy=ALL, indicator_mode="semijoin")).variable_marginals()
    return m.select("variable", "value", F.col("mass").cast("bigint").alias("mass"), F.round("prob", 9).alias("prob"))


@query(f"{_LOOK} SELECT l_partkey, l_suppkey, l_returnflag, sum(w)::BIGINT AS mass FROM j GROUP BY ALL")
def lookahead_factor_marginal_psf(spark, sf_dir):
    return infer(supply.lookahead(spark, sf_dir), "pairwise").factor_marginals()["part_supp_flag"]


# toy network: strategies, layouts, baselines (M12, M13, B0-B3; W3, W11)
for _name, _strategy, _config in (("plain", "multiway", INT), ("projected", "multiway_proj", INT), ("pairwise", "pairwise", INT), ("hybrid", "hybrid", INT), ("hybrid_timed", "hybrid", replace(INT, strategy_mode="timed")), ("quotient", "pairwise", InferConfig(calibration="quotient")), ("merge_down", "pairwise", InferConfig(calibration="quotient", down="merge")), ("forward_list", "pairwise", InferConfig(layout="forward_list")), ("free_first", "multiway", InferConfig(order="free_first")), ("min_domain", "multiway", InferConfig(order="min_domain"))):

    def _run(spark, sf_dir, strategy=_strategy, config=_config):
        m = infer(toy.network(spark, sf_dir), strategy, config=config).variable_marginals(probs=False)
        return m.select("variable", "value", F.round("mass", 3).cast("bigint").alias("mass"))

    query(f"{_TOY} {_union(_TOY_VARS, prob=False)}", f"toy_marginals_{_name}")(_run)

_TOY_PROBS = f"{_TOY} {_union(_TOY_VARS, mass=False)}"


@query(_TOY_PROBS)
def toy_marginals_brute(spark, sf_dir):
    return _probs(brute_force(toy.network(spark, sf_dir)))


@query(_TOY_PROBS)
def toy_marginals_dense(spark, sf_dir):
    return _probs(dense_junction_tree(toy.network(spark, sf_dir)))


@query(_TOY_PROBS)
def toy_marginals_circuit(spark, sf_dir):
    return _probs(compile_circuit(toy.network(spark, sf_dir)).evaluate()[0])


@query(_TOY_PROBS)
def toy_marginals_joingraph(spark, sf_dir):
    return _probs(join_graph_propagation(toy.network(spark, sf_dir), degree=4)[0])


@query()
def toy_marginals_joingraph_degree2(spark, sf_dir):
    return _probs(join_graph_propagation(toy.network(spark, sf_dir), degree=2, iterations=3)[0])


@query(_TOY_PROBS)
def toy_marginals_batched(spark, sf_dir):
    return _probs(solve_trees(toy.network(spark, sf_dir)).filter("variable is not null"))


@query(_TOY_PROBS)
def toy_marginals_scaled(spark, sf_dir):
    return _probs(infer(toy.network(spark, sf_dir), "pairwise", config=InferConfig(scaled=True)).variable_marginals())


@query(f"{_TOY} SELECT c_mktsegment, o_orderstatus, sum(w)::BIGINT AS mass FROM j GROUP BY ALL")
def toy_joint_segment_status(spark, sf_dir):
    return marginal(toy.network(spark, sf_dir), ("c_mktsegment", "o_orderstatus"), strategy="pairwise").select("c_mktsegment", "o_orderstatus", "mass")


@query(f"{_TOY} SELECT z::BIGINT AS z FROM z")
def toy_partition_function(spark, sf_dir):
    return infer(toy.network(spark, sf_dir), "pairwise").partition_function()


@query(f"{_TOY} SELECT 'seg_nation' AS factor, c_mktsegment AS v1, c_nationkey::VARCHAR AS v2, NULL AS v3, sum(w)::BIGINT AS mass FROM j GROUP BY ALL UNION ALL SELECT 'seg_prio', c_mktsegment, o_orderpriority, NULL, sum(w)::BIGINT FROM j GROUP BY ALL UNION ALL SELECT 'nation_prio_status', c_nationkey::VARCHAR, o_orderpriority, o_orderstatus, sum(w)::BIGINT FROM j GROUP BY ALL")
def toy_factor_marginals(spark, sf_dir):
    out = None
    for name, df in infer(toy.network(spark, sf_dir), "pairwise").factor_marginals().items():
        vars = [c for c in df.columns if c != "mass"]
        part = df.select(F.lit(name).alias("factor"), *[(F.col(vars[i]).cast("string") if i < len(vars) else F.lit(None).cast("string")).alias(f"v{i + 1}") for i in range(3)], "mass")
        out = part if out is None else out.unionByName(part)
    return out


@query(f"{_TOY} SELECT c_mktsegment, c_nationkey, o_orderpriority, o_orderstatus, w::BIGINT AS mass FROM j ORDER BY w DESC, c_mktsegment, c_nationkey, o_orderpriority, o_orderstatus LIMIT 20")
def toy_most_probable_rows(spark, sf_dir):
    n = toy.network(spark, sf_dir)
    f = pairwise_product(tuple(_TOY_VARS), list(n.factors), "greedy", MAX_PRODUCT)
    return rel.most_probable(f, 20).withColumnRenamed(W, "mass")


@query(f"{_TOY} " + " UNION ALL ".join(f"SELECT '{v}' AS variable, {v}::VARCHAR AS value, max(w)::BIGINT AS mass FROM j GROUP BY {v}" for v in _TOY_VARS))
def toy_max_marginals(spark, sf_dir):
    return _masses(infer(toy.network(spark, sf_dir), "pairwise", config=InferConfig(semiring=MAX_PRODUCT)).variable_marginals(probs=False))


@query(f"{_TOY} " + " UNION ALL ".join(f"SELECT DISTINCT '{v}' AS variable, {v}::VARCHAR AS value FROM j" for v in _TOY_VARS))
def toy_support_boolean(spark, sf_dir):
    n = toy.network(spark, sf_dir)
    ones = Network.of([Factor(f.name, f.vars, f.df.withColumn(W, F.lit(1).cast("bigint"))) for f in n.factors], n.domains, n.sizes)
    return infer(ones, "pairwise", config=InferConfig(semiring=BOOLEAN)).variable_marginals(probs=False).select("variable", "value")


@query(f"{_TOY}, e AS (SELECT * FROM j WHERE o_orderstatus = 'F') {_union(_TOY_VARS[:3], 'e')}")
def toy_evidence_marginals(spark, sf_dir):
    m = infer(toy.network(spark, sf_dir), "pairwise", evidence={"o_orderstatus": "F"}).variable_marginals()
    return m.select("variable", "value", F.col("mass").cast("bigint").alias("mass"), F.round("prob", 9).alias("prob"))


@query(f"{_TOY}, e AS (SELECT * REPLACE (w * CASE o_orderstatus WHEN 'F' THEN 0.7 WHEN 'O' THEN 0.2 ELSE 0.1 END AS w) FROM j) {_union(_TOY_VARS, 'e', mass=False)}")
def toy_soft_evidence(spark, sf_dir):
    n = toy.network(spark, sf_dir).with_unary("o_orderstatus", {"F": 0.7, "O": 0.2, "P": 0.1})
    return _probs(infer(n, "pairwise").variable_marginals())


@query(f"{_TOY}, e AS (SELECT * FROM j WHERE o_orderpriority IN ('1-URGENT', '2-HIGH') AND c_nationkey BETWEEN 3 AND 9) {_union(_TOY_VARS, 'e')}")
def toy_set_evidence(spark, sf_dir):
    n = toy.network(spark, sf_dir)
    n = n.replaced([n.factor("seg_prio").where_in("o_orderpriority", ["1-URGENT", "2-HIGH"]), n.factor("seg_nation").where_between("c_nationkey", 3, 9)])
    m = infer(n, "pairwise").variable_marginals()
    return m.select("variable", "value", F.col("mass").cast("bigint").alias("mass"), F.round("prob", 9).alias("prob"))


@query(f"{_TOY}, u AS ({_union(_TOY_VARS, prob=False)}) SELECT variable, value, mass, rk FROM (SELECT *, row_number() OVER (PARTITION BY variable ORDER BY mass DESC, value) AS rk FROM u) WHERE rk <= 3")
def topk_values(spark, sf_dir):
    return rel.topk(_masses(infer(toy.network(spark, sf_dir), "pairwise").variable_marginals(probs=False)), 3)


# star network
def _star_sql(where: str = "") -> str:
    src = {
        "region": "(SELECT n_regionkey AS region FROM nation)", "nation": "(SELECT n_regionkey AS region, n_nationkey AS nation FROM nation)",
        "segment": "(SELECT c_nationkey AS nation, c_mktsegment AS segment FROM customer)",
        "prio": "(SELECT c_mktsegment AS segment, o_orderpriority AS prio FROM orders JOIN customer ON o_custkey = c_custkey)",
        "status": "(SELECT o_orderpriority AS prio, o_orderstatus AS status FROM orders)",
        "linestatus": "(SELECT o_orderstatus AS status, l_linestatus AS linestatus FROM lineitem JOIN orders ON l_orderkey = o_orderkey)",
        "flag": "(SELECT l_linestatus AS linestatus, l_returnflag AS flag FROM lineitem)", "lineno": "(SELECT l_returnflag AS flag, l_linenumber AS lineno FROM lineitem)",
        "quantity": "(SELECT l_linenumber AS lineno, l_quantity::INT AS quantity FROM lineitem)",
        "tax": "(SELECT l_quantity::INT AS quantity, round(l_discount * 100)::INT AS discount, round(l_tax * 100)::INT AS tax FROM lineitem)",
        "brand": "(SELECT l_quantity::INT AS quantity, p_brand AS brand FROM lineitem JOIN part ON l_partkey = p_partkey)",
        "type": "(SELECT p_brand AS brand, p_type AS ptype FROM part)", "size": "(SELECT p_brand AS brand, p_type AS ptype, p_size AS psize FROM part)",
    }
    ctes = []
    for name, child, parents in star.SHAPE:
        over = f"PARTITION BY {', '.join(parents)}" if parents else ""
        cond = f" WHERE {where}" if where and where.split(" ")[0] in (child, *parents) else ""
        ctes.append(f"p_{name} AS (SELECT * FROM (SELECT {', '.join((*parents, child))}, count(*)::DOUBLE / sum(count(*)) OVER ({over}) AS p FROM {src[name]} GROUP BY {', '.join((*parents, child))}){cond})")
    chain = [(n, c, p) for n, c, p in star.SHAPE if n not in ("tax", "brand", "type", "size")]
    prev = None
    for name, child, parents in chain:
        ctes.append(f"f_{child} AS (SELECT {child}, sum(p{' * f' if parents else ''}) AS f FROM p_{name}{f' JOIN f_{prev} USING ({prev})' if parents else ''} GROUP BY {child})")
        prev = child
    ctes.append("t_tax AS (SELECT quantity, sum(p) AS t FROM p_tax GROUP BY quantity)")
    ctes.append("t_size AS (SELECT brand, ptype, sum(p) AS t FROM p_size GROUP BY brand, ptype)")
    ctes.append("t_type AS (SELECT brand, sum(p * t) AS t FROM p_type JOIN t_size USING (brand, ptype) GROUP BY brand)")
    ctes.append("t_brand AS (SELECT quantity, sum(p * t) AS t FROM p_brand JOIN t_type USING (brand) GROUP BY quantity)")
    ctes.append("b_quantity AS (SELECT quantity, t_tax.t * t_brand.t AS b FROM t_tax JOIN t_brand USING (quantity))")
    for (_, child, _), (name, nxt, _) in reversed(list(zip(chain, chain[1:]))):
        ctes.append(f"b_{child} AS (SELECT {child}, sum(p * b) AS b FROM p_{name} JOIN b_{nxt} USING ({nxt}) GROUP BY {child})")
    parts = [f"SELECT '{c}' AS variable, {c}::VARCHAR AS value, f * b AS m FROM f_{c} JOIN b_{c} USING ({c})" for _, c, _ in chain]
    q = "f_quantity JOIN {} USING (quantity)"
    parts += [f"SELECT '{v}', {v}::VARCHAR, sum(f * p * t_brand.t) FROM {q.format('p_tax')} JOIN t_brand USING (quantity) GROUP BY {v}" for v in ("tax", "discount")]
    down = f"{q.format('p_brand')} JOIN t_tax USING (quantity)"
    parts.append(f"SELECT 'brand', brand, sum(f * p_brand.p * t_tax.t * t_type.t) FROM {down} JOIN t_type USING (brand) GROUP BY brand")
    parts.append(f"SELECT 'ptype', ptype, sum(f * p_brand.p * t_tax.t * p_type.p * t_size.t) FROM {down} JOIN p_type USING (brand) JOIN t_size USING (brand, ptype) GROUP BY ptype")
    parts.append(f"SELECT 'psize', psize::VARCHAR, sum(f * p_brand.p * t_tax.t * p_type.p * p_size.p) FROM {down} JOIN p_type USING (brand) JOIN p_size USING (brand, ptype) GROUP BY psize")
    skip = f" WHERE variable <> '{where.split(' ')[0]}'" if where else ""
    return f"WITH {', '.join(ctes)}, u AS ({' UNION ALL '.join(parts)}) SELECT variable, value, round(m / sum(m) OVER (PARTITION BY variable), 6) AS prob FROM u{skip}"


@query(_star_sql())
def star_variable_marginals(spark, sf_dir):
    return _probs(solve_trees(star.network(spark, sf_dir)).filter("variable is not null"), 6)


@query(_star_sql())
def star_marginals_pairwise(spark, sf_dir):
    return _probs(infer(star.network(spark, sf_dir), "pairwise").variable_marginals(), 6)


@query(_star_sql("status = 'F'"))
def star_evidence_marginals(spark, sf_dir):
    n = apply_evidence(star.network(spark, sf_dir), {"status": "F"})
    return _probs(solve_trees(n).filter("variable is not null"), 6)


@query("SELECT 'region' AS variable, n_regionkey::VARCHAR AS value FROM nation WHERE n_nationkey = 7")
def star_singleton_consistency(spark, sf_dir):
    src = star.base(spark, sf_dir)
    n = Network.of([Factor.counts("nation", src["nation"], ("region", "nation")), Factor.counts("segment", src["segment"], ("nation", "segment"))])
    _, found = singleton_consistency(apply_evidence(n, {"nation": 7}))
    return spark.createDataFrame([(k, str(v)) for k, v in sorted(found.items())], "variable string, value string")


# size, sparsity, projections (M2, M9)
@query(f"{_TOY} SELECT factor, arity, n_rows, domain_cells, n_rows / domain_cells AS sparsity FROM (SELECT 'seg_nation' AS factor, 2 AS arity, (SELECT count(*) FROM ab) AS n_rows, (SELECT count(DISTINCT c_mktsegment) * count(DISTINCT c_nationkey) FROM ab)::DOUBLE AS domain_cells UNION ALL SELECT 'seg_prio', 2, (SELECT count(*) FROM ac), (SELECT count(DISTINCT c_mktsegment) * count(DISTINCT o_orderpriority) FROM ac) UNION ALL SELECT 'nation_prio_status', 3, (SELECT count(*) FROM bcd), (SELECT count(DISTINCT c_nationkey) * count(DISTINCT o_orderpriority) * count(DISTINCT o_orderstatus) FROM bcd))")
def factor_profile(spark, sf_dir):
    return toy.network(spark, sf_dir).factor_profile()


@query("WITH s AS (SELECT count(*) / (count(DISTINCT n_regionkey) * count(DISTINCT n_nationkey))::DOUBLE AS s FROM nation UNION ALL SELECT count(*) / (count(DISTINCT a) * count(DISTINCT b))::DOUBLE FROM (SELECT DISTINCT l_returnflag AS a, l_linestatus AS b FROM lineitem) UNION ALL SELECT count(*) / (count(DISTINCT a) * count(DISTINCT b))::DOUBLE FROM (SELECT DISTINCT p_brand AS a, p_size AS b FROM part)) SELECT round(median(s), 9) AS median_sparsity, round(avg(s), 9) AS mean_sparsity, round(max(s), 9) AS max_sparsity FROM s")
def sparsity_summary(spark, sf_dir):
    n = Network.of([
        Factor.counts("nation", table(spark, sf_dir, "nation", "n_regionkey", "n_nationkey"), ("n_regionkey", "n_nationkey")),
        Factor.counts("flags", table(spark, sf_dir, "lineitem", "l_returnflag", "l_linestatus"), ("l_returnflag", "l_linestatus")),
        Factor.counts("brand_size", table(spark, sf_dir, "part", "p_brand", "p_size"), ("p_brand", "p_size")),
    ])
    s = n.sparsity_summary()
    return s.select(*[F.round(c, 9).alias(c) for c in s.columns])


@query("SELECT DISTINCT l_partkey, l_suppkey, 1 AS w FROM lineitem")
def indicator_projection(spark, sf_dir):
    return indicator(supply.part_supp_flag(spark, sf_dir), ("l_partkey", "l_suppkey")).df


@query("SELECT 'part_supp_flag' AS factor, 'l_partkey,l_suppkey' AS vars, round(count(*) / ((SELECT count(*) FROM part) * (SELECT count(*) FROM supplier))::DOUBLE, 9) AS density FROM (SELECT DISTINCT l_partkey, l_suppkey FROM lineitem)")
def projection_density(spark, sf_dir):
    n = supply.lookahead(spark, sf_dir)
    rep = projection_report(decompose(n), ProjectionCache(n))
    return rep.filter("factor = 'part_supp_flag'").select("factor", "vars", F.round("density", 9).alias("density"))


# indices and tries
_CODES = "SELECT c_nationkey AS a, dense_rank() OVER (ORDER BY c_mktsegment) - 1 AS b, dense_rank() OVER (ORDER BY o_orderpriority) - 1 AS c FROM orders JOIN customer ON o_custkey = c_custkey"


def _coded(spark, sf_dir):
    c = table(spark, sf_dir, "customer", "c_custkey", "c_nationkey", "c_mktsegment")
    o = table(spark, sf_dir, "orders", "o_custkey", "o_orderpriority")
    x = o.join(c, F.col("o_custkey") == F.col("c_custkey")).select(F.col("c_nationkey").cast("bigint").alias("a"), F.col("c_mktsegment").alias("b"), F.col("o_orderpriority").alias("c"))
    for v in ("b", "c"):
        x = Domain.fit(x, v).encode(x, v)
    return x.select("a", "b", "c").distinct()


@query(f"WITH t AS (SELECT DISTINCT * FROM ({_CODES})) SELECT a, b, c, (a * 5 + b) * 5 + c AS idx FROM t")
def forward_index(spark, sf_dir):
    return _coded(spark, sf_dir).withColumn("idx", index.forward_index(["a", "b", "c"], [25, 5, 5]))


@query(f"WITH t AS (SELECT DISTINCT * FROM ({_CODES})) SELECT a, b, c, (c * 5 + b) * 25 + a AS idx FROM t")
def reverse_index(spark, sf_dir):
    return _coded(spark, sf_dir).withColumn("idx", index.reverse_index(["a", "b", "c"], [25, 5, 5]))


@query(f"WITH t AS (SELECT DISTINCT * FROM ({_CODES})) SELECT a, b, c, (c * 5 + b) * 25 + a AS again FROM t")
def index_roundtrip(spark, sf_dir):
    x = _coded(spark, sf_dir).select(index.forward_index(["a", "b", "c"], [25, 5, 5]).alias("i"))
    codes = index.decode_index("i", [25, 5, 5])
    return x.select(*[c.alias(n) for c, n in zip(codes, "abc")], index.reindex("i", [25, 5, 5]).alias("again"))


@query("WITH t AS (SELECT DISTINCT p_brand, p_type, p_size FROM part), r AS (SELECT *, dense_rank() OVER (ORDER BY p_brand) - 1 AS p0, dense_rank() OVER (ORDER BY p_brand, p_type) - 1 AS p1, dense_rank() OVER (ORDER BY p_brand, p_type, p_size) - 1 AS p2 FROM t) SELECT 0 AS level, p0 AS pos, NULL::BIGINT AS parent_pos, p_brand AS value, min(p1) AS child_lo, max(p1) AS child_hi FROM r GROUP BY ALL UNION ALL SELECT 1, p1, p0, p_type, min(p2), max(p2) FROM r GROUP BY ALL UNION ALL SELECT 2, p2, p1, p_size::VARCHAR, NULL, NULL FROM r", "level_order_trie")
def _trie(spark, sf_dir):
    p = table(spark, sf_dir, "part", "p_brand", "p_type", "p_size")
    return level_order_trie(Factor.counts("bts", p, ("p_brand", "p_type", "p_size")))


# sparsity induction and dense tables
_HASH = "((({seed}::BIGINT * 48271 + a * 69621 + 11) % 2147483647) * 48271 + b * 69621 + 11) % 2147483647"


@query(f"WITH t AS (SELECT (l_linenumber - 1)::BIGINT AS a, (l_quantity::INT - 1)::BIGINT AS b, count(*) AS w FROM lineitem GROUP BY ALL), k AS (SELECT * FROM t WHERE ({_HASH.format(seed=3)}) % 1000 < 200 OR (a = b AND a < 7)) SELECT a, b, w FROM k UNION ALL SELECT i, i, 1 FROM range(7) r(i) WHERE NOT EXISTS (SELECT 1 FROM t WHERE a = i AND b = i)")
def induced_sparsity(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem", "l_linenumber", "l_quantity").select((F.col("l_linenumber") - 1).alias("a"), (F.col("l_quantity").cast("int") - 1).alias("b"))
    return Factor.counts("ln_q", li, ("a", "b")).induce_sparsity(20, 3, {"a": list(range(7)), "b": list(range(50))}).df


@query("SELECT b.p_brand, t.p_type, s.p_size, coalesce(c.w, 0) AS w FROM (SELECT DISTINCT p_brand FROM part) b CROSS JOIN (SELECT DISTINCT p_type FROM part) t CROSS JOIN (SELECT DISTINCT p_size FROM part) s LEFT JOIN (SELECT p_brand, p_type, p_size, count(*) AS w FROM part GROUP BY ALL) c USING (p_brand, p_type, p_size)")
def dense_truth_table(spark, sf_dir):
    f = Factor.counts("bts", table(spark, sf_dir, "part", "p_brand", "p_type", "p_size"), ("p_brand", "p_type", "p_size"))
    return f.to_dense(domains_of(Network.of([f], {"p_brand": 25, "p_type": 6, "p_size": 50}, {"bts": 1})))


# products and joins
def _big(spark, sf_dir):
    return supply.part_supp_flag(spark, sf_dir), Factor.counts("by_part", table(spark, sf_dir, "part", "p_partkey", "p_size").select(F.col("p_partkey").alias("l_partkey"), "p_size").filter("p_size > 25"), ("l_partkey",))


_PROD = f"WITH {_PSF}, p AS (SELECT p_partkey AS l_partkey, count(*) AS w FROM part WHERE p_size > 25 GROUP BY ALL) SELECT l_partkey, l_suppkey, l_returnflag, psf.w * p.w AS w FROM psf JOIN p USING (l_partkey)"


@query(_PROD)
def hash_product(spark, sf_dir):
    return rel.hash_product(*_big(spark, sf_dir)).df


@query(_PROD)
def sort_merge_product(spark, sf_dir):
    return rel.sort_merge_product(*_big(spark, sf_dir)).df


@query(_PROD)
def broadcast_product(spark, sf_dir):
    return rel.hash_product(*_big(spark, sf_dir), hint="broadcast").df


@query(f"WITH {_PSF}, s AS (SELECT l_suppkey, sum(w) AS t FROM psf GROUP BY ALL) SELECT l_partkey, l_suppkey, l_returnflag, round(psf.w / s.t, 9) AS w FROM psf JOIN s USING (l_suppkey)")
def quotient_message(spark, sf_dir):
    f = supply.part_supp_flag(spark, sf_dir)
    return rel.hash_product(f, f.onto(("l_suppkey",)), "div").df.withColumn(W, F.round(W, 9))


@query(f"WITH {_PSF} SELECT l_partkey, l_suppkey, l_returnflag, w FROM psf WHERE NOT EXISTS (SELECT 1 FROM part WHERE p_partkey = l_partkey AND p_size > 25)")
def dead_rows(spark, sf_dir):
    return rel.dead_rows(*_big(spark, sf_dir))


@query("SELECT o_orderpriority, o_orderstatus, round(n / sum(n) OVER (PARTITION BY o_orderpriority), 9) AS prob FROM (SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM orders GROUP BY ALL)")
def conditional_factor(spark, sf_dir):
    f = Factor.conditional("c", table(spark, sf_dir, "orders", "o_orderpriority", "o_orderstatus"), "o_orderstatus", ("o_orderpriority",))
    return f.df.select("o_orderpriority", "o_orderstatus", F.round(W, 9).alias("prob"))


@query("SELECT a.s AS a, b.s AS b, 1 AS w FROM (SELECT DISTINCT p_size AS s FROM part) a JOIN (SELECT DISTINCT p_size AS s FROM part) b ON a.s < b.s AND (a.s + b.s) % 7 = 0")
def constraint_factor(spark, sf_dir):
    s = table(spark, sf_dir, "part", "p_size")
    return Factor.constraint("c", s.select(F.col("p_size").alias("a")), s.select(F.col("p_size").alias("b")), "a < b AND (a + b) % 7 = 0").df


@query("SELECT a.s AS a, b.s AS b, 1 AS w FROM (SELECT DISTINCT p_size AS s FROM part) a JOIN (SELECT DISTINCT p_size AS s FROM part) b ON abs(a.s - b.s) <= 4")
def near_values_factor(spark, sf_dir):
    s = table(spark, sf_dir, "part", "p_size")
    return Factor.within("n", s.select(F.col("p_size").alias("a")), s.select(F.col("p_size").alias("b")), 4).df


@query("SELECT x.event_type AS a, y.event_type AS b, count(*) AS w FROM events x JOIN events y ON x.user_id = y.user_id AND y.ts > x.ts AND y.ts <= x.ts + INTERVAL 3600 SECOND GROUP BY ALL")
def cooccur_factor(spark, sf_dir):
    e = table(spark, sf_dir, "events", "user_id", "ts", "event_type")
    return Factor.cooccur("c", e, "user_id", "ts", "event_type", 3600).df


@query("SELECT l_returnflag, l_linestatus, l_linenumber, grouping_id(l_returnflag, l_linestatus, l_linenumber)::BIGINT AS gid, count(*) AS mass FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus, l_linenumber)")
def cube_marginals(spark, sf_dir):
    v = ["l_returnflag", "l_linestatus", "l_linenumber"]
    f = Factor.counts("c", table(spark, sf_dir, "lineitem", *v), v)
    return rel.cube_marginals(f.df, v).withColumn("gid", F.col("gid").cast("bigint"))


@query("SELECT l_partkey AS k FROM lineitem INTERSECT SELECT p_partkey FROM part WHERE p_size > 25")
def common_support(spark, sf_dir):
    return rel.common_support(table(spark, sf_dir, "lineitem", "l_partkey").select(F.col("l_partkey").alias("k")), table(spark, sf_dir, "part", "p_partkey", "p_size").filter("p_size > 25").select(F.col("p_partkey").alias("k")))


@query("SELECT o_orderkey AS k FROM orders EXCEPT SELECT l_orderkey FROM lineitem")
def diff_support(spark, sf_dir):
    return rel.diff_support(table(spark, sf_dir, "orders", "o_orderkey").select(F.col("o_orderkey").alias("k")).distinct(), table(spark, sf_dir, "lineitem", "l_orderkey").select(F.col("l_orderkey").alias("k")).distinct())


@query("SELECT l_returnflag, round(ln(sum(exp(l_tax * 10 + l_discount))), 9) AS lse FROM lineitem GROUP BY ALL")
def log_sum_exp_factor(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem", "l_returnflag", "l_tax", "l_discount").withColumn("x", F.col("l_tax") * 10 + F.col("l_discount"))
    return discretise.log_sum_exp(li, ["l_returnflag"], "x", "lse").withColumn("lse", F.round("lse", 9))


@query("WITH t AS (SELECT l_partkey, l_suppkey, count(*) AS w FROM lineitem GROUP BY ALL) SELECT bag, v1, w FROM (SELECT 0 AS bag, l_partkey::VARCHAR AS v1, sum(w)::DOUBLE AS w FROM t GROUP BY ALL UNION ALL SELECT 1, l_suppkey::VARCHAR, sum(w) FROM t GROUP BY ALL)")
def level_batch(spark, sf_dir):
    f = supply.part_supp(spark, sf_dir)
    out = run_level({0: [f], 1: [f]}, {0: ("l_partkey",), 1: ("l_suppkey",)})
    return out.select("bag", F.col("vals")[0].alias("v1"), W)


# measures (C1-C11, W16)
def _lookahead_dec(spark, sf_dir):
    return decompose(supply.lookahead(spark, sf_dir))


@query(f"WITH {_CP}, {_CS}, {_PSF}, n AS (SELECT ln((SELECT count(*) FROM cp))::DOUBLE AS e, ln((SELECT count(*) FROM cs)) AS f, ln((SELECT count(*) FROM psf)) AS g) SELECT 'l_partkey,l_suppkey,l_returnflag' AS bag, round(g / ln(2), 6) AS log2_agm FROM n UNION ALL SELECT 'o_custkey,l_partkey,l_suppkey', round(least((e + f + g) / 2, e + f, e + g, f + g) / ln(2), 6) FROM n")
def agm_bounds(spark, sf_dir):
    dec = _lookahead_dec(spark, sf_dir)
    names = ["o_custkey", "l_partkey", "l_suppkey", "l_returnflag"]
    return spark.createDataFrame([(",".join(v for v in names if v in c), round(measures.agm(dec, b), 6)) for b, c in enumerate(dec.chi)], "bag string, log2_agm double")


@query("SELECT * FROM (VALUES ('htw', 2.0), ('fhtw', 1.5), ('tw_bag', 3.0), ('tw_minus_one', 2.0)) t(measure, value)")
def width_measures(spark, sf_dir):
    dec = _lookahead_dec(spark, sf_dir)
    rows = [("htw", float(measures.htw(dec))), ("fhtw", measures.fhtw(dec)), ("tw_bag", float(measures.tw(dec))), ("tw_minus_one", float(measures.tw(dec, "minus_one")))]
    return spark.createDataFrame(rows, "measure string, value double")


@query(f"WITH {_CP}, {_CS}, {_PSF}, n AS (SELECT (SELECT count(*) FROM cp)::DOUBLE AS e, (SELECT count(*) FROM cs)::DOUBLE AS f, (SELECT count(*) FROM psf)::DOUBLE AS g, (SELECT count(*) FROM customer)::DOUBLE AS a, (SELECT count(*) FROM part)::DOUBLE AS b, (SELECT count(*) FROM supplier)::DOUBLE AS c) SELECT measure, round(value, 6) AS value FROM (SELECT 'log10_rho' AS measure, log10(a * b * c + b * c * 3) AS value FROM n UNION ALL SELECT 'log10_agm', log10(least(sqrt(e * f * g), e * f, e * g, f * g) + g) FROM n UNION ALL SELECT 'log10_r_j', log10((least(sqrt(e * f * g), e * f, e * g, f * g) + g) / (a * b * c + b * c * 3)) FROM n UNION ALL SELECT 'log10_r_d', 1.5 * log10(greatest(e, f, g)) - 3 * log10(greatest(a, b, c)) FROM n)")
def ratio_measures(spark, sf_dir):
    p = measures.profile(_lookahead_dec(spark, sf_dir))
    return spark.createDataFrame([(k, round(p[k], 6)) for k in ("log10_rho", "log10_agm", "log10_r_j", "log10_r_d")], "measure string, value double")


_BANDED = (("grid28", 28, False), ("grid28_wide", 28, True), ("grid14_wide", 14, True))


def _band_sql() -> str:
    def rows_of(dims) -> str:
        signs = " + ".join(f"{2**i} * (embedding[{d + 1}] > 0)::INT" for i, d in enumerate(dims))
        return f"count(DISTINCT {signs})"

    n = [f"SELECT '{name}' AS network, greatest({', '.join(dict.fromkeys(rows_of(d) for d, full in grid.tables(side, side, wide_factor=wide).values() if full))})::INT AS max_factor FROM embeddings" for name, side, wide in _BANDED]
    shape = "(VALUES ('grid28', 606, 43, 38.0, TRUE), ('grid28_wide', 606, 43, 38.0, TRUE), ('grid14_wide', 160, 20, 18.0, FALSE)) t(network, n_bags, max_bag, fhtw, large)"
    band = "CASE WHEN large THEN 1 ELSE 4 END + (r_d > 0)::INT + (r_d > 10)::INT"
    return f"WITH n AS ({' UNION ALL '.join(n)}), r AS (SELECT *, fhtw * log10(max_factor) - max_bag * log10(2) AS r_d FROM {shape} JOIN n USING (network)) SELECT network, n_bags, max_bag, fhtw, max_factor, {band} AS band, CASE WHEN {band} <= 4 THEN 'multiway' ELSE 'dense' END AS winner FROM r"


@query(_band_sql())
def network_band(spark, sf_dir):
    """Bands of the grids (C9), by the sizes that their factors have on the embeddings."""
    rows = []
    for name, side, wide in _BANDED:
        n = grid.metadata(side, side, wide_factor=wide)
        p = measures.profile(decompose(replace(n, sizes=grid.measured_sizes(spark, sf_dir, side, side, wide_factor=wide))))
        rows.append((name, p["n_bags"], p["max_bag"], p["fhtw"], p["max_factor"], p["band"], p["winner"]))
    return spark.createDataFrame(rows, "network string, n_bags int, max_bag int, fhtw double, max_factor int, band int, winner string")


_RATIO_DIMS = range(3, 9)


def _ratio_sql() -> str:
    cols = ", ".join(f"floor((embedding[{i + 1}]::DOUBLE + 1) * 22)::BIGINT AS b{i}" for i in range(8))
    low, high = (f"{f}(" + ", ".join(f"(SELECT {g}(b{i}) FROM b)" for i in range(8)) + ")" for f, g in (("least", "min"), ("greatest", "max")))
    pairs, rows = [(i, j) for i in range(8) for j in range(i + 1, 8)], []
    for keep in (20, 40):
        for i, j in pairs:
            rows.append(f"SELECT {keep} AS keep, {j} AS j, (SELECT count(*) FROM (SELECT DISTINCT b{i} - lo AS x, b{j} - lo AS y FROM b, m) WHERE (7919 * x + 104729 * y + 31 * {i} + 17 * {j}) % 100 < {100 * keep // 42} OR x = y) AS n")
    part = "SELECT 'clique' || k || '_' || keep AS network, k, any_value(d) AS d, max(n) AS n, sum(log10(n)) / (k - 1) - k * log10(any_value(d)) AS all_factors FROM p, m, (SELECT unnest(range(3, 9)) AS k) WHERE j < k GROUP BY k, keep"
    r_d = "k / 2.0 * log10(n) - k * log10(d)"
    return f"WITH b AS (SELECT {cols} FROM embeddings), m AS (SELECT {low} AS lo, {high} - {low} + 1 AS d), p AS ({' UNION ALL '.join(rows)}), c AS ({part}) SELECT network, CASE WHEN k * log10(d) > 9 THEN 1 ELSE 4 END + ({r_d} > 0)::INT + ({r_d} > 10)::INT AS band, round({r_d}, 6) AS log10_r_d, abs({r_d} - all_factors) <= log10(2) AS within_two FROM c"


@query(_ratio_sql())
def published_ratio_check(spark, sf_dir):
    """R_D of the binned embeddings' cliques (C8), and whether it is within a factor of two of the ratio by all
    pair tables' sizes, each covering its variables in equal parts. ``published.ROWS`` has figures of other
    networks, which no table carries; the tests hold ``measures.ratio`` against them."""
    import math

    rows = []
    for keep in (20, 40):
        n = clique.network(spark, sf_dir, dims=8, keep=keep)
        for k in _RATIO_DIMS:
            own = tuple(f for f in n.factors if set(f.vars) <= {f"d{i}" for i in range(k)})
            dec = decompose(Network(own, {f"d{i}": n.domains[f"d{i}"] for i in range(k)}, {f.name: n.sizes[f.name] for f in own}))
            p = measures.profile(dec)
            both = sum(math.log10(x) for x in dec.network.sizes.values()) / (k - 1) - p["log10_rho"]
            rows.append((f"clique{k}_{keep}", p["band"], round(p["log10_r_d"], 6), abs(p["log10_r_d"] - both) <= math.log10(2)))
    return spark.createDataFrame(rows, "network string, band int, log10_r_d double, within_two boolean")


@query("SELECT * FROM (VALUES ('c_nationkey,o_orderpriority,o_orderstatus', 'nation_prio_status'), ('c_mktsegment,c_nationkey,o_orderpriority', 'seg_nation,seg_prio')) t(chi, alpha)")
def bag_table(spark, sf_dir):
    dec = decompose(toy.network(spark, sf_dir))
    return dec.table(spark).select(F.concat_ws(",", F.array_sort("chi")).alias("chi"), F.concat_ws(",", F.array_sort("alpha")).alias("alpha"))


@query()
def strategy_map(spark, sf_dir):
    return st.strategy_map(spark, st.choose_strategies(decompose(supply.lookahead(spark, sf_dir))))


@query("SELECT * FROM (VALUES ('multiway', 2, 100.0), ('multiway_proj', 0, 0.0), ('pairwise', 0, 0.0)) t(strategy, bags, percent)")
def strategy_report(spark, sf_dir):
    dec = decompose(toy.network(spark, sf_dir))
    return st.strategy_report(spark, st.fixed(dec, st.PLAIN))


def _lawful(dec, choices, allowed) -> bool:
    """Every bag decided by an allowed strategy, and inherited choices equal to their source."""
    return all(c.strategy in allowed and (c.inherited_from is None or c.strategy == choices[c.inherited_from].strategy) for c in choices.values())


@query("SELECT * FROM (VALUES ('cost', 2, 2, 100.0, TRUE), ('timed', 2, 2, 100.0, TRUE), ('random', 2, 2, 100.0, TRUE)) t(mode, bags, decided, percent, lawful)")
def strategy_modes(spark, sf_dir):
    """The choice by metadata, by timed trial products, and beyond the cell limit at random."""
    dec = decompose(toy.network(spark, sf_dir))
    rows = []
    for mode, options, allowed in (("cost", {}, (0, 1, 2)), ("timed", {"mode": "timed"}, (0, 1, 2)), ("random", {"mode": "timed", "rho_limit": 0.0}, (0, 1))):
        choices = st.choose_strategies(dec, **options)
        shares = [r.percent for r in st.strategy_report(spark, choices).collect()]
        rows.append((mode, len(dec.chi), len(choices), float(sum(shares)), _lawful(dec, choices, allowed)))
    return spark.createDataFrame(rows, "mode string, bags int, decided int, percent double, lawful boolean")


@query()
def strategy_shares(spark, sf_dir):
    """Shares of the strategies chosen by timed trials on the network with a factor to look ahead at (M13e)."""
    return st.strategy_report(spark, st.choose_strategies(decompose(supply.lookahead(spark, sf_dir)), mode="timed"))


@query()
def explain_bags(spark, sf_dir):
    return infer(toy.network(spark, sf_dir), "hybrid").explain_bags()


# events (W7)
_TRANS = "SELECT prev, next, count(*) AS w FROM (SELECT lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS prev, event_type AS next FROM events) WHERE prev IS NOT NULL GROUP BY ALL"
_EMIT = "SELECT event_type, (props->>'$.k')::INT AS k, count(*) AS w FROM events GROUP BY ALL"


@query(_TRANS)
def event_transition_factor(spark, sf_dir):
    return events.transition_counts(spark, sf_dir).df


@query(_EMIT)
def event_emission_factor(spark, sf_dir):
    return events.emission_counts(spark, sf_dir).df


@query(f"WITH RECURSIVE t AS (SELECT prev, next, w / sum(w) OVER (PARTITION BY prev) AS p FROM ({_TRANS})), e AS (SELECT event_type, k, w / sum(w) OVER (PARTITION BY event_type) AS p FROM ({_EMIT})), f AS (SELECT 0 AS slice, prev AS s, 1.0::DOUBLE AS f FROM (SELECT DISTINCT prev FROM t) UNION ALL SELECT slice, s, sum(x) FROM (SELECT f.slice + 1 AS slice, t.next AS s, f.f * t.p AS x FROM f JOIN t ON f.s = t.prev WHERE f.slice < 719) GROUP BY slice, s) SELECT 's' || slice AS variable, s AS value, round(f / sum(f) OVER (PARTITION BY slice), 9) AS prob FROM f UNION ALL SELECT 'k' || slice, k::VARCHAR, round(x / sum(x) OVER (PARTITION BY slice), 9) FROM (SELECT slice, k, sum(f * p) AS x FROM f JOIN e ON s = event_type GROUP BY slice, k)")
def event_chain_marginals(spark, sf_dir):
    n, templates = events.chain(spark, sf_dir)
    return _probs(solve_trees(n, templates).filter("variable is not null"))


# cliques and grids
def _clique_sql(dims: int, keep: int) -> str:
    cols = ", ".join(f"floor((embedding[{i + 1}]::DOUBLE + 1) * 22)::BIGINT AS b{i}" for i in range(dims))
    low = "least(" + ", ".join(f"(SELECT min(b{i}) FROM b)" for i in range(dims)) + ")"
    ctes = [f"b AS (SELECT {cols} FROM embeddings)", f"m AS (SELECT {low} AS lo)"]
    joins, seen = "", set()
    for i in range(dims):
        for j in range(i + 1, dims):
            ctes.append(f"p{i}{j} AS (SELECT DISTINCT b{i} - lo AS d{i}, b{j} - lo AS d{j} FROM b, m WHERE (7919 * (b{i} - lo) + 104729 * (b{j} - lo) + 31 * {i} + 17 * {j}) % 100 < {100 * keep // 42} OR b{i} = b{j})")
            on = [v for v in (i, j) if v in seen]
            joins += f"p{i}{j}" if not joins else f" JOIN p{i}{j} USING ({', '.join(f'd{v}' for v in on)})"
            seen |= {i, j}
    ctes.append(f"j AS (SELECT {', '.join(f'd{i}' for i in range(dims))}, 1 AS w FROM {joins})")
    return f"WITH {', '.join(ctes)} {_union([f'd{i}' for i in range(dims)], prob=False)}"


def _clique(spark, sf_dir, dims: int, keep: int, multiway: bool = True):
    n = clique.network(spark, sf_dir, dims=dims, keep=keep)
    fs = [Factor(f.name, f.vars, rel.materialise(f.df)) for f in n.factors]
    vars = tuple(f"d{i}" for i in range(dims))
    if not multiway and masks.fits(n.domains):
        return masks.clique_marginals(vars, fs)
    bag = multiway_product(vars, fs, impl="grid") if multiway else pairwise_product(vars, fs, "greedy")
    f = Factor("bag", vars, rel.materialise(bag.df))
    out = None
    for v in vars:
        m = f.onto((v,)).df.select(F.lit(v).alias("variable"), F.col(v).cast("string").alias("value"), F.col(W).alias("mass"))
        out = m if out is None else out.unionByName(m)
    return out


@query(_clique_sql(5, 20))
def clique_marginals(spark, sf_dir):
    return _clique(spark, sf_dir, 5, 20)


@query(_clique_sql(8, 20))
def clique8_marginals(spark, sf_dir):
    return _clique(spark, sf_dir, 8, 20)


@query(_clique_sql(8, 40))
def clique8_marginals_40(spark, sf_dir):
    """At 40 % by pairwise joins of the leading dimensions, the rest extended and counted in bits: the product has
    billions of rows on 10,000 vectors."""
    return _clique(spark, sf_dir, 8, 40, multiway=False)


def _grid_sql(rows: int, cols: int) -> str:
    ctes, joins, seen = [], "", set()
    name = lambda p: f"v{p[0]:02d}_{p[1]:02d}"
    weight = []
    for n, (a, b) in enumerate(grid.edge_list(rows, cols)):
        x, y = (cols * a[0] + a[1]) % 64 + 1, (cols * b[0] + b[1]) % 64 + 1
        ctes.append(f"e{n} AS (SELECT (embedding[{x}] > 0)::INT AS {name(a)}, (embedding[{y}] > 0)::INT AS {name(b)}, count(*)::DOUBLE AS w{n} FROM embeddings GROUP BY ALL)")
        on = [name(p) for p in (a, b) if p in seen]
        joins += f"e{n}" if not joins else f" JOIN e{n} USING ({', '.join(on)})"
        seen |= {a, b}
        weight.append(f"w{n}")
    vars = [name((r, c)) for r in range(rows) for c in range(cols)]
    ctes.append(f"j AS (SELECT {', '.join(vars)}, {' * '.join(weight)} AS w FROM {joins})")
    return f"WITH {', '.join(ctes)} {_union(vars, mass=False)}"


@query(_grid_sql(3, 3))
def grid_small_marginals(spark, sf_dir):
    n, templates = grid.network(spark, sf_dir, 3, 3, full_every=1)
    return _probs(solve_trees(n, templates).filter("variable is not null"))


@query()
def grid_thinned_marginals(spark, sf_dir):
    n, templates = grid.network(spark, sf_dir, 28, 28)
    return _probs(solve_trees(n, templates, measured=True).filter("variable is not null"))


# text tables
@query(f"WITH d AS (SELECT *, least(floor(n_chars / 1000.0)::INT, 9) AS size FROM documents), a AS (SELECT lang, source, count(*) AS w FROM d GROUP BY ALL), b AS (SELECT lang, size, count(*) AS w FROM d GROUP BY ALL), c AS (SELECT source, quality, toxic, count(*) AS w FROM d JOIN labels USING (doc_id) GROUP BY ALL), j AS (SELECT lang, source, size, quality, toxic, a.w * b.w * c.w AS w FROM a JOIN b USING (lang) JOIN c USING (source)) {_union(['lang', 'source', 'size', 'quality', 'toxic'], prob=False)}")
def label_marginals(spark, sf_dir):
    return _masses(infer(text.labels(spark, sf_dir), "pairwise").variable_marginals(probs=False))


@query(f"WITH s AS (SELECT lag(role) OVER (PARTITION BY conv_id ORDER BY turn) AS prev_role, role FROM conversations), a AS (SELECT prev_role, role, count(*) AS w FROM s WHERE prev_role IS NOT NULL GROUP BY ALL), b AS (SELECT turn, role, count(*) AS w FROM conversations GROUP BY ALL), j AS (SELECT prev_role, role, turn, a.w * b.w AS w FROM a JOIN b USING (role)) {_union(['prev_role', 'role', 'turn'], prob=False)}")
def role_chain(spark, sf_dir):
    return _masses(infer(text.roles(spark, sf_dir), "pairwise").variable_marginals(probs=False))


@query("SELECT lower(regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1)) AS host, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS lang, count(*) AS mass FROM pages GROUP BY ALL")
def host_lang_factor(spark, sf_dir):
    return text.hosts(spark, sf_dir).factor("host_lang").df.withColumnRenamed(W, "mass")


# batch twins of the streaming factors
@query("SELECT date_trunc('day', ts) AS start, event_type, count(*) AS w FROM events GROUP BY ALL")
def window_count_factor(spark, sf_dir):
    out = stream.window_counts(stream.with_time(table(spark, sf_dir, "events", "ts", "event_type")), ["event_type"], "1 day")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", W)


@query("WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS cut FROM events), s AS (SELECT *, sum(cut) OVER (PARTITION BY user_id ORDER BY ts) AS no FROM g) SELECT user_id, min(ts) AS start, count(*) AS w FROM s GROUP BY user_id, no")
def session_count_factor(spark, sf_dir):
    out = stream.window_counts(stream.with_time(table(spark, sf_dir, "events", "ts", "user_id")), ["user_id"], gap="6 hours")
    return out.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), W)
