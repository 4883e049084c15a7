"""The marginal engine: worked examples, brute force, baselines, measures."""

import itertools
import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from bagjoin import published
from bagjoin.baselines.brute import brute_force
from bagjoin.baselines.circuit import compile_circuit
from bagjoin.baselines.dense import DenseLimitError, dense_junction_tree
from bagjoin.baselines.join_graph import join_graph_propagation
from bagjoin.functions import discretise, index
from bagjoin.functions.semiring import BOOLEAN, MAX_PRODUCT
from bagjoin.model import Domain, Factor, FactorError, InconsistentEvidence, Network
from bagjoin.networks import events, grid, supply, toy
from bagjoin.operators import relational as rel
from bagjoin.operators.batch import BatchLimitError, solve_trees
from bagjoin.operators.grid import LocalTrie, NestedTrie, agree, gallop, is_cyclic, join_tries, shares
from bagjoin.operators.infer import InferConfig, compare_marginals, infer, marginal
from bagjoin.operators.preprocess import apply_evidence, singleton_consistency
from bagjoin.operators.product import extend_product, multiway_product, pairwise_product
from bagjoin.operators.projections import ProjectionPolicy, indicator
from bagjoin.operators.trie import level_order_trie, trie_from_index
from bagjoin.plans import measures
from bagjoin.plans import strategy as st
from bagjoin.plans.cover import fractional_cover, integral_cover
from bagjoin.plans.decomposition import bags_of, decompose, min_fill_order

ALL = ProjectionPolicy(1.0, 1)


def meta(scopes, domain, size):
    fs = [Factor(f"f{i}", tuple(s), None) for i, s in enumerate(scopes)]
    return Network(tuple(fs), {v: domain for s in scopes for v in s}, {f.name: size for f in fs})


def made(spark, scopes, d, density, seed, kind="long"):
    r = random.Random(seed)
    tables = [{k: r.randrange(1, 5) for k in itertools.product(range(d), repeat=len(s)) if r.random() < density} for s in scopes]
    for s, t in zip(scopes, tables):
        t.setdefault((0,) * len(s), 1)
    fs = [Factor(f"f{i}", tuple(s), spark.createDataFrame([(*k, w) for k, w in t.items()], ", ".join(f"{v} long" for v in s) + f", w {kind}")) for i, (s, t) in enumerate(zip(scopes, tables))]
    return Network.of(fs), tables


def brute(scopes, tables, d):
    vars = sorted({v for s in scopes for v in s})
    mass, joint = {}, {}
    for k in itertools.product(range(d), repeat=len(vars)):
        e = dict(zip(vars, k))
        w = math.prod(t.get(tuple(e[v] for v in s), 0) for s, t in zip(scopes, tables))
        if w:
            joint[k] = w
            for v in vars:
                mass[v, str(e[v])] = mass.get((v, str(e[v])), 0) + w
    return mass, joint


SCOPES = [("a", "b"), ("a", "c"), ("b", "c", "d"), ("d", "e")]


def got(df):
    return {(x.variable, x.value): x.mass for x in df.collect()}


# planning
def test_triangle_and_lookahead_widths():
    tri = decompose(meta(["AB", "BC", "CA"], 10, 10)).check()
    assert (measures.fhtw(tri), measures.htw(tri), measures.tw(tri), measures.tw(tri, "minus_one")) == (1.5, 2, 3, 2)
    assert math.isclose(2 ** measures.agm(tri, 0), 10**1.5)
    ex = decompose(meta(["AB", "AC", "BCD"], 10, 10)).check()
    assert sorted(map(len, ex.chi)) == [3, 3] and (measures.fhtw(ex), measures.htw(ex)) == (1.5, 2)
    value, share = fractional_cover("ABC", {"f0": ("AB", 1.0), "f1": ("AC", 1.0), "f2": ("BCD", 1.0)})
    assert value == 1.5 and all(math.isclose(x, 0.5) for x in share.values())
    assert fractional_cover("ABC", {"f0": ("AB", 1.0), "f1": ("AC", 1.0)})[0] == 2.0
    k = decompose(meta([a + b for a, b in itertools.combinations("ABCDEFGH", 2)], 20, 79))
    assert measures.fhtw(k) == 4.0 and measures.band(k) == 1
    assert integral_cover("ABCD", [("A", "B"), ("B", "C"), ("C", "D")]) == 2
    star = decompose(meta([("h", x) for x in "abcde"], 5, 25))
    assert measures.fhtw(star) == 1.0 and measures.tw(star) == 2


def test_random_decompositions_hold():
    r = random.Random(1)
    for _ in range(30):
        vs = "abcdefghij"
        scopes = [tuple(r.sample(vs, r.randrange(1, 4))) for _ in range(r.randrange(1, 12))]
        for cost in ("min_fill", "min_degree"):
            dec = decompose(meta(scopes, 3, 9), cost=cost).check()
            for root in ("largest", "centre", 0):
                dec.rooted(root).check()
            assert sum(map(len, dec.levels)) == len(dec.chi)
    assert min_fill_order(SCOPES) == min_fill_order(list(reversed(SCOPES)))
    assert bags_of([("x",)], ["x"]) == [frozenset("x")]


def test_published_rows():
    near = 0
    for _, band, n, d, width, bag, r_d in published.ROWS:
        x = measures.ratio(n, d, width, bag)
        near += abs(x - math.log10(r_d)) <= math.log10(2)
        assert measures.band_of(1e10 if band <= 3 else 1e6, math.log10(r_d)) == band
    assert near == len(published.ROWS) - len(published.ROUNDED_OTHERWISE) == 48
    assert measures.predicted_winner(4) == "multiway" and measures.predicted_winner(5) == "dense"


def test_grid_measures():
    p = measures.profile(decompose(grid.metadata(8, 8, full_every=1)))
    assert (p["max_bag"], p["fhtw"], p["band"]) == (11, 9.0, 5)
    wide = measures.profile(decompose(grid.metadata(28, 28, wide_factor=True)))
    plain = measures.profile(decompose(grid.metadata(28, 28)))
    assert (plain["band"], wide["band"]) == (2, 3) and math.isclose(plain["log10_r_j"], wide["log10_r_j"], abs_tol=0.2)


# products
def test_products_agree(spark):
    for scopes, density in ((SCOPES, 0.6), ([("a", "b"), ("c", "d"), ("b",)], 0.8), ([("a", "b"), ("b", "c"), ("c", "a")], 0.4)):
        n, tables = made(spark, scopes, 3, density, 5)
        vars = tuple(sorted({v for s in scopes for v in s}))
        joint = brute(scopes, tables, 3)[1]
        for f in (pairwise_product(vars, list(n.factors), "greedy"), extend_product(vars, list(n.factors)), multiway_product(vars, list(n.factors), impl="grid", cells=6), multiway_product(vars, list(n.factors), free=vars[-1:], order="free_first", impl="extend")):
            assert {tuple(x[:-1]): x.w for x in f.df.collect()} == joint


def test_hub_candidates_stay_linear(spark, sf):
    n = supply.hub(spark, sf)
    parts = spark.read.parquet(f"{sf}/part.parquet").count()
    steps = {}

    def see(v, df):
        steps[v] = df.count()
        return df

    f = extend_product(("a", "b", "c"), list(n.factors), observe=see)
    assert f.df.count() == 3 * parts - 2
    assert max(steps.values()) <= 4 * parts
    assert rel.multiply(n.factors[0], n.factors[1]).df.count() == parts**2 + parts - 1


def test_extension_has_no_python_and_grid_shuffles_once(spark, sf):
    n = supply.hub(spark, sf)
    plan = extend_product(("a", "b", "c"), list(n.factors)).df._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan
    fs = [Factor(f.name, f.vars, rel.materialise(f.df)) for f in n.factors]
    g = multiway_product(("a", "b", "c"), fs, impl="grid").df._jdf.queryExecution().executedPlan().toString()
    assert g.count("Exchange hashpartitioning") == 1


def test_local_join_pieces():
    run = np.array([1, 3, 4, 7, 9])
    assert gallop(run, 0, 5, 5) == 3 and gallop(run, 0, 5, 10) == 5 and gallop(run, 2, 5, 0) == 2
    runs = [run, np.array([2, 3, 7, 8]), np.array([3, 5, 7])]
    assert [v for v, _ in agree(runs, [(0, len(x)) for x in runs])] == [3, 7]
    assert is_cyclic(["ab", "bc", "ca"]) and not is_cyclic(["ab", "bc", "bcd"])
    assert math.prod(shares(("a", "b", "c"), [(("a", "b"), 100), (("b", "c"), 100), (("c", "a"), 100)], 8).values()) <= 8
    cols = [np.array([2, 1, 1, 2]), np.array([5, 6, 5, 5])]
    t = LocalTrie([c[:3] for c in cols], np.array([1.0, 2.0, 3.0]))
    assert [v.tolist() for v in t.values] == [[1, 2], [5, 6, 5]] and t.below(0, 0) == (0, 2)
    rows = list(NestedTrie([c[:3] for c in cols], np.array([1.0, 2.0, 3.0])).rows())
    assert rows == [(1, 5, 3.0), (1, 6, 2.0), (2, 5, 1.0)]
    assert [(k, w) for k, w in join_tries(["a", "b"], [("a", "b")], [t])] == [((1, 5), 3.0), ((1, 6), 2.0), ((2, 5), 1.0)]
    assert list(join_tries(["a"], [("a",)], [LocalTrie([np.zeros(0, np.int64)], np.zeros(0))])) == []


def test_cross_products_are_checked(spark):
    a = Factor("a", ("x",), spark.range(100).select(F.col("id").alias("x"), F.lit(1).alias("w")))
    b = Factor("b", ("y",), spark.range(100).select(F.col("id").alias("y"), F.lit(1).alias("w")))
    assert rel.multiply(a, b).df.count() == 10_000
    with pytest.raises(rel.CrossProductError):
        rel.multiply(a, b, cross_limit=9_999)


# inference
@pytest.mark.parametrize("strategy", ["multiway", "multiway_proj", "pairwise", "hybrid"])
def test_strategies_and_calibrations(spark, strategy):
    n, tables = made(spark, SCOPES, 3, 0.7, 7)
    mass, joint = brute(SCOPES, tables, 3)
    for cal in ("product", "quotient"):
        c = infer(n, strategy, config=InferConfig(calibration=cal, policy=ALL))
        m = got(c.variable_marginals())
        assert set(m) == set(mass) and all(math.isclose(m[k], mass[k], rel_tol=1e-9) for k in mass)
        assert c.partition_function().first().z == sum(joint.values())
        for b, p in enumerate(c.dec.parent):  # both ends of an edge agree on its separator
            if p >= 0:
                sep = c.dec.separator(b)
                x, y = ({tuple(r[:-1]): r.w for r in c.products[i].onto(sep).df.collect()} for i in (b, p))
                assert set(x) == set(y) and all(math.isclose(x[k], y[k], rel_tol=1e-9) for k in x)


def test_layouts_semirings_and_forests(spark):
    scopes = [("a", "b"), ("b", "c"), ("x", "y")]
    n, tables = made(spark, scopes, 3, 0.6, 9)
    mass, joint = brute(scopes, tables, 3)
    assert got(infer(n, "pairwise", config=InferConfig(layout="forward_list")).variable_marginals()) == mass
    c = infer(n, "pairwise", config=InferConfig(scaled=True))
    assert math.isclose(c.log_z(), math.log(sum(joint.values())))
    best = got(infer(n, "pairwise", config=InferConfig(semiring=MAX_PRODUCT)).variable_marginals(probs=False))
    vars = sorted({v for s in scopes for v in s})
    for (v, x), m in best.items():
        assert m == max(w for k, w in joint.items() if str(k[vars.index(v)]) == x)
    with pytest.raises(ValueError):
        infer(n, "pairwise", config=InferConfig(semiring=BOOLEAN, calibration="quotient"))


def test_joint_of_distant_variables_and_evidence(spark):
    n, tables = made(spark, SCOPES, 3, 0.8, 11)
    _, joint = brute(SCOPES, tables, 3)
    want = {}
    for k, w in joint.items():
        want[k[0], k[4]] = want.get((k[0], k[4]), 0) + w
    assert {(x.a, x.e): x.mass for x in marginal(n, ("a", "e"), strategy="pairwise").collect()} == want
    m = got(infer(n, "pairwise", evidence={"b": 0, "a": 0}).variable_marginals())
    for (v, x), w in m.items():
        i = "abcde".index(v)
        assert w == sum(y for k, y in joint.items() if k[0] == 0 and k[1] == 0 and str(k[i]) == x)
    with pytest.raises(KeyError):
        apply_evidence(n, {"nope": 1})
    with pytest.raises(InconsistentEvidence):
        infer(n, "pairwise", evidence={"a": 99, "b": 0})


def test_baselines_agree(spark):
    n, tables = made(spark, SCOPES, 3, 0.7, 13)
    exact = brute_force(n)
    for other in (dense_junction_tree(n), compile_circuit(n).evaluate()[0], join_graph_propagation(n, 5)[0], solve_trees(n).filter("variable is not null")):
        assert compare_marginals(exact, other)[1]
    df, is_exact = join_graph_propagation(n, 2, iterations=2)
    assert not is_exact and df.count() > 0
    with pytest.raises(DenseLimitError):
        dense_junction_tree(n, max_cells=10)
    with pytest.raises(BatchLimitError):
        solve_trees(n, budget=1.0)
    c = compile_circuit(n)
    some, z = c.evaluate({"a": 0})
    again = infer(n, "pairwise", evidence={"a": 0})
    assert compare_marginals(some.filter("variable <> 'a'"), again.variable_marginals())[1]
    assert math.isclose(z.first().z, again.partition_function().first().z)


def test_dense_engine_refuses_the_large_lookahead():
    n = Network(tuple(Factor(k, v, None) for k, v in (("cp", ("c", "p")), ("cs", ("c", "s")), ("psf", ("p", "s", "f")))), {"c": 15000, "p": 20000, "s": 1000, "f": 3}, {"cp": 599_351, "cs": 586_871, "psf": 597_042})
    dec = decompose(n)
    assert measures.rho(dec) > 1e9 and measures.band(dec) == 1
    with pytest.raises(DenseLimitError):
        dense_junction_tree(n)


def test_golden_values(spark, sf):
    n = supply.lookahead(spark, sf)
    own = [n.factor("cust_part"), n.factor("cust_supp")]
    vars = ("o_custkey", "l_partkey", "l_suppkey")
    assert pairwise_product(vars, own).df.count() == 52_769
    assert extend_product(vars, [*own, indicator(n.factor("part_supp_flag"), vars)]).df.count() == 50_463
    c = infer(n, "multiway_proj", config=InferConfig(policy=ALL))
    assert c.partition_function().first().z == 852_474
    assert {r.l_returnflag: r.mass for r in c.marginal(["l_returnflag"]).collect()} == {"A": 277_476, "N": 295_521, "R": 279_477}
    t = infer(toy.network(spark, sf), "hybrid")
    assert t.partition_function().first().z == 666_060
    assert all(r.rows <= r.agm * (1 + 1e-9) and r.rows <= r.cells for r in infer(toy.network(spark, sf), "multiway").explain_bags().collect())


def test_thinned_grid_has_two_solutions(spark, sf):
    n, templates = grid.network(spark, sf, 6, 6)
    m = {}
    for r in solve_trees(n, templates).filter("variable is not null").collect():
        m.setdefault(r.variable, []).append(r.prob)
    assert len(m) == 36 and all(math.isclose(sum(p), 1) for p in m.values())
    assert max(abs(max(p) - max(m["v00_00"])) for p in m.values()) < 1e-9


def test_long_chain_runs_as_one_job(spark, sf):
    n, templates = events.chain(spark, sf, slices=120)
    rows = solve_trees(n, templates).collect()
    assert len({r.variable for r in rows if r.variable}) == 240


# strategy choice
def test_strategy_choice_with_a_fake_clock(spark):
    n, _ = made(spark, [("a", "b"), ("b", "c"), ("c", "d"), ("d", "e")], 2, 1.0, 3)
    dec = decompose(n)
    ticks = iter(itertools.accumulate(itertools.cycle([0, 5, 0, 1, 0, 9])))
    out = st.choose_strategies(dec, "timed", clock=lambda: next(ticks), run=lambda df: None)
    assert {c.strategy for c in out.values()} == {st.PROJECTED} and all(c.costs for c in out.values())
    rnd = st.choose_strategies(dec, "timed", rho_limit=1, seed=4)
    assert {c.strategy for c in rnd.values()} <= {0, 1} and all(c.why == "random" for c in rnd.values())
    assert st.choose_strategies(dec) == st.choose_strategies(dec)


def test_choice_spreads_to_bags_without_factors():
    from bagjoin.plans.decomposition import Decomposition

    n = Network((Factor("f", ("a", "b"), None),), {v: 3 for v in "abcd"}, {"f": 9})
    dec = Decomposition([("a", "b"), ("b", "c"), ("c", "d")], [-1, 0, 1], [("f",), (), ()], [("f",), (), ()], n)
    out = st._decide(dec, lambda b: (3.0, 2.0, 1.0))
    assert [out[b].strategy for b in range(3)] == [2, 2, 2] and out[2].inherited_from == 0
    dec = Decomposition(dec.chi, dec.parent, [(), ("f",), ()], dec.lam, n)
    out = st._decide(dec, lambda b: (0.0, 2.0, 1.0) if b == 1 else (9.0, 9.0, 0.0))
    assert [out[b].strategy for b in range(3)] == [2, 0, 0] and out[0].why == "root"


# encodings and helpers
def test_indices(spark):
    df = spark.createDataFrame([(1, 2, 4), (1, 0, 2)], "a long, b long, c long")
    sizes = [2, 3, 5]
    x = df.select("*", index.forward_index(["a", "b", "c"], sizes).alias("f"), index.reverse_index(["a", "b", "c"], sizes).alias("r")).collect()
    assert [(r.f, r.r) for r in x] == [(29, 29), (17, 13)]
    y = df.select(index.forward_index(["a", "b", "c"], sizes).alias("i")).select(*index.decode_index("i", sizes), index.reindex("i", sizes)).collect()
    assert [tuple(r) for r in y] == [(1, 2, 4, 29), (1, 0, 2, 13)]
    assert index.check_width([2] * 62) == "bigint" and index.check_width([2] * 64, wide=True) == "decimal(38,0)"
    with pytest.raises(index.IndexWidthError):
        index.check_width([2] * 64)
    index.register(spark)
    r = spark.sql("SELECT fwd_index(array(1L, 0L, 2L), array(2L, 3L, 5L)) AS f, rev_index(array(1L, 0L, 2L), array(2L, 3L, 5L)) AS r").first()
    assert (r.f, r.r) == (17, 13)


def test_tries(spark):
    rng = random.Random(2)
    rows = sorted({(rng.randrange(3), rng.randrange(4), rng.randrange(5)) for _ in range(25)})
    f = Factor("f", ("a", "b", "c"), spark.createDataFrame([(*r, 1) for r in rows], "a long, b long, c long, w long"))
    levels = {(r.level, r.pos): r for r in level_order_trie(f).collect()}
    back = []
    for (lv, pos), r in levels.items():
        if lv == 2:
            up = levels[1, r.parent_pos]
            back.append((int(levels[0, up.parent_pos].value), int(up.value), int(r.value)))
    assert sorted(back) == rows
    sizes = [3, 4, 5]
    fwd = np.array([(a * 4 + b) * 5 + c for a, b, c in rows])
    rev = np.array([(c * 4 + b) * 3 + a for a, b, c in rows])
    x, y = trie_from_index(fwd, np.ones(len(rows)), sizes, "forward"), trie_from_index(rev, np.ones(len(rows)), sizes, "reverse")
    assert all((a == b).all() for a, b in zip(x.values, y.values)) and all((a == b).all() for a, b in zip(x.child, y.child))


def test_factor_checks(spark):
    bad = spark.createDataFrame([(1, 1.0), (None, 1.0), (2, -1.0), (1, 2.0)], "a int, x double")
    with pytest.raises(FactorError):
        Factor("f", ("a",), bad.withColumnRenamed("x", "w")).check()
    assert Factor.listing("f", bad, ("a",), "x", null_policy="drop").check().df.collect() == [(1, 3.0)]
    assert {r.a for r in Factor.listing("f", bad, ("a",), "x", null_policy="as_value").df.collect()} == {"1", "unknown"}
    d = Domain.fit(bad.dropna(), "a")
    assert d.decode(d.encode(bad.dropna())).count() == 3
    c = Factor.conditional("c", spark.createDataFrame([("x", 1), ("x", 2), ("y", 1)], "p string, q int"), "q", ("p",), smoothing=1.0).df
    assert math.isclose(c.agg(F.sum("w")).first()[0], 2.0) and c.count() == 4
    u = Network.of([Factor.counts("f", bad.dropna(), ("a",))], uncovered={"z": spark.createDataFrame([(7,), (8,)], "z int")})
    assert u.domains["z"] == 2
    t = spark.createDataFrame([(0, 1), (1, 1), (2, 0)], "i long, j long")
    s = Factor.counts("s", t, ("i", "j")).induce_sparsity(0, 1, {"i": [0, 1, 2], "j": [0, 1]}).df
    assert {(r.i, r.j) for r in s.collect()} == {(0, 0), (1, 1)}


def test_singleton_modes(spark):
    a = Factor("a", ("x", "y"), spark.createDataFrame([(1, 1, 1), (1, 2, 1)], "x long, y long, w long"))
    b = Factor("b", ("y", "z"), spark.createDataFrame([(2, 5, 1), (3, 6, 1)], "y long, z long, w long"))
    for mode in ("arc", "exact"):
        _, found = singleton_consistency(Network.of([a, b]), mode)
        assert found == {"x": 1, "y": 2, "z": 5}
    with pytest.raises(InconsistentEvidence):
        singleton_consistency(Network.of([a, Factor("b", ("y", "z"), b.df.filter("y = 3"))]))


def test_discretising(spark):
    df = spark.range(100).withColumn("x", F.col("id") / 10.0)
    assert df.select(discretise.bin_width("x", 0, 2.5)).distinct().count() == 4
    assert discretise.bin_ntile(df, "x", 4, "q").groupBy("q").count().count() == 4
    a, b = (discretise.sample_by_key(spark.range(1000).selectExpr("id AS k", "id % 7 AS v"), ["k"], 0.3, 1) for _ in range(2))
    assert a.join(b, "k").count() == a.count() and 200 < a.count() < 400


def test_pushdown_and_pruning(spark, sf):
    f = toy.network(spark, sf).factor("nation_prio_status").where("o_orderstatus", "F")
    plan = f.df._jdf.queryExecution().executedPlan().toString()
    assert "EqualTo(o_orderstatus,F)" in plan and "o_totalprice" not in plan


def test_partition_counts_do_not_matter(spark, sf):
    old = spark.conf.get("spark.sql.shuffle.partitions")
    seen = set()
    try:
        for n in ("1", "7"):
            spark.conf.set("spark.sql.shuffle.partitions", n)
            seen.add(tuple(sorted(got(infer(toy.network(spark, sf), "multiway").variable_marginals()).items())))
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", old)
    assert len(seen) == 1


def test_variables_in_very_many_bags_still_give_a_junction_tree():
    """Scopes (m, n, x), two shared variables in each of 1350 bags."""
    from bagjoin.plans.decomposition import bag_tree, decompose, min_fill_order

    scopes = [s for i in range(450) for s in (("m", "n", f"x{i}"), ("m", f"x{i}", f"y{i}"), ("n", f"x{i}", f"z{i}"))]
    bags, parent = bag_tree(scopes, min_fill_order(scopes))
    assert len(bags) == 1350 and sum(p < 0 for p in parent) == 1
    assert sum(len(bags[b] & bags[p]) for b, p in enumerate(parent) if p >= 0) == 1349 * 2
    for v in {v for s in scopes for v in s}:
        assert sum(v in bags[b] and (p < 0 or v not in bags[p]) for b, p in enumerate(parent)) == 1
    r = random.Random(5)
    for _ in range(40):
        some = [tuple(r.sample("abcdefghij", r.randrange(1, 4))) for _ in range(r.randrange(1, 9))]
        bags, parent = bag_tree(some, min_fill_order(some))
        assert all(any(set(s) <= b for b in bags) for s in some)
        assert not any(a < b or a == b and i != j for i, a in enumerate(bags) for j, b in enumerate(bags))
        for v in {v for s in some for v in s}:
            assert sum(v in bags[b] and (p < 0 or v not in bags[p]) for b, p in enumerate(parent)) == 1


def test_small_tree_guard_counts_rows_whatever_the_number_of_bags(spark):
    from bagjoin.operators.local import Listing, RowLimitError, calibrate, times

    wide = Listing(("a", "b"), np.array([[0, i] for i in range(100)]), np.ones(100))
    other = Listing(("a", "c"), np.array([[0, i] for i in range(100)]), np.ones(100))
    assert len(times(wide, other, 10_000).w) == 10_000
    with pytest.raises(RowLimitError):
        times(wide, other, 9_999)
    with pytest.raises(RowLimitError):
        calibrate([("a", "b"), ("a", "c")], [-1, 0], [[wide], [other]], 0, 150)
    from bagjoin.operators.batch import predicted_rows

    df = spark.createDataFrame([(0, 0, 1.0), (0, 1, 1.0), (1, 0, 1.0)], "a long, b long, w double")
    chain = [Factor(f"f{i}", (f"x{i}", f"x{i + 1}"), df.toDF(f"x{i}", f"x{i + 1}", "w")) for i in range(2)]
    net = Network.of(chain, {f"x{i}": 2 for i in range(3)}, {f"f{i}": 3 for i in range(2)})
    dec = decompose(net)
    assert predicted_rows(dec, list(range(len(dec.chi)))) == 6
    with pytest.raises(BatchLimitError):
        solve_trees(net, dec=dec, budget=2.0)
    assert solve_trees(net, dec=dec, budget=3.0).count() == 7
