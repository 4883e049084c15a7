"""Exactness and size: what only shows on larger or finer data than the fixtures have."""

import datetime
import random

import numpy as np
from pyspark.sql import functions as F

from bagjoin import queries
from bagjoin.model import Factor, Network
from bagjoin.networks import grid
from bagjoin.operators import batch, masks, summed
from bagjoin.operators import relational as rel
from bagjoin.operators.grid import LocalTrie, join_tries, join_tries_batched
from bagjoin.operators.infer import InferConfig, infer, message_up
from bagjoin.operators.product import bag_product, pairwise_product, split_triangle
from bagjoin.plans import strategy as st
from bagjoin.plans.decomposition import decompose
from bagjoin.queries import QUERIES


def test_cooccurrence_is_compared_to_the_microsecond(spark):
    day = datetime.datetime(1969, 12, 31, 23, 59, 59)
    at = [datetime.timedelta(microseconds=x) for x in (0, 400, 3_600_000_000, 3_600_000_401, 9_000_000_000, 9_000_000_000)]
    rows = [(1, day + t, str(i)) for i, t in enumerate(at)]
    df = spark.createDataFrame(rows, "k long, ts timestamp_ntz, v string")
    got = {(r.a, r.b) for r in Factor.cooccur("c", df, "k", "ts", "v", 3600).df.collect()}
    assert got == {(str(i), str(j)) for i, x in enumerate(at) for j, y in enumerate(at) if x < y <= x + datetime.timedelta(hours=1)}


def test_quotient_keeps_integers_beyond_a_double(spark):
    big = 3_037_000_493
    ab = Factor("ab", ("a", "b"), spark.createDataFrame([(0, 0, big), (1, 0, 7), (1, 1, 3)], "a long, b long, w long"))
    bc = Factor("bc", ("b", "c"), spark.createDataFrame([(0, 0, big), (1, 0, 5), (1, 1, 1)], "b long, c long, w long"))
    mass = {("a", "0"): big * big, ("a", "1"): 7 * big + 18, ("b", "0"): big * big + 7 * big, ("b", "1"): 18, ("c", "0"): big * big + 7 * big + 15, ("c", "1"): 3}
    for down in ("hash", "merge"):
        m = infer(Network.of([ab, bc]), "pairwise", config=InferConfig(calibration="quotient", down=down)).variable_marginals(probs=False)
        assert {(r.variable, r.value): r.mass for r in m.collect()} == mass


def test_triangle_with_a_hub_makes_few_rows(spark):
    n, made = 300, []
    rows = [(k, 0, 1 + k % 3) for k in range(n)] + [(0, k, 2) for k in range(1, n)] + [(5, 7, 4), (7, 9, 1), (9, 5, 3)]
    fs = [Factor(x + y, (x, y), rel.materialise(spark.createDataFrame(rows, f"{x} long, {y} long, w long"))) for x, y in ("ab", "bc", "ca")]
    out = split_triangle(("a", "b", "c"), fs)
    assert sorted(map(tuple, out.df.collect())) == sorted(map(tuple, pairwise_product(("a", "b", "c"), fs).df.collect()))
    plan = out.df._jdf.queryExecution()
    plan.executedPlan().execute().count()
    todo = [plan.executedPlan()]
    while todo:
        p = todo.pop()
        kind = p.getClass().getSimpleName()
        if "Join" in kind or "NestedLoop" in kind:
            made.append(p.metrics().apply("numOutputRows").value())
        todo += [p.executedPlan()] if kind == "AdaptiveSparkPlanExec" else [p.plan()] if kind.endswith("QueryStageExec") else [p.children().apply(i) for i in range(p.children().size())]
    assert made and max(made) <= 20 * len(rows)


def test_level_of_a_large_bag_goes_in_shards(spark):
    ab = Factor("ab", ("a", "b"), spark.range(6000).select((F.col("id") % 2000).alias("a"), F.col("id").alias("b"), (F.col("id") % 5 + 1).alias("w")))
    bc = Factor("bc", ("b", "c"), spark.range(6000).select(F.col("id").alias("b"), (F.col("id") % 7).alias("c"), F.lit(2).cast("bigint").alias("w")))
    ids = range(6000)
    want = {(0, str(a)): sum(i % 5 + 1 for i in ids if i % 2000 == a) for a in range(2000)} | {(1, str(c)): sum(2 * (i % 5 + 1) for i in ids if i % 7 == c) for c in range(7)}
    got = {(r.bag, r.vals[0]): r.w for r in batch.run_level({0: [ab], 1: [ab, bc]}, {0: ("a",), 1: ("c",)}).collect()}
    assert got == want
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:  # a bag is not held by one task
        out = batch.run_level({0: [ab]}, {0: ("a",)})
        assert out.select(F.spark_partition_id()).distinct().count() == 4 and out.count() == 2000
    finally:
        spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")


def test_clique_counted_in_bits(spark):
    import itertools
    import random

    rng, vars = random.Random(3), tuple("abcdef")
    held = {p: {(x, y) for x in range(6) for y in range(6) if rng.random() < 0.6} | {(62, 62)} for p in itertools.combinations(vars, 2)}
    fs = [Factor("".join(p), p, spark.createDataFrame([(x, y, 1) for x, y in sorted(rows)], f"{p[0]} long, {p[1]} long, w long")) for p, rows in held.items()]
    mass = {}
    for row in [*itertools.product(range(6), repeat=6), (62,) * 6]:
        if all((row[vars.index(x)], row[vars.index(y)]) in rows for (x, y), rows in held.items()):
            for v, x in zip(vars, row):
                mass[v, str(x)] = mass.get((v, str(x)), 0) + 1
    for lead in (2, 4):
        assert {(r.variable, r.value): r.mass for r in masks.clique_marginals(vars, fs, lead).collect()} == mass


def test_bands_and_ratios_follow_the_embeddings(spark, tmp_path):
    rows = [(i, [0.3 + 0.01 * (i % 2)] * 64, 0) for i in range(4)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    assert set(grid.measured_sizes(spark, str(tmp_path), 28, 28, wide_factor=True).values()) == {1}
    assert {r.max_factor for r in QUERIES["network_band"](spark, str(tmp_path)).collect()} == {1}
    assert {(r.log10_r_d, r.within_two) for r in QUERIES["published_ratio_check"](spark, str(tmp_path)).collect()} == {(0.0, True)}


def test_down_message_looks_in_the_bag_only_for_pairs_without_an_order(spark, tmp_path, monkeypatch):
    def write(orders, lines):
        spark.createDataFrame(orders, "o_orderkey long, o_custkey long").write.mode("overwrite").parquet(f"{tmp_path}/orders.parquet")
        spark.createDataFrame(lines, "l_orderkey long, l_partkey long, l_suppkey long, l_returnflag string").write.mode("overwrite").parquet(f"{tmp_path}/lineitem.parquet")
        for t in ("customer", "part", "supplier"):
            spark.range(9).write.mode("overwrite").parquet(f"{tmp_path}/{t}.parquet")

    def ask():
        return {tuple(r) for r in QUERIES["lookahead_down_message"](spark, str(tmp_path)).collect()}

    # order 9 is missing: (1, 2) is customer 7's by two other lines, nobody has (3, 2); order 4 has no customer
    write([(1, 7), (2, 7), (3, 8), (4, None)], [(1, 1, 1, "A"), (2, 2, 2, "A"), (9, 1, 2, "N"), (9, 1, 2, "A"), (3, 3, 3, "A"), (9, 3, 2, "R"), (4, 5, 5, "A")])
    assert ask() == {(1, 1, 1), (2, 2, 1), (1, 2, 2), (3, 3, 1)}
    write([(1, 7), (2, 7)], [(1, 1, 1, "A"), (1, 1, 1, "R"), (2, 2, 2, "A")])
    for name in ("pairwise_product", "extend_product"):
        monkeypatch.setattr(queries, name, None)  # no bag is made
    assert ask() == {(1, 1, 2), (2, 2, 1)}


def test_batched_join_of_tries():
    rng = np.random.default_rng(5)
    order, scopes = ["a", "b", "c", "d"], [("a", "b"), ("b", "c"), ("a", "c"), ("b", "c", "d"), ("d",)]
    tries = []
    for s in scopes:
        rows = np.unique(rng.integers(-9, 9, (150, len(s))), axis=0)
        tries.append(LocalTrie(list(rows.T), rng.integers(1, 5, len(rows))))
    want = dict(join_tries(order, scopes, tries))
    for rows in (1, 50, 1 << 18):
        got = {}
        for key, w in join_tries_batched(order, scopes, tries, rows):
            got |= zip(map(tuple, np.stack(key, 1).tolist()), w.tolist())
        assert got == want and want


def test_up_message_does_not_shuffle_the_bag(spark):
    people, each = 40, 100  # a bag of 400,000 rows over 8,000 rows of factors
    rows = spark.range(people * each).select((F.col("id") % people).alias("c"), F.xxhash64("id").alias("v"), (F.col("id") % 3 + 1).alias("w"))
    cp = Factor("cp", ("c", "p"), rel.materialise(rows.select("c", F.pmod("v", F.lit(90_000)).alias("p"), "w").dropDuplicates(["c", "p"])))
    cs = Factor("cs", ("c", "s"), rel.materialise(rows.select("c", F.pmod("v", F.lit(70_001)).alias("s"), "w").dropDuplicates(["c", "s"])))
    psf = Factor("psf", ("p", "s", "f"), spark.createDataFrame([(1, 1, 1, 1)], "p long, s long, f long, w long"))
    n = Network.of([cp, cs, psf])
    dec = decompose(n, root=decompose(n).bag_of(("f",)))
    _, up, _ = message_up(dec, st.fixed(dec, st.PLAIN), InferConfig(materialise="lazy"))
    (m,) = up.values()
    moved, plan = 0, m.df._jdf.queryExecution().executedPlan()
    rows_out = plan.execute().count()
    todo = [plan]
    while todo:
        p = todo.pop()
        kind = p.getClass().getSimpleName()
        if kind == "ShuffleExchangeExec":
            moved += p.metrics().apply("shuffleRecordsWritten").value()
        todo += [p.executedPlan()] if kind == "AdaptiveSparkPlanExec" else [p.plan()] if kind.endswith("QueryStageExec") else [p.children().apply(i) for i in range(p.children().size())]
    assert rows_out > 300_000 and moved <= 8_000
    want = cp.df.withColumnRenamed("w", "u").join(cs.df, "c").groupBy("p", "s").agg(F.sum(F.col("u") * F.col("w")).alias("w"))
    assert m.df.select("p", "s", "w").exceptAll(want).isEmpty() and want.exceptAll(m.df.select("p", "s", "w")).isEmpty()


def test_sum_of_a_product_with_nulls_and_wide_values(spark):
    rng, top = random.Random(8), (1 << 63) - 1
    xs, ys, js = [None, 0, -top - 1, top, 5, -7, 6], [None, 3, -4, 1 << 40, -top, top], [None, 1, 2, 3, 4]
    for heavy in (1, 3, 1 << 30):
        a, b = ({(j, v): rng.randint(1, heavy) for j in js for v in vs if rng.random() < 0.7} for vs in (xs, ys))
        want: dict = {}
        for (j, x), w in a.items():
            for (i, y), u in b.items():
                if i == j and j is not None:
                    want[x, y] = want.get((x, y), 0) + w * u
        fa = Factor("a", ("j", "x"), spark.createDataFrame([(*k, w) for k, w in a.items()], "j int, x long, w long"))
        fb = Factor("b", ("y", "j"), spark.createDataFrame([(y, j, w) for (j, y), w in b.items()], "y long, j int, w long"))
        for factors in ([fa, fb], [fb, fa]):
            _, out = bag_product(("j", "x", "y"), factors, ("x", "y"))
            assert out.df.dtypes == [("x", "bigint"), ("y", "bigint"), ("w", "bigint")]
            assert {(r.x, r.y): r.w for r in out.df.collect()} == want and out.df.count() == len(want)
    none = Factor("b", ("y", "j"), fb.df.filter("j > 9"))
    assert bag_product(("j", "x", "y"), [fa, none], ("x", "y"))[1].df.isEmpty()


def test_cells_are_summed_in_pieces():
    rng = np.random.default_rng(4)
    for top in (1, 9, 1 << 31):
        lists, want = [], {}
        for _ in range(3):
            na, nb = rng.integers(1, 30, 20), rng.integers(1, 30, 20)
            va, vb = np.where(rng.random(na.sum()) < 0.4, 7, rng.integers(-50, 50, na.sum())), rng.integers(-9, 9, nb.sum())  # 7 is heavy
            wa, wb = rng.integers(1, top, na.sum(), endpoint=True), rng.integers(1, min(top, 99), nb.sum(), endpoint=True)
            step = np.concatenate([np.diff(v, prepend=0) for v in np.split(vb, np.cumsum(nb)[:-1])])
            lists.append(b"".join(map(summed.pack, (na, va, np.zeros_like(va), wa, nb, step, np.zeros_like(vb), wb))))
            for x, u, y, w in zip(*(np.split(v, np.cumsum(n)[:-1]) for v, n in ((va, na), (wa, na), (vb, nb), (wb, nb)))):
                for i, p in enumerate(x.tolist()):
                    for k, q in enumerate(y.tolist()):
                        want[p, q] = want.get((p, q), 0) + int(u[i]) * int(w[k])
        for rows in (1, 100, 1 << 19):
            found = [z for x, _, y, _, w in summed.sums_of_cell(lists, rows) for z in zip(x.tolist(), y.tolist(), w.tolist())]
            assert len(found) == len(want) and {(x, y): w for x, y, w in found} == want
