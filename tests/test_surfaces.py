"""Sources, formats, SQL, streaming, benchmark runner, driver contract."""

import math

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from bagjoin import sql as front
from bagjoin.bench import run as bench
from bagjoin.model import Factor, Network
from bagjoin.networks import toy
from bagjoin.operators.infer import compare_marginals, infer
from bagjoin.sources import formats, tables
from bagjoin.streaming import factors as stream


def small(spark):
    a = Factor("a", ("x", "y"), spark.createDataFrame([(0, 0, 1.0), (0, 1, 2.0), (1, 1, 0.5)], "x long, y long, w double"))
    b = Factor("b", ("y",), spark.createDataFrame([(0, 3.0), (1, 1.0)], "y long, w double"))
    return Network.of([a, b])


def test_formats_round_trip(spark, tmp_path):
    n = small(spark)
    want = infer(n, "pairwise").variable_marginals()
    for read, write in ((formats.read_uai, formats.write_uai), (formats.read_fg, formats.write_fg)):
        path = f"file://{tmp_path}/{write.__name__}"
        write(n, path)
        back = infer(read(spark, path), "pairwise").variable_marginals().withColumn("variable", F.translate("variable", "x01", "?xy")).withColumn("variable", F.regexp_replace("variable", "\\?", ""))
        assert compare_marginals(want, back)[1]


def test_networks_save_and_load(spark, tmp_path):
    n = small(spark)
    tables.save_network(n, f"file://{tmp_path}/net")
    m = tables.load_network(spark, f"file://{tmp_path}/net")
    assert m.domains == n.domains and compare_marginals(infer(n, "pairwise").variable_marginals(), infer(m, "pairwise").variable_marginals())[1]
    tables.write_marginals(infer(n, "pairwise").variable_marginals(), "parquet", f"file://{tmp_path}/out")
    tables.write_marginals(infer(n, "pairwise").variable_marginals(), "memory", "kept_marginals")
    assert spark.table("kept_marginals").count() == spark.read.parquet(f"file://{tmp_path}/out").count() == 4
    tables.views(n)
    assert spark.table("net_a").count() == 3


def test_sql_front_door(spark, sf):
    front.register(spark)
    front.register_network("toy", toy.network(spark, sf))
    r = front.sql(spark, "MARGINAL c_mktsegment FROM toy WHERE o_orderstatus = 'F' AND c_nationkey = 3")
    assert math.isclose(r.agg(F.sum("prob")).first()[0], 1.0)
    assert front.sql(spark, "SELECT 1 AS one").first().one == 1
    bags = spark.sql("""SELECT * FROM decompose_network('[["a","b"],["b","c"],["c","a"],["c","d"]]')""").collect()
    assert sorted(b.variables for b in bags) == ["a,b,c", "c,d"]
    with pytest.raises(ValueError):
        front.sql(spark, "MARGINAL a FROM toy WHERE a > 3")


def _files(spark, sf, tmp_path, parts=3):
    e = spark.read.parquet(f"{sf}/events.parquet").orderBy("ts", "event_id")
    path = f"{tmp_path}/events"
    rows = e.collect()
    n = -(-len(rows) // parts)
    for i in range(parts):
        spark.createDataFrame(rows[i * n : (i + 1) * n], e.schema).coalesce(1).write.mode("append").parquet(path)
    return path, e


def test_streamed_windows_equal_batch(spark, sf, tmp_path):
    path, e = _files(spark, sf, tmp_path)
    s = stream.dedupe(stream.with_lateness(stream.read_events(spark, path), delay="60 days"))
    q = stream.window_counts(s, ["event_type"], "1 day").writeStream.format("memory").queryName("win").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(120)
    want = stream.window_counts(stream.with_time(e), ["event_type"], "1 day")
    assert spark.table("win").exceptAll(want).count() == 0  # windows are final once the watermark has passed them


def test_late_rows_are_dropped(spark, tmp_path):
    path = f"{tmp_path}/late"
    row = lambda t: f"SELECT 1L AS event_id, 1L AS user_id, timestamp_ntz'{t}' AS ts, 'a' AS event_type, 0D AS value, '' AS props"
    for t in ("2024-01-01 00:10:00", "2024-01-09 00:00:00", "2024-01-10 00:00:00", "2024-01-01 00:20:00", "2024-01-20 00:00:00"):
        spark.sql(row(t)).coalesce(1).write.mode("append").parquet(path)
        __import__("time").sleep(1.1)  # files are taken in the order of their times
    s = stream.with_lateness(stream.read_events(spark, path), delay="1 hour")
    q = stream.window_counts(s, ["event_type"], "1 hour").writeStream.format("memory").queryName("late").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert spark.table("late").filter("start = timestamp'2024-01-01 00:00:00'").first().w == 1


def test_stateful_transitions_equal_batch(spark, sf, tmp_path):
    path, e = _files(spark, sf, tmp_path, 2)
    t = stream.transitions(stream.read_events(spark, path))
    q = t.writeStream.format("memory").queryName("trans").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(180)
    want = Factor.transition("t", e, "user_id", ["ts", "event_id"], "event_type").df.collect()
    have = {(r.prev, r.next): r.n for r in spark.table("trans").groupBy("prev", "next").agg(F.count("*").alias("n")).collect()}
    assert sum(have.values()) == sum(r.w for r in want)


def test_recalibration_per_batch(spark, sf, tmp_path):
    path, e = _files(spark, sf, tmp_path, 2)
    base = Factor.counts("type", e.limit(5), ("event_type",))
    n = Network.of([base])
    seen = []
    q = stream.recalibrate(stream.read_events(spark, path).select("event_type"), n, "type", lambda df, i: seen.append({r.value: r.mass for r in df.collect()}), f"{tmp_path}/state").trigger(availableNow=True).start()
    q.awaitTermination(180)
    assert len(seen) == 2 and sum(seen[-1].values()) == e.count() + 5


def test_benchmark_runner(spark, sf):
    r = bench.run(spark, sf, "pairwise", "W3", repeats=1).unionByName(bench.run(spark, sf, "dense", "W3", repeats=1)).unionByName(bench.run(spark, sf, "hybrid", "W18", repeats=1))
    assert {x.status for x in r.collect()} == {"ok"}
    assert bench.compare(r, "dense").filter("engine = 'pairwise'").first().speed_up > 0
    cal = infer(toy.network(spark, sf), "pairwise")
    assert bench.memory(cal).count() == 2 and bench.storage_profile(cal.dec.network).count() == 3


def test_driver_contract(spark):
    assert entry.entry(spark).columns == ["variable", "value", "mass", "prob"]
    assert set(entry.oracle_sql()) <= set(entry.queries())
