"""Run an engine on a workload, repeat, and report times, status and bytes."""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from concurrent.futures import TimeoutError as Late
from statistics import mean

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines.circuit import compile_circuit
from ..baselines.dense import DenseLimitError, dense_junction_tree
from ..baselines.join_graph import join_graph_propagation
from ..model import InconsistentEvidence, Network
from ..networks import clique, events, grid, star, supply, text, toy
from ..operators.batch import BatchLimitError, solve_trees
from ..operators.infer import InferConfig, infer

#: id -> (builder of a network, or of a network and its templates)
WORKLOADS: dict[str, Callable] = {
    "W1": supply.triangle, "W1s": supply.hub, "W2": supply.lookahead, "W3": toy.network, "W4": clique.network, "W5": lambda s, d: grid.network(s, d, 28, 28),
    "W6": lambda s, d: grid.network(s, d, 28, 28, wide_factor=True), "W7": events.chain, "W8": star.network, "W9": lambda s, d: grid.network(s, d, 14, 14, wide_factor=True),
    "W17": text.labels, "W18": text.roles, "W19": text.hosts,
}


def workload(spark: SparkSession, sf_dir: str, name: str) -> tuple[Network, dict[str, str]]:
    made = WORKLOADS[name](spark, sf_dir)
    return made if isinstance(made, tuple) else (made, {})


def _multiway(strategy: str):
    return lambda n, t: infer(n, strategy, config=InferConfig()).variable_marginals()


ENGINES: dict[str, Callable[[Network, dict], DataFrame]] = {
    "multiway": _multiway("multiway"), "multiway_proj": _multiway("multiway_proj"), "pairwise": _multiway("pairwise"), "hybrid": _multiway("hybrid"),
    "batched": lambda n, t: solve_trees(n, t, measured=True).filter("variable IS NOT NULL"), "dense": lambda n, t: dense_junction_tree(n),
    "join_graph": lambda n, t: join_graph_propagation(n, len(n.vars))[0], "circuit": lambda n, t: compile_circuit(n).evaluate()[0],
}


def run(spark: SparkSession, sf_dir: str, engine: str, name: str, repeats: int = 5, timeout: float = 3600.0) -> DataFrame:
    """(engine, workload, status, seconds, runs). Status: ok, T over time, F cell limit, E inconsistent, B batch limit."""
    network, templates = workload(spark, sf_dir, name)
    times, status = [], "ok"
    tag = f"bench-{engine}-{name}"

    def once() -> None:
        spark.sparkContext.addJobTag(tag)
        ENGINES[engine](network, templates).write.format("noop").mode("overwrite").save()

    for _ in range(repeats):
        began = time.perf_counter()
        pool = ThreadPoolExecutor(1)
        try:
            pool.submit(once).result(timeout)
        except Late:
            spark.sparkContext.cancelJobsWithTag(tag)
            status = "T"
        except DenseLimitError:
            status = "F"
        except InconsistentEvidence:
            status = "E"
        except BatchLimitError:
            status = "B"
        finally:
            pool.shutdown(wait=True)
        if status != "ok":
            break
        times.append(time.perf_counter() - began)
    return spark.createDataFrame([(engine, name, status, mean(times) if status == "ok" else None, len(times))], "engine string, workload string, status string, seconds double, runs int")


def compare(results: DataFrame, base: str) -> DataFrame:
    """Speed-up of every engine over ``base``, per workload."""
    b = results.filter(F.col("engine") == base).select("workload", F.col("seconds").alias("base_s"))
    return results.join(b, "workload").select("workload", "engine", "status", "seconds", (F.col("base_s") / F.col("seconds")).alias("speed_up"))


def memory(cal) -> DataFrame:
    """(bag, product_rows, product_bytes, message_bytes): sizes that Spark's statistics give (C14)."""
    size = lambda df: int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    rows = [(b, f.df.count(), size(f.df), size(cal.up[b].df) if b in cal.up else 0) for b, f in cal.products.items()]
    return cal.dec.network.spark.createDataFrame(rows, "bag int, product_rows long, product_bytes long, message_bytes long")


def storage_profile(network: Network) -> DataFrame:
    """(factor, rows, index_bits, list_bytes, trie_bytes): index lists beside level-order tries (C17)."""
    from ..functions.index import index_bits

    rows = []
    for f in network.factors:
        n = network.sizes[f.name]
        levels = [f.count_support(f.vars[: j + 1]) for j in range(len(f.vars))]
        rows.append((f.name, n, index_bits([network.domains[v] for v in f.vars]), 16 * n, 8 * sum(levels) + 8 * sum(levels[:-1]) + 8 * n))
    return network.spark.createDataFrame(rows, "factor string, rows long, index_bits double, list_bytes long, trie_bytes long")
