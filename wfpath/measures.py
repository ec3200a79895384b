"""Cost and accuracy measures of the methods."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wfpath.functions.labels import label_bits
from wfpath.operators import allpairs, baseline, general, pairwise
from wfpath.plans import rpq
from wfpath.plans.safety import UnsafeQuery, _compiled, compile_rpq, is_safe
from wfpath.plans.spec import Spec
from wfpath.sources.runs import RunData


def timed(action: Callable[[], object], repeat: int = 1) -> float:
    """Mean seconds of an action."""
    began = time.perf_counter()
    for _ in range(repeat):
        action()
    return (time.perf_counter() - began) / repeat


def drained(df: DataFrame) -> int:
    """Runs a query to its end without keeping rows; returns their number."""
    return df.agg(F.count(F.lit(1))).first()[0]


def overhead(spark: SparkSession, cases: list[tuple[str, Spec, list[str]]]) -> DataFrame:
    """Milliseconds to parse, minimise and check: name, size, queries, avg_ms, worst_ms."""
    rows = []
    for name, spec, queries in cases:
        ms = []
        for q in queries:
            _compiled.cache_clear()
            rpq.compile_.cache_clear()
            ms.append(1000 * timed(lambda q=q, spec=spec: is_safe(spec, q)))
        rows.append((name, spec.size, len(queries), sum(ms) / len(ms), max(ms)))
    return spark.createDataFrame(rows, "name string, size int, queries int, avg_ms double, worst_ms double")


def pairwise_time(run: RunData, query: str, pairs: DataFrame, method: str = "labels") -> float:
    """Microseconds a pair, with the compilation spread over all pairs."""
    n = pairs.count()
    return 1e6 * timed(lambda: drained(general.holds(run, query, pairs, method).where("holds"))) / max(n, 1)


def allpairs_time(run: RunData, query: str, method: str, l1: DataFrame | None = None, l2: DataFrame | None = None) -> float:
    return timed(lambda: drained(general.evaluate(run, query, l1, l2, method)))


def improvement(base_s: float, ours_s: float) -> float:
    """The share of the baseline's time that is saved."""
    return (base_s - ours_s) / base_s if base_s else 0.0


def improved_shares(spark: SparkSession, times: list[tuple[str, float, float]]) -> DataFrame:
    """Of (query, baseline seconds, our seconds): shares improved, and improved by more than 40 %."""
    gains = [improvement(b, o) for _, b, o in times]
    n = max(len(gains), 1)
    return spark.createDataFrame([(len(gains), sum(g > 0 for g in gains) / n, sum(g > 0.4 for g in gains) / n)], "queries int, improved double, by_over_40 double")


def selectivity(pairs: DataFrame) -> DataFrame:
    """Matching pairs by run."""
    return pairs.groupBy("run_id").agg(F.count(F.lit(1)).alias("pairs"))


def reachable_pairs(run: RunData, l1: DataFrame | None = None, l2: DataFrame | None = None) -> DataFrame:
    """run_id, reachable, tested (|l1| times |l2|), pruned (the share that a reachability filter saves)."""
    n1 = allpairs.listed(run.nodes, l1).groupBy("run_id").agg(F.count(F.lit(1)).alias("n1"))
    n2 = allpairs.listed(run.nodes, l2).groupBy("run_id").agg(F.count(F.lit(1)).alias("n2"))
    found = allpairs.state_set(run.nodes, compile_rpq(run.spec, rpq.reach()), l1, l2, "count")
    x = n1.join(n2, "run_id").join(found, "run_id", "left")
    reachable, tested = F.coalesce("n", F.lit(0)), F.col("n1") * F.col("n2")
    return x.select("run_id", reachable.alias("reachable"), tested.alias("tested"), (1 - reachable / tested).alias("pruned"))


def plan_profile(run: RunData, query: str, strategy: str = "top_down") -> dict[str, int]:
    """Safe parts, joins and fixpoint rounds of a decomposed query, and the rows of its result."""
    counter = baseline.Rounds()
    plan = general.decompose(run.spec, query, strategy)
    rows = drained(general.evaluate_plan(plan, run, counter=counter))
    return {"safe_parts": plan.safe_parts(), "joins": plan.joins(), "rounds": counter.rounds, "rows": rows}


def label_lengths(run: RunData) -> DataFrame:
    """run_id, nodes, longest label in entries and in bits, against log2 of the nodes."""
    chain = F.aggregate("label", F.lit(0).cast("bigint"), lambda acc, e: F.greatest(acc, e["idx"]))
    longest = run.nodes.agg(F.max(chain)).first()[0] or 1
    bits = label_bits(run.spec, int(longest))
    return run.nodes.groupBy("run_id").agg(F.count(F.lit(1)).alias("nodes"), F.max(F.size("label")).alias("entries"), F.max(bits).alias("bits"), F.round(F.log2(F.count(F.lit(1))), 3).alias("log2_nodes"))


def safe_share(spec: Spec, n: int = 40, n_ops: int = 4, seed: int = 0) -> float:
    """The share of random queries that are safe."""
    return sum(is_safe(spec, rpq.random_rpq(spec.tags, seed + i, n_ops)) for i in range(n)) / n


def described(run: RunData) -> DataFrame:
    """Edges, nodes and tags of each run."""
    e = run.edges.groupBy("run_id").agg(F.count(F.lit(1)).alias("n_edges"), F.countDistinct("tag").alias("n_tags"))
    return e.join(run.nodes.groupBy("run_id").agg(F.count(F.lit(1)).alias("n_nodes")), "run_id").select("run_id", "n_nodes", "n_edges", "n_tags")


def prepare_time(run: RunData, path: str) -> dict[str, float]:
    """Milliseconds to derive labels, and to write the tag index."""
    return {"labels": 1000 * timed(lambda: drained(run.nodes)), "index": 1000 * timed(lambda: baseline.write_index(run.edges, path))}


def diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows of each that the other lacks: missing (in a only) and extra (in b only)."""
    return a.exceptAll(b).withColumn("side", F.lit("missing")).union(b.exceptAll(a).withColumn("side", F.lit("extra")))


def pair_tests(run: RunData, method: str, l1: DataFrame | None = None, l2: DataFrame | None = None) -> int:
    """Label comparisons of a method: all pairs of a run, or the reachable ones."""
    if method == "nested":
        return int(reachable_pairs(run, l1, l2).agg(F.sum("tested")).first()[0] or 0)
    return drained(allpairs.reachable(run.nodes, run.spec, l1, l2))


__all__ = ["UnsafeQuery", "pairwise"]
