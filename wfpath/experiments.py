"""The experiments on the two workflows with the published statistics, and their sweeps.

Runs are simulated from seeds, so a run's edges can stand in a SQL text as values: the queries
registered here are checked by a walk in DuckDB over just those edges.  The sweeps take times and
are for the bench; each gives rows that a plot would need.
"""

from __future__ import annotations

import functools
import random
from collections.abc import Callable
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wfpath import measures
from wfpath.operators import allpairs, general
from wfpath.plans import rpq
from wfpath.plans.rpq import Node
from wfpath.plans.safety import compile_rpq, is_safe
from wfpath.plans.spec import Spec, branchy_like, deep_like, fork_tags, random_spec
from wfpath.sources.runs import RunData, StoredRun, table
from wfpath.sources.simulate import EDGE, NODE, derive, simulate


@functools.cache
def workflow(name: str) -> Spec:
    """deep (its innermost recursion is a fork), branchy, or random<size>."""
    if name == "deep":
        return deep_like(fork=True)
    if name == "branchy":
        return branchy_like()
    return random_spec(int(name.removeprefix("random")), n_cycles=3, cycle_len=1, seed=int(name.removeprefix("random")))


@dataclass(frozen=True)
class Simulated:
    """One simulated run of a workflow; has what a carrier has, but no tables."""

    name: str
    target: int
    seed: int = 0
    focus: int | None = None

    @property
    def spec(self) -> Spec:
        return workflow(self.name)

    def build(self, spark: SparkSession, sf_dir: str = "") -> RunData:
        return simulate(spark, self.spec, self.target, self.seed, 1, self.focus)

    def stored(self, spark: SparkSession, sf_dir: str, folder: str) -> StoredRun:
        return StoredRun(lambda: self.build(SparkSession.active()), self.spec, folder)

    def duckdb(self) -> str:
        """The run's edges as SQL values."""
        rows = ", ".join(f"('y{self.seed}', '{u}', '{v}', '{t}')" for u, v, t in derive(self.spec, self.target, self.seed, self.focus)[1])
        return f"SELECT * FROM (VALUES {rows}) AS v(run_id, src, dst, tag)"


@dataclass(frozen=True)
class SourceRuns:
    """A run of a workflow for each source of documents; the source's document ids choose one of some derivations."""

    name: str
    target: int
    focus: int | None = None
    variants: int = 3

    @property
    def spec(self) -> Spec:
        return workflow(self.name)

    def build(self, spark: SparkSession, sf_dir: str) -> RunData:
        n, spec, target, focus = self.variants, self.spec, self.target, self.focus
        docs = table(spark, sf_dir, "documents").where("source IS NOT NULL").select(F.col("source").alias("run_id"), F.pmod(F.coalesce("doc_id", F.lit(0)), F.lit(n)).alias("own"))
        chosen = docs.groupBy("run_id").agg((F.sum("own") % n).cast("int").alias("seed"))

        def nodes_of(batches):
            for pdf in batches:
                for run, seed in zip(pdf["run_id"], pdf["seed"], strict=True):
                    nodes, _ = derive(spec, target, int(seed), focus)
                    yield pd.DataFrame([(run, v, m, [dict(zip(("kind", "a", "b", "idx"), e, strict=True)) for e in label]) for v, m, label in nodes], columns=["run_id", "node_id", "module", "label"])

        def edges_of(batches):
            for pdf in batches:
                for run, seed in zip(pdf["run_id"], pdf["seed"], strict=True):
                    yield pd.DataFrame([(run, *e) for e in derive(spec, target, int(seed), focus)[1]], columns=["run_id", "src", "dst", "tag"])

        return RunData(chosen.mapInPandas(nodes_of, NODE), chosen.mapInPandas(edges_of, EDGE), spec)

    def duckdb(self) -> str:
        """The derivations' edges as SQL values, joined with the sources that choose them."""
        n = self.variants
        rows = ", ".join(f"({seed}, '{u}', '{v}', '{t}')" for seed in range(n) for u, v, t in derive(self.spec, self.target, seed, self.focus)[1])
        chosen = f"SELECT source AS run_id, sum((coalesce(doc_id, 0) % {n} + {n}) % {n}) % {n} AS seed FROM documents WHERE source IS NOT NULL GROUP BY source"
        return f"SELECT run_id, src, dst, tag FROM ({chosen}) AS c JOIN (VALUES {rows}) AS v(seed, src, dst, tag) ON v.seed = c.seed"


@functools.cache
def focus_of(name: str) -> int:
    """The cycle whose star is the fork experiment's query."""
    spec, t = workflow(name), star_tag(name)
    return next(c.number for c in spec.cycles for k, i in c.slots if any(v == i and x == t for _, v, x in spec[k].edges))


@functools.cache
def star_tag(name: str) -> str:
    """A tag that links the heads of the members of a chain, whose star is safe."""
    spec = workflow(name)
    return next(t for t in fork_tags(spec) if is_safe(spec, f"{t}*"))


@functools.cache
def passing(name: str, k: int, n: int, target: int = 300, seed: int = 0, draws: int = 300) -> tuple[str, ...]:
    """``n`` safe passing queries of ``k`` tags that match on a run: half with the rarest tags found, half with the commonest.

    Tags are drawn along random paths of the run, so a query has a match there, as long as there are enough such.
    """
    spec, rng = workflow(name), random.Random(seed + k)
    if k == 0:
        return (str(rpq.reach()),) * n
    onward: dict[str, list[tuple[str, str]]] = {}
    counts: dict[str, int] = {}
    heads = set()
    edges = derive(spec, target, seed)[1]
    for u, v, t in edges:
        onward.setdefault(u, []).append((v, t))
        counts[t] = counts.get(t, 0) + 1
        heads.add(v)
    source = next(u for u, _, _ in edges if u not in heads)
    safe_tags = {t for t in counts if is_safe(spec, rpq.ifq([t]))}
    weight: dict[str, int] = {}
    for _ in range(draws):
        at, path = source, []
        while at in onward:
            at, t = rng.choice(onward[at])
            path.append(t)
        path = [t for t in path if t in safe_tags]
        if len(path) >= k:
            tags = [path[i] for i in sorted(rng.sample(range(len(path)), k))]
            query = str(rpq.ifq(tags))
            if query not in weight and is_safe(spec, query):
                weight[query] = sum(counts[t] for t in tags)
        if len(weight) >= 20 * n:
            break
    pool, tries = sorted(safe_tags), 0
    while len(weight) < n and tries < draws:
        # where too few paths pass so many safe tags: queries that no path may match
        tries += 1
        query = str(rpq.ifq(rng.choices(pool, k=k)))
        if query not in weight and is_safe(spec, query):
            weight[query] = 0
    ranked = sorted(weight, key=lambda q: (weight[q], q))
    return tuple([*ranked[: (n + 1) // 2], *ranked[len(ranked) - n // 2 :]])


@functools.cache
def unsafe(name: str, n: int, n_ops: int = 4, seed: int = 0) -> tuple[Node, ...]:
    """``n`` random unsafe queries with a safe part."""
    spec, found, at = workflow(name), [], seed
    while len(found) < n:
        q = rpq.rewrite(rpq.random_rpq(spec.tags, at, n_ops))
        at += 1
        if not is_safe(spec, q) and general.decompose(spec, q, "runs").safe_parts():
            found.append(q)
    return tuple(found)


@functools.cache
def with_safe_operands(name: str, n_ops: int, n_safe: int, seed: int = 0) -> Node:
    """A query of ``n_ops`` operands, exactly ``n_safe`` of which are safe; unsafe as a whole if any operand isn't."""
    spec, rng = workflow(name), random.Random(seed)
    ops: list[Node] = []
    while len(ops) < n_ops:
        q = rpq.rewrite(rpq.random_rpq(spec.tags, rng.randrange(1 << 30), 1))
        if is_safe(spec, q) == (len(ops) < n_safe):
            ops.append(q)
    rng.shuffle(ops)
    out = ops[0]
    for q in ops[1:]:
        out = rpq.cat(out, q) if rng.random() < 0.5 else rpq.alt(out, q)
    return rpq.rewrite(out)


def two_lists(run: RunData, size: int) -> tuple[DataFrame, DataFrame]:
    """Two lists of ``size`` nodes, drawn by two hashes of their names."""
    pick = lambda n: run.nodes.select("run_id", "node_id").orderBy(F.xxhash64("node_id", F.lit(n)), "node_id").limit(size)
    return pick(1), pick(2)


def times(rows: list[tuple], columns: str, spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(rows, columns)


def overhead_sweep(spark: SparkSession, sizes: tuple[int, ...] = (400, 600, 800, 1000, 1200), specs: int = 10, queries: int = 20) -> DataFrame:
    """Milliseconds of parsing and checking against the size of the specification: passing queries of three tags on random ones."""
    cases = []
    for size in sizes:
        for seed in range(specs):
            spec, rng = random_spec(size, n_cycles=3, seed=1000 * size + seed), random.Random(seed)
            cases.append((f"{size}", spec, [str(rpq.ifq(rng.choices(spec.tags, k=3))) for _ in range(queries)]))
    per_spec = measures.overhead(spark, cases)
    return per_spec.groupBy("name").agg(F.avg("size").alias("size"), F.sum("queries").alias("queries"), F.avg("avg_ms").alias("avg_ms"), F.max("worst_ms").alias("worst_ms"))


def overhead_by_k(spark: SparkSession, ks: range = range(11), queries: int = 20) -> DataFrame:
    """Milliseconds of parsing and checking against the number of tags, on both workflows."""
    cases = []
    for name in ("deep", "branchy"):
        spec = workflow(name)
        for k in ks:
            rng = random.Random(k)
            cases.append((f"{name} {k}", spec, [str(rpq.ifq(rng.choices(spec.tags, k=k))) for _ in range(queries)]))
    return measures.overhead(spark, cases)


def pairwise_sweep(spark: SparkSession, make: Callable[[Simulated], RunData], sizes=(1000, 2000, 4000, 8000), ks=(3,), methods=("labels", "rare_tag", "index"), side: int = 100) -> DataFrame:
    """Microseconds a pair of passing queries on the deep workflow, by size of the run, number of tags and method."""
    rows = []
    for target in sizes:
        run = make(Simulated("deep", target))
        l1, l2 = two_lists(run, side)
        pairs = l1.select("run_id", F.col("node_id").alias("src")).join(l2.select("run_id", F.col("node_id").alias("dst")), "run_id")
        for k in ks:
            query = passing("deep", k, 2)[-1]
            rows += [(target, k, m, measures.pairwise_time(run, query, pairs, m)) for m in methods if k or m != "rare_tag"]
    return times(rows, "edges int, k int, method string, us_a_pair double", spark)


def allpairs_sweep(spark: SparkSession, make: Callable[[Simulated], RunData], target: int = 2000, methods=("nested", "filtered", "state_set", "index"), n: int = 8) -> DataFrame:
    """Seconds of ``n`` passing queries of three tags over all pairs of nodes, by workflow and method, with the pairs found."""
    rows = []
    for name in ("deep", "branchy"):
        run = make(Simulated(name, target))
        for query in passing(name, 3, n):
            found = measures.drained(general.evaluate(run, query, method="state_set"))
            rows += [(name, query, found, m, measures.allpairs_time(run, query, m)) for m in methods]
    return times(rows, "workflow string, query string, pairs long, method string, seconds double", spark)


def star_sweep(spark: SparkSession, make: Callable[[Simulated], RunData], sizes=(1000, 4000, 16000), methods=("filtered", "state_set", "joins"), names=("deep", "branchy")) -> DataFrame:
    """Seconds of a fork's star by size of the run and method, on runs where only that recursion goes on."""
    rows = []
    for name in names:
        for target in sizes:
            run = make(Simulated(name, target, focus=focus_of(name)))
            rows += [(name, target, m, measures.allpairs_time(run, f"{star_tag(name)}*", m)) for m in methods]
    return times(rows, "workflow string, edges int, method string, seconds double", spark)


def general_sweep(spark: SparkSession, make: Callable[[Simulated], RunData], n: int = 40, target: int = 1000, side: int = 200) -> DataFrame:
    """Random unsafe queries on both workflows: seconds of joins over the parse tree and of safe parts by labels, and the share saved."""
    rows = []
    for name in ("deep", "branchy"):
        run = make(Simulated(name, target))
        l1, l2 = two_lists(run, side)
        for q in unsafe(name, n):
            base = measures.allpairs_time(run, q, "joins", l1, l2)
            ours = measures.allpairs_time(run, q, "decompose_runs", l1, l2)
            rows.append((name, str(q), base, ours, measures.improvement(base, ours)))
    return times(rows, "workflow string, query string, joins_s double, ours_s double, improvement double", spark)


def shares(results: DataFrame) -> DataFrame:
    """Of a general sweep: queries by workflow, the share improved, and the share improved by more than 40 %."""
    return results.groupBy("workflow").agg(F.count(F.lit(1)).alias("queries"), F.avg((F.col("improvement") > 0).cast("int")).alias("improved"), F.avg((F.col("improvement") > 0.4).cast("int")).alias("by_over_40"))


def matched_by_workflow(spark: SparkSession, make: Callable[[Simulated], RunData], target: int = 300, n: int = 4) -> DataFrame:
    """Pairs that the same number of passing queries find on runs of the same size, deep against branchy."""
    out = None
    for name in ("deep", "branchy"):
        run = make(Simulated(name, target))
        for i, query in enumerate(passing(name, 3, n)):
            one = allpairs.state_set(run.nodes, compile_rpq(run.spec, query), output="count").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("pairs")).select(F.lit(name).alias("workflow"), F.lit(i).alias("i"), "pairs")
            out = one if out is None else out.union(one)
    return out
