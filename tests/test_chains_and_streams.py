"""Chains by halves of ranges, walks by hops, relational operators, and what streams drop and forget."""

import random

import pandas as pd
import pytest
from pyspark.sql import functions as F

from wfpath import experiments, measures
from wfpath.functions.labels import member, pack, pos
from wfpath.operators import allpairs, baseline, general, relational
from wfpath.plans import rpq
from wfpath.plans.safety import compile_rpq, is_safe
from wfpath.plans.spec import BadSpec, Spec, deep_like, fork_tags
from wfpath.sources.simulate import derive
from wfpath.streaming import labels as streams

CHAIN = Spec.chain("S", [("S", "a C z"), ("C", "x C"), ("C", "y")])


def chain_nodes(spark, n):
    """The nodes of a run whose chain has ``n`` members before its last."""
    label = lambda k: F.array(pos(1, 2), member(1, 1, F.col("id") + 1), pos(k, 1))
    xs = spark.range(n).select(F.lit("r").alias("run_id"), F.concat(F.lit("x"), F.col("id").cast("string")).alias("node_id"), F.lit("x").alias("module"), label(2).alias("label"))
    y = spark.range(n, n + 1).select(F.lit("r").alias("run_id"), F.lit("y").alias("node_id"), F.lit("y").alias("module"), label(3).alias("label"))
    return xs.union(y)


def test_halves_meet_once(spark):
    left = spark.range(1, 41).select(F.lit(1).alias("k"), F.col("id").alias("i"))
    right = left.select("k", F.col("i").alias("j"))
    tops = right.groupBy("k").agg(F.max("j").alias("top"))
    met = allpairs.lower_half(left, "i", tops, ["k"]).join(allpairs.upper_half(right, "j"), ["k", "mid"]).select("i", "j").collect()
    assert sorted(map(tuple, met)) == [(i, j) for i in range(1, 41) for j in range(i + 1, 41)]


def test_long_chain_is_counted_without_its_pairs(spark):
    n = 100_000
    nodes = chain_nodes(spark, n)
    plan = compile_rpq(CHAIN, "x*")
    assert allpairs.state_set(nodes, plan, output="count").first()["n"] == (n + 1) * (n + 2) // 2
    assert allpairs.state_set(nodes, plan, output="exists").count() == 1
    l1, l2 = nodes.where("node_id IN ('x5', 'x70000')"), nodes.where("node_id IN ('x3', 'x69999', 'y')")
    assert {(r["src"], r["dst"]) for r in allpairs.state_set(nodes, plan, l1, l2).collect()} == {("x5", "x69999"), ("x5", "y"), ("x70000", "y")}
    assert {(r["src"], r["dst"]) for r in allpairs.reachable(nodes, CHAIN, l1, l2).collect()} == {("x5", "x69999"), ("x5", "y"), ("x70000", "y")}


@pytest.mark.parametrize("most", [1, 48])
def test_hops_reach_what_steps_reach(spark, most):
    rng = random.Random(4)
    edges = {(f"n{a}", f"n{b}") for a, b in ((i, i + 1) for i in range(60))} | {tuple(f"n{x}" for x in sorted(rng.sample(range(61), 2))) for _ in range(30)}
    onward = {}
    for u, v in edges:
        onward.setdefault(u, []).append(v)
    want = set()
    for s in ("n0", "n17"):
        todo = [s]
        while todo:
            at = todo.pop()
            if (s, at) not in want:
                want.add((s, at))
                todo += onward.get(at, [])
    graph = spark.createDataFrame([("r", u, 0, v, 0) for u, v in edges], "run_id string, at string, q int, dst string, q2 int")
    start = spark.createDataFrame([("r", s, s, 0) for s in ("n0", "n17")], "run_id string, src string, at string, q int")
    counter = baseline.Rounds()
    got = [(r["src"], r["at"]) for r in baseline.spread_from(start, graph, most, counter).collect()]
    assert len(got) == len(set(got)) and set(got) == want
    assert counter.rounds < 12 if most > 1 else counter.rounds > 12


def test_rare_tag_starts_from_a_tag(spark):
    from wfpath.sources.runs import CARRIERS

    run = CARRIERS["example"].build(spark, "")
    with pytest.raises(ValueError):
        general.evaluate(run, "a*", method="rare_tag")
    few, any_ = (sorted(map(tuple, general.evaluate(run, "_*.e._*", method="rare_tag", threshold=t).collect())) for t in (0, 1000))
    assert few == any_ and len(few) == 16


def test_walk_equals_labels_on_workflows(spark):
    for name in ("deep", "branchy"):
        run = experiments.Simulated(name, 40, seed=2).build(spark)
        query = experiments.passing(name, 3, 2)[-1]
        assert measures.diff(general.evaluate(run, query, method="walk"), general.evaluate(run, query, method="state_set")).count() == 0


def test_focus_runs_repeat_one_recursion():
    for name in ("deep", "branchy"):
        spec, focus, tag = experiments.workflow(name), experiments.focus_of(name), experiments.star_tag(name)
        nodes, edges = derive(spec, 200, 0, focus)
        longest = {}
        for _, _, label in nodes:
            for e in label:
                if e[0] == 1:
                    longest[e[1]] = max(longest.get(e[1], 0), e[3])
        assert longest[focus] > 10 and all(n <= 2 for c, n in longest.items() if c != focus)
        assert tag in fork_tags(spec) and sum(t == tag for _, _, t in edges) > 10
    assert deep_like(fork=True).statistics == deep_like().statistics


def test_queries_with_safe_operands():
    for n in (1, 3):
        spec = experiments.workflow("branchy")
        assert not is_safe(spec, experiments.with_safe_operands("branchy", 4, n))
    assert all(not is_safe(experiments.workflow("deep"), q) for q in experiments.unsafe("deep", 3))
    assert len(set(experiments.passing("deep", 3, 8))) == 8


def test_measures_of_sweeps(spark):
    one = experiments.overhead_sweep(spark, (60,), specs=2, queries=2).collect()
    assert one[0]["queries"] == 4 and one[0]["worst_ms"] >= one[0]["avg_ms"] > 0
    results = spark.createDataFrame([("deep", 0.5), ("deep", -0.1), ("branchy", 0.3)], "workflow string, improvement double")
    assert {r["workflow"]: (r["queries"], r["improved"], r["by_over_40"]) for r in experiments.shares(results).collect()} == {"deep": (2, 0.5, 0.5), "branchy": (1, 1.0, 0.0)}
    run = experiments.Simulated("deep", 20).build(spark)
    l1, l2 = experiments.two_lists(run, 4)
    pairs = l1.select("run_id", F.col("node_id").alias("src")).join(l2.select("run_id", F.col("node_id").alias("dst")), "run_id")
    assert measures.pairwise_time(run, "_*", pairs) > 0 and measures.allpairs_time(run, "_*", "filtered", l1, l2) > 0
    assert measures.pair_tests(run, "nested", l1, l2) == 16
    assert measures.plan_profile(run, "_*")["safe_parts"] == 1
    assert measures.improved_shares(spark, [("q", 2.0, 1.0), ("r", 1.0, 2.0)]).first()["by_over_40"] == 0.5


def test_labels_too_large_are_refused(spark):
    far = spark.createDataFrame([(1,)], "x int").select(F.array(member(1, 1, F.lit(1 << 41))).alias("label"))
    with pytest.raises(Exception, match="too large to pack"):
        far.select(pack(F.col("label"))).collect()
    with pytest.raises(BadSpec):
        Spec.build("S", [("S", ["a"] * (1 << 16), [])])


def test_ranges_and_as_of(spark):
    a = spark.createDataFrame([(1, 0, "a"), (1, 9, "b"), (2, 25, "c"), (1, 30, "d")], "k int, at long, name string")
    b = spark.createDataFrame([(1, 9, "x"), (1, 10, "y"), (2, 24, "z"), (2, 34, "w"), (1, 19, "v")], "k int, other long, it string")
    got = {(r["name"], r["it"]) for r in relational.within_range(a, b, ["k"], "at", "other", 10).collect()}
    assert got == {("a", "x"), ("b", "x"), ("b", "y"), ("c", "w")}
    starts = spark.createDataFrame([(1, 5, "early"), (1, 9, "nine"), (2, 26, "late")], "k int, at long, it string")
    assert {r["name"]: r["it"] for r in relational.as_of(a, starts, ["k"], "at", "it").collect()} == {"a": None, "b": "nine", "c": None, "d": "nine"}


def streamed(spark, tmp_path, files, **options):
    """The labels of a stream that reads these files one by one."""
    schema = "event_id long, ts timestamp, user_id long, event_type string"
    folder = tmp_path / "in"
    folder.mkdir()
    for i, rows in enumerate(files):
        frame = pd.DataFrame([(e, pd.Timestamp(t), u, k) for e, t, u, k in rows], columns=["event_id", "ts", "user_id", "event_type"])
        frame["ts"] = frame["ts"].astype("datetime64[us]")
        spark.createDataFrame(frame, schema).coalesce(1).write.parquet(str(folder / f"part{i}"))
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(str(folder))
    return {r["node_id"] for r in streams.stored(streams.labelled(stream, **options), "file://" + str(tmp_path)).collect()}


def test_late_events_are_dropped(spark, tmp_path):
    files = [
        [(1, "2024-03-01 10:00", 1, "click"), (2, "2024-03-01 10:05", 1, "view")],
        [(3, "2024-05-01 10:00", 1, "click")],
        [(4, "2024-05-01 10:10", 1, "view")],
        [(5, "2024-03-02 09:00", 1, "click"), (6, "2024-05-01 10:20", 1, "click")],
    ]
    got = streamed(spark, tmp_path, files, watermark="1 day")
    steps = {n for n in got if n.endswith(("click", "view"))}
    assert steps == {"u1.s1.e1.click", "u1.s1.e2.view", "u1.s2.e1.click", "u1.s2.e2.view", "u1.s2.e3.click"}


def test_old_runs_are_closed_and_forgotten(spark, tmp_path):
    files = [[(1, "2024-03-01 10:00", 1, "click")], [(2, "2024-05-01 10:00", 2, "click")], [(3, "2024-05-02 10:00", 2, "view")], [(4, "2024-05-03 10:00", 1, "click")]]
    got = streamed(spark, tmp_path, files, watermark="1 day", keep_hours=240)
    first, later = (pd.Timestamp(t).value // 1000 for t in ("2024-03-01 10:00", "2024-05-03 10:00"))
    assert {f"u1@{first}.end", f"u1@{first}.halt", f"u1@{first}.s1.pause", f"u1@{later}.begin", f"u1@{later}.s1.e1.click"} <= got
