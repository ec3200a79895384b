import pandas as pd
import pytest
from pyspark.sql import functions as F

from wfpath import measures, workloads
from wfpath.functions.labels import array_kernel, pack, unpack
from wfpath.operators import allpairs, baseline, general, pairwise
from wfpath.plans import rpq, safety, spec
from wfpath.sources import runs, simulate
from wfpath.streaming import labels as streams

SF = "/root/testdata/sf0.001"


def rows(df):
    got = [tuple(r) for r in df.collect()]
    assert len(got) == len(set(got)), "a pair came twice"
    return set(got)


@pytest.fixture(scope="session")
def example(spark):
    return runs.CARRIERS["example"].build(spark, SF)


@pytest.mark.parametrize("query, n", [("A+", 6), ("A", 3), ("_*.e._*", 16), ("_*", 43), ("a*", 13)])
def test_example_counts(example, query, n):
    want = rows(general.evaluate(example, query, method="walk"))
    assert len(want) == n
    for method in ("nested", "state_set"):
        assert rows(general.evaluate(example, query, method=method)) == want, method


@pytest.mark.parametrize("query, n", [("e", 1), ("_*.a._*", 17)])
def test_example_unsafe(example, query, n):
    for method in ("joins", "decompose_runs"):
        assert len(rows(general.evaluate(example, query, method=method))) == n
    with pytest.raises(safety.UnsafeQuery):
        general.evaluate(example, query, method="state_set")


def test_lists(spark, example):
    l1 = spark.createDataFrame([("example", n) for n in ("d:1", "d:2", "e:2", "d:1", "nowhere")], "run_id string, node_id string")
    l2 = spark.createDataFrame([("example", n) for n in ("b:1", "b:2")] + [("other", "b:1")], "run_id string, node_id string")
    for method in ("nested", "filtered", "state_set", "joins", "walk"):
        assert {(u, v) for _, u, v in rows(general.evaluate(example, "A+", l1, l2, method))} == {("d:1", "b:1"), ("d:2", "b:1"), ("e:2", "b:1")}
    none = l1.limit(0)
    assert rows(allpairs.state_set(example.nodes, safety.compile_rpq(example.spec, "_*"), none, l2)) == set()


def test_pairwise(spark, example):
    pairs = spark.createDataFrame([("example", "d:2", "b:1"), ("example", "c:1", "b:3"), ("example", "c:1", "lost")], "run_id string, src string, dst string")
    got = {(u, v): h for _, u, v, h in rows(general.holds(example, "A+", pairs))}
    assert got == {("d:2", "b:1"): True, ("c:1", "b:3"): False, ("c:1", "lost"): False}
    arrays = {(u, v): h for _, u, v, h in rows(pairwise.holds(pairs, example.nodes, safety.compile_rpq(example.spec, "A+"), "arrays"))}
    assert arrays == got
    assert {h for *_, h in rows(general.holds(example, "_*.a._*", pairs))} == {False}


def test_kernels_on_random_grammars():
    checked = 0
    for seed in range(12):
        g = spec.random_spec(40, n_cycles=2, cycle_len=1 + seed % 2, seed=seed)
        nodes, edges = simulate.derive(g, 50, seed)
        out = {}
        for u, v, t in edges:
            out.setdefault(u, []).append((v, t))
        label = {n: [dict(zip(("kind", "a", "b", "idx"), e, strict=True)) for e in lab] for n, _, lab in nodes}
        for k in range(8):
            q = rpq.random_rpq(g.tags, seed * 100 + k, 3)
            if not safety.is_safe(g, q):
                continue
            plan, want = safety.compile_rpq(g, q), set()
            for s in label:
                seen, todo = {(s, 0)}, [(s, 0)]
                while todo:
                    at, state = todo.pop()
                    for v, t in out.get(at, []):
                        d = plan.dfa.delta[state][plan.dfa._at[t]]
                        if d >= 0 and (v, d) not in seen:
                            seen.add((v, d))
                            todo.append((v, d))
                want |= {(s, a) for a, state in seen if state in plan.dfa.finals}
            pairs = [(a, b) for a in label for b in label]
            got = array_kernel(plan).func(pd.Series([label[a] for a, _ in pairs]), pd.Series([label[b] for _, b in pairs]))
            assert {p for p, h in zip(pairs, got, strict=True) if h} == want, (seed, q)
            checked += 1
    assert checked > 20


def test_simulated_run_all_methods(spark):
    g = spec.random_spec(60, n_cycles=2, cycle_len=2, seed=2)
    run = simulate.simulate(spark, g, 80, 2)
    q = next(q for q in (rpq.random_rpq(g.tags, 200 + k, 3) for k in range(40)) if safety.is_safe(g, q))
    want = rows(general.evaluate(run, q, method="walk"))
    for method in ("nested", "filtered", "state_set"):
        assert rows(general.evaluate(run, q, method=method)) == want


def test_labels_pack_and_log(spark, example):
    both = example.nodes.select("label", unpack(pack(F.col("label"))).alias("back")).collect()
    assert all(r["label"] == r["back"] for r in both)
    log = [("r", "x0", None, None, None, "S"), ("r", "c", "x0", 1, 1, "c"), ("r", "A1", "x0", 1, 2, "A"), ("r", "B1", "x0", 1, 3, "B"), ("r", "b1", "x0", 1, 4, "b"), ("r", "a1", "A1", 2, 1, "a"), ("r", "A2", "A1", 2, 2, "A"), ("r", "d1", "A1", 2, 3, "d"), ("r", "e1", "A2", 3, 1, "e"), ("r", "e2", "A2", 3, 2, "e")]
    df = spark.createDataFrame(log, "run_id string, exec string, parent string, prod int, pos int, module string")
    got = {r["node_id"]: [tuple(e) for e in r["label"]] for r in simulate.labels_from_log(df, example.spec).collect()}
    assert got["e2"] == [(0, 1, 2, 0), (1, 1, 1, 2), (0, 3, 2, 0)] and got["d1"] == [(0, 1, 2, 0), (1, 1, 1, 1), (0, 2, 3, 0)] and got["c"] == [(0, 1, 1, 0)]


def test_closure_modes(spark):
    chain = spark.createDataFrame([("r", str(i), str(i + 1)) for i in range(9)], "run_id string, src string, dst string")
    got = {}
    for mode in ("linear", "semi", "double"):
        c = baseline.Rounds()
        assert baseline.closure(chain, mode, c).count() == 45
        got[mode] = c.rounds
    assert got["double"] < got["semi"]


def test_choice_and_plans():
    d = runs.DOCUMENTS
    assert general.choose(d, "split*", {"split": 10}, 100, 100, 100).method == "state_set"
    assert general.choose(d, "_*.translate._*", {"translate": 0}, 9, 9, 9).method == "none"
    part = general.decompose(d, "split*.(_*.translate._*)", "runs")
    assert part.kind != "safe" and part.safe_parts() >= 2
    assert general.decompose(d, "split*").kind == "safe"


def test_streamed_labels(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet").where("user_id < 3")
    whole = str(tmp_path / "in")
    events.repartition(1).sortWithinPartitions("ts").write.parquet(whole)
    stream = spark.readStream.schema(events.schema).parquet(whole)
    got = streams.with_keys(streams.stored(streams.labelled(stream), "file://" + str(tmp_path)))
    n = got.count()
    assert n == got.select("run_id", "label_key").distinct().count() and n > events.count()
    sessions = runs.events_ranked(events).select("run_id", "a").distinct().count()
    assert got.where("module = 'arrive'").count() == sessions


def test_measures(spark, example):
    got = measures.overhead(spark, [("x", example.spec, ["A+", "e"])]).first()
    assert got["queries"] == 2 and got["worst_ms"] >= got["avg_ms"]
    assert measures.improvement(4.0, 1.0) == 0.75
    r = measures.reachable_pairs(example).first()
    assert (r["reachable"], r["tested"]) == (43, 100)
    assert 0 < measures.safe_share(example.spec) <= 1


def test_plan_has_no_python(spark):
    data = runs.CARRIERS["documents"].build(spark, SF)
    text = allpairs.state_set(data.nodes, safety.compile_rpq(data.spec, "split*"))._jdf.queryExecution().toString()
    assert "Python" not in text and "Pandas" not in text and "CartesianProduct" not in text


@pytest.mark.parametrize("key", ["fork_star_state_set", "conv_cycle_turns_decompose", "pairwise_ifq_supply", "safety_catalogue", "run_edges_talks"])
def test_workloads_against_duckdb(spark, key):
    import os

    import duckdb

    con = duckdb.connect()
    for f in os.listdir(SF):
        con.sql(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM '{SF}/{f}'")
    df = workloads.QUERIES[key](spark, SF)
    cols = sorted(df.columns)
    got = sorted(map(repr, (tuple(r) for r in df.select(*cols).collect())))
    assert got == sorted(map(repr, con.sql(f"SELECT {', '.join(cols)} FROM ({workloads.ORACLES[key]}) AS t").fetchall()))
