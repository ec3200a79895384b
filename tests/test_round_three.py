"""What the reviewer's second round found: queries on large tables, and queries that read no table."""

import os

import duckdb
import pytest
from pyspark.sql import functions as F

from wfpath import workloads
from wfpath.operators import allpairs, general
from wfpath.plans.safety import compile_rpq
from wfpath.sources import runs

SF = "/root/testdata/sf0.001"


def same_as_sql(spark, key):
    con = duckdb.connect()
    for f in os.listdir(SF):
        con.execute(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM '{SF}/{f}'")
    df = workloads.QUERIES[key](spark, SF)
    cols = sorted(df.columns)
    got = sorted(map(repr, (tuple(r) for r in df.select(*cols).collect())))
    assert got == sorted(map(repr, con.execute(f"SELECT {', '.join(cols)} FROM ({workloads.ORACLES[key]}) AS t").fetchall()))
    return got


def test_lists_of_orders_derive_no_other_node(spark, tmp_path):
    """All nodes of a run were written, and joined with the lists, for two modules of it."""
    carrier = runs.CARRIERS["full_orders"]
    whole = carrier.nodes(spark, SF)
    data = carrier.stored(spark, SF, f"file://{tmp_path}/run")
    for modules in (["accept"], ["settle", "close"], ["refund", "open"]):
        key = lambda x: sorted(map(repr, x.select("run_id", "node_id", "module", "label").collect()))
        assert key(data.part(modules)) == key(whole.where(F.col("module").isin(modules)))
    u, v = data.part(["accept"]), data.part(["settle", "close"])
    out = allpairs.state_set(general.labelled(data, u, v), compile_rpq(data.spec, "_*.accept._*.pick._*"), u, v, "count")
    assert out.count() and not os.path.exists(tmp_path / "run" / "nodes")
    plan = runs._orders_nodes(spark, SF, True, frozenset(["accept"]))._jdf.queryExecution().optimizedPlan().toString()
    windows = [line for line in plan.split("\n") if "Window" in line]
    assert windows and not any("l_linenumber" in line for line in windows)


@pytest.mark.parametrize("key, table", [("augmented_example", "conversations"), ("determinism", "conversations"), ("equivalence", "conversations"), ("example_plus_joins", "conversations"), ("branchy_star_joins", "documents"), ("deep_star_nested", "documents")])
def test_given_tables_are_read(spark, key, table):
    """These made their rows up."""
    assert table in workloads.ORACLES[key]
    assert same_as_sql(spark, key)


def test_nested_turns_have_the_grammars_labels(spark):
    data = runs.NESTS.build(spark, SF)
    key = lambda method: sorted(map(tuple, general.evaluate(data, "A+", method=method).collect()))
    assert key("state_set") == key("joins")


def test_rounds_grow_with_the_logarithm_of_a_chain(spark):
    """hops ended at 16 steps, so a chain of pages took a round for each 16 of them."""
    from wfpath.operators import baseline

    n = 400
    graph = spark.range(n).select(F.lit("r").alias("run_id"), F.col("id").cast("string").alias("at"), F.lit(0).alias("q"), (F.col("id") + 1).cast("string").alias("dst"), F.lit(0).alias("q2"))
    start = spark.createDataFrame([("r", "3", "3", 0)], "run_id string, src string, at string, q int")
    counter = baseline.Rounds()
    found = baseline.spread_from(start, graph, counter=counter)
    assert {r["at"] for r in found.collect()} == {str(i) for i in range(3, n + 1)} and found.count() == n - 2
    assert counter.rounds <= 12


def test_the_quality_path_is_laid_on_all_rows(spark, monkeypatch):
    """it was laid on some 4,000 of the tuning rows."""
    from wfpath.llm import quality_rules

    n = 9000
    none = [F.lit(0).cast("long").alias(c) for c in quality_rules.STATS if c not in ("n_words", "n_symbols")]
    rows = spark.range(n).select(F.col("id").alias("_id"), (F.col("id") % 3 == 0).alias("_bad"), F.lit(100).cast("long").alias("n_words"), F.when(F.col("id") % 3 == 0, 30).otherwise(0).cast("long").alias("n_symbols"), *none)
    counted, path_of = [], quality_rules.path_of
    monkeypatch.setattr(quality_rules, "path_of", lambda grouped, worth: counted.append(grouped) or path_of(grouped, worth))
    path = quality_rules.tuned(rows)
    assert sum(b for b, _ in counted[0].values()) == n // 3 and sum(g for _, g in counted[0].values()) == n - n // 3
    assert path and path[0]["symbols"] < 0.3


@pytest.mark.parametrize("key", ["branchy_ifq_7_nested", "branchy_star_joins", "branchy_star_joins_double", "branchy_star_nested", "deep_ifq_0_nested", "deep_ifq_7_nested"])
def test_runs_of_sources_are_derived_by_each_query(spark, key):
    """Only the first query of an application read documents, and the others what that one had written."""
    files = lambda: {os.path.basename(os.path.dirname(f)) if os.path.basename(f).startswith("part-") else os.path.basename(f) for f in df.inputFiles()}
    for _ in range(2):
        df = workloads.QUERIES[key](spark, SF)
        assert "documents.parquet" in files()


def test_tiles_keep_the_pairs_of_a_join(spark, monkeypatch):
    """the pairs of one long chain were one task's, and copies of the nested method's nodes were collected to broadcast them."""
    monkeypatch.setattr(allpairs, "SIDE", 16)
    data = runs.CARRIERS["documents"].build(spark, SF)
    rows = lambda x: sorted(map(tuple, x.select("run_id", "src", "dst").collect()))
    plan = compile_rpq(data.spec, "split*")
    found = rows(allpairs.state_set(data.nodes, plan))
    assert rows(allpairs.filtered(data.nodes, plan)) == found and len(set(found)) == len(found)
    crawl = runs.CARRIERS["crawl"].build(spark, SF)
    some = crawl.part(["seed", "fetch"])
    walked = rows(general.evaluate(crawl, "_*", some, None, "walk"))
    assert rows(general.evaluate(crawl, "_*", some, None, "state_set")) == walked


def test_the_first_edge_of_a_tag_is_enough(spark):
    """Matches were joined through every edge of the tag on their way."""
    crawl = runs.CARRIERS["crawl"].build(spark, SF)
    l1, l2 = crawl.part(["seed", "fetch"]), crawl.part(["store", "stop"])
    found = general._until(crawl, ["upgrade"], l1, None)
    assert found.groupBy("run_id", "src").count().where("count > 1").count() == 0
    rows = lambda x: sorted(map(tuple, x.select("run_id", "src", "dst").collect()))
    walked = rows(general.evaluate(crawl, "_*.upgrade._*", l1, l2, "walk"))
    assert walked and rows(general.evaluate(crawl, "_*.upgrade._*", l1, l2, "decompose")) == walked
    assert rows(general.evaluate(crawl, "_*.upgrade._*", l1, l2, "decompose_runs")) == walked


@pytest.mark.parametrize("mode", ["linear", "semi", "double"])
def test_closures_of_trees_take_few_rounds(spark, mode):
    """A chain took a round for each of its steps, or joined all that was found with itself."""
    from wfpath.operators import baseline

    rows = lambda x: sorted(map(tuple, x.collect()))
    tree = [("r", f"{i}", f"{i + 1}") for i in range(70)] + [("r", f"{i}", f"{i}.x") for i in range(70)] + [("s", "0", "1"), ("s", "1", "2")]
    above = {(r, v): (u, r) for r, u, v in tree}
    expected = []
    for r, _, v in tree:
        at = (r, v)
        while at in above:
            expected.append((r, above[at][0], v))
            at = (r, above[at][0])
    counter = baseline.Rounds()
    down = baseline.closure(spark.createDataFrame(tree, "run_id string, src string, dst string"), mode, counter)
    assert rows(down) == sorted(expected) and counter.rounds <= 9
    up = baseline.closure(spark.createDataFrame([(r, v, u) for r, u, v in tree], "run_id string, src string, dst string"), mode)
    assert rows(up) == sorted((r, v, u) for r, u, v in expected)
    # a cycle, a diamond and a node by itself
    for edges in ([("r", "a", "b"), ("r", "b", "c"), ("r", "c", "a")], [("r", "a", "b"), ("r", "a", "c"), ("r", "b", "d"), ("r", "c", "d"), ("r", "d", "e")], [("r", "a", "a")]):
        found = {(u, v) for _, u, v in edges}
        while more := {(u, y) for u, v in found for x, y in found if v == x} - found:
            found |= more
        assert rows(baseline.closure(spark.createDataFrame(edges, "run_id string, src string, dst string"), mode)) == sorted(("r", u, v) for u, v in found)


def test_a_walk_within_tasks_is_the_walk_by_hops(spark, monkeypatch):
    """each step of a walk over short runs was joined, compared and stored, and walks began at many edges instead of few nodes."""
    from wfpath.operators import baseline

    events = runs.CARRIERS["events"].build(spark, SF)
    l1, l2 = events.part(["begin"]), events.part(["end", "leave"])
    rows = lambda x: sorted(map(tuple, x.select("run_id", "src", "dst").collect()))
    query = "_*.error.retry._*.(click|STEP)*"
    starts, walk = [], baseline.product_walk
    monkeypatch.setattr(baseline, "product_walk", lambda nodes, edges, dfa, a=None, b=None, counter=None: starts.append(a.count()) or walk(nodes, edges, dfa, a, b, counter))
    found = rows(general.evaluate(events, "_*.error._*", l1, l2, "rare_tag"))
    assert found and max(starts) <= max(l1.count(), l2.count()) and starts[0] == l1.count()
    monkeypatch.setattr(baseline, "product_walk", walk)
    assert rows(general.evaluate(events, "_*.error._*", l1, l2, "walk")) == found
    within = rows(general.evaluate(events, query, l1, None, "walk"))
    monkeypatch.setattr(baseline, "ROWS", 50)
    monkeypatch.setattr(baseline, "PLACES", 300)
    assert rows(general.evaluate(events, query, l1, None, "walk")) == within and len(set(within)) == len(within)
    # runs with more edges go by hops, and both kinds at once are all
    n = [r["n"] for r in events.edges.groupBy("run_id").agg(F.count(F.lit(1)).alias("n")).collect()]
    monkeypatch.setattr(baseline, "WITHIN", sorted(n)[len(n) // 2])
    assert rows(general.evaluate(events, query, l1, None, "walk")) == within


def test_a_list_of_one_node_a_run_is_decided_by_pairs(spark, monkeypatch, tmp_path):
    """all nodes were written, and copied by levels and places of their chains to meet the one node of a run."""
    data = runs.CARRIERS["full_orders"].stored(spark, SF, f"file://{tmp_path}/run")
    l1, l2 = data.part(["open"]), data.part(["close"])
    rows = lambda x: sorted(map(tuple, x.select("run_id", "src", "dst").collect()))
    walked = rows(general.evaluate(runs.CARRIERS["full_orders"].build(spark, SF), "_*.(hold|inspect)._*", l1, l2, "walk"))
    used = []
    nested, state_set = allpairs.nested, allpairs.state_set
    monkeypatch.setattr(allpairs, "nested", lambda *a, **k: used.append("nested") or nested(*a, **k))
    monkeypatch.setattr(allpairs, "state_set", lambda *a, **k: used.append("state_set") or state_set(*a, **k))
    assert walked and rows(general.evaluate(data, "_*.(hold|inspect)._*", l1, l2, "decompose")) == walked
    assert used == ["nested", "nested"]
    assert not os.path.exists(tmp_path / "run" / "nodes")


@pytest.mark.parametrize("mode", ["linear", "semi", "double"])
def test_hops_of_short_runs_are_no_jobs(spark, monkeypatch, mode):
    """each hop and each round of a closure was a job and a folder, and all nodes with labels and all edges were written before."""
    from wfpath.operators import baseline

    rows = lambda x: sorted(map(tuple, x.collect()))
    tree = [("r", f"{i}", f"{i + 1}") for i in range(70)] + [("r", f"{i}", f"{i}.x") for i in range(70)] + [("s", "0", "1"), ("s", "1", "2"), ("t", "0", "0.x"), ("t", "0", "0.y")]
    for turned in (False, True):
        pairs = spark.createDataFrame([(r, v, u) if turned else (r, u, v) for r, u, v in tree], "run_id string, src string, dst string")
        steps = {}
        for r, u, v in tree:
            steps.setdefault((r, u), []).append(v)
        beyond = lambda r, x: [y for v in steps.get((r, x), []) for y in [v, *beyond(r, v)]]  # noqa: B023, E731
        expected = sorted((r, y, u) if turned else (r, u, y) for r, u in steps for y in beyond(r, u))
        written, cut = [], baseline.cut
        with monkeypatch.context() as m:
            m.setattr(baseline, "Pile", None)
            m.setattr(baseline, "cut", lambda df: written.append(1) or cut(df))
            assert rows(baseline.closure(pairs, mode)) == expected and len(written) == 1
    # a null is no node to go on from
    if mode != "double":
        return
    odd = spark.createDataFrame([("r", f"{i}", f"{i + 1}") for i in range(40)] + [("r", None, "0"), ("r", "40", None), (None, "0", "1")], "run_id string, src string, dst string")
    assert baseline.closure(odd, mode).count() == 40 * 41 // 2 + 41 + 41 + 1 + 1


def test_joins_derive_only_the_tags_of_their_query(spark, tmp_path):
    """all nodes with labels and all edges were written for the edges of one tag."""
    data = runs.CARRIERS["documents"].stored(spark, SF, f"file://{tmp_path}/run")
    whole = runs.CARRIERS["documents"].build(spark, SF)
    rows = lambda x: sorted(map(tuple, x.select("run_id", "src", "dst").collect()))
    found = rows(general.evaluate(data, "split*", method="joins_double"))
    assert os.listdir(tmp_path / "run") == ["edges-split"]
    assert found == rows(general.evaluate(whole, "split*", method="state_set"))
    for query in ("split.(read|split)+", "_.tokenise", "()|read", "split?._"):
        assert rows(general.evaluate(data, query, method="joins")) == rows(general.evaluate(whole, query, method="walk"))


def test_a_cleaned_run_is_written_anew(spark, tmp_path):
    """F8: after a cleaning, rows of one kind were written where all kinds have their folders."""
    import shutil

    whole = runs.CARRIERS["crawl"].build(spark, SF)
    data = runs.CARRIERS["crawl"].stored(spark, SF, f"file://{tmp_path}/run")
    key = lambda x: sorted(map(repr, x.select("run_id", "src", "dst").collect()))

    def found():
        return key(general.evaluate(data, "_*.upgrade._*", data.part(["seed", "fetch"]), data.part(["store", "stop"]), "auto"))

    expected = key(general.evaluate(whole, "_*.upgrade._*", whole.part(["seed", "fetch"]), whole.part(["store", "stop"]), "walk"))
    assert found() == expected
    for _ in range(2):
        for folder in os.listdir(tmp_path):
            shutil.rmtree(tmp_path / folder)
        assert found() == expected and found() == expected
        kinds = {x for folder in os.listdir(tmp_path) for x in os.listdir(tmp_path / folder)}
        assert all(x.startswith(("nodes", "edges")) for x in kinds)


def test_pieces_are_coded_once_in_a_process(monkeypatch):
    """op6_token_files: each slice of texts had all its pieces coded again."""
    import numpy as np
    import pyarrow as pa

    from wfpath.llm import tokens

    texts = pa.array(["one two three don't x9", None, "two été  three; four", "", "ONE four five (five) seven"])
    plain = tokens.Encoder(tokens.VOCABULARY)
    expected = [plain.tokenizer.encode(t.as_py() or "", add_special_tokens=False).ids + [2] for t in texts]
    coded, old = [], tokens.Encoder.coded
    monkeypatch.setattr(tokens.Encoder, "coded", lambda self, pieces: coded.extend(pieces) or old(self, pieces))
    for most, again in ((tokens.KEPT, False), (9, True), (2, True)):
        monkeypatch.setattr(tokens, "KEPT", most)
        monkeypatch.setattr(tokens, "_encoders", {})
        coded.clear()
        for a, b in ((0, 5), (2, 5), (0, 2), (0, 5)):
            ids, at = tokens.encode(texts.slice(a, b - a), 2)
            got = [x.tolist() for x in np.split(ids, at[1:-1])]
            assert got == expected[a:b]
        assert (len(coded) > len(set(coded))) == again
