"""What the reviewer's third round found: paths of a fork's tag over long runs."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from wfpath.functions.labels import Decoder
from wfpath.operators import allpairs, general, tiles
from wfpath.plans.safety import compile_rpq
from wfpath.sources import runs

SF = "/root/testdata/sf0.001"
rows = lambda x: sorted(map(tuple, x.select("run_id", "src", "dst").collect()))


@pytest.mark.parametrize("carrier, query", [("documents", "split*"), ("documents", "_*"), ("talks", "_*.start._*"), ("talks", "TURN*"), ("talks", "(TURN|note|hear|say|think|configure)*"), ("supply", "_*.hub._*.gate._*"), ("supply", "split*"), ("crawl", "HOP"), ("example", "A+")])
def test_pairs_within_tiles_are_those_of_the_columns(spark, monkeypatch, carrier, query):
    """the nested method joined each pair of nodes with both labels and decoded these again for it."""
    data = runs.CARRIERS[carrier].build(spark, SF)
    plan = compile_rpq(data.spec, query)
    few = data.nodes.where(F.pmod(F.xxhash64("run_id"), F.lit(1 if carrier in ("documents", "supply", "example") else 7)) == 0)
    expected = rows(allpairs.nested(few, plan, short=True))
    assert expected == rows(allpairs.nested(few, plan))
    monkeypatch.setattr(tiles, "LARGE", 4)
    monkeypatch.setattr(tiles, "ONCE", 50)
    monkeypatch.setattr(tiles, "CELLS", 40)
    t = tiles.Tables.of(Decoder(plan))
    d = Decoder(plan)
    from wfpath.functions.labels import pack
    from wfpath.operators.pairwise import masked

    own = few.select("run_id").distinct().limit(3)
    some = few.join(own, "run_id", "left_semi")
    both = masked(some, d).select("run_id", "node_id", pack(F.col("label")).alias("label"), "exits", "entries").toArrow()
    both = both.append_column("tile", both["run_id"])
    one = lambda k, masks: both.select(["tile", "run_id", "node_id", "label"]).append_column("side", pa.array(np.full(len(both), k, np.int8))).append_column("masks", both[masks])
    held = pa.concat_tables([one(0, "exits"), one(1, "entries")]).sort_by([("tile", "ascending"), ("label", "ascending")])
    found = sorted(tuple(x.values()) for b in tiles.pairs_of(held, t) for x in b.to_pylist())
    kept = set(map(tuple, own.collect()))
    assert found == [x for x in expected if (x[0],) in kept]


@pytest.mark.parametrize("mode", ["linear", "semi", "double"])
def test_ways_are_shuffled_as_lists(spark, monkeypatch, mode):
    """short and long ways of a run were shuffled, a row for each, and runs of over 65,536 edges stored theirs round by round."""
    from wfpath.operators import baseline, walks

    edges = [("r", str(i), str(i + 1)) for i in range(300)] + [("r", str(i), f"{i}.x") for i in range(300)] + [("r", "40", f"y{i}") for i in range(30)] + [("s", "0", "1"), ("t", "a", "b"), ("t", "b", "c"), ("t", "b", "d")]
    expected, above = [], {(r, v): u for r, u, v in edges}
    for r, _, v in edges:
        at = v
        while (at := above.get((r, at))) is not None:
            expected.append((r, at, v))
    for block, ends, at, some in ((9, 2048, 1 << 15, 1 << 12), (2, 7, 13, 5)):
        for name, value in (("BLOCK", block), ("ENDS", ends), ("AT", at), ("TILES", some)):
            monkeypatch.setattr(walks, name, value)
        for turned in (False, True):
            of = sorted((r, v, u) if turned else (r, u, v) for r, u, v in edges)
            table = pa.table([list(x) for x in zip(*of, strict=True)], names=["run_id", "src", "dst"])
            near = [tuple(x.values()) for b in walks.near(table, mode) for x in b.to_pylist()]
            tiled = [x for b in walks.far(table, mode) for x in b.to_pylist()]
            found = near + [(x["run_id"], u, v) for x in tiled for u in x["srcs"] for v in x["dsts"]]
            assert sorted(found) == sorted((r, v, u) if turned else (r, u, v) for r, u, v in expected)
    # few rows are shuffled, and no round is a folder, for a run of over 65,536 edges too
    assert baseline.HELD > 1 << 16
    long = spark.range(3000).select(F.lit("r").alias("run_id"), F.col("id").cast("string").alias("src"), (F.col("id") + 1).cast("string").alias("dst"))
    monkeypatch.setattr(baseline, "Pile", None)
    found = baseline.closure(long, mode)
    assert found.count() == 3000 * 3001 // 2 and "Join" not in found._jdf.queryExecution().optimizedPlan().toString()


@pytest.mark.parametrize("carrier, query", [("documents", "split*"), ("talks", "(TURN|note|hear|say|think|configure)*"), ("crawl", "_*.HOPS._*")])
def test_pairs_that_meet_are_tested_within_tiles(spark, monkeypatch, carrier, query):
    """each pair that met was a row with both labels and masks, and these were decoded again for it."""
    monkeypatch.setattr(allpairs, "FULL", 5)
    monkeypatch.setattr(allpairs, "WIDE", 7)
    monkeypatch.setattr(allpairs, "PARTS", 3)
    data = runs.CARRIERS[carrier].build(spark, SF)
    plan = compile_rpq(data.spec, query)
    few = data.nodes.where(F.pmod(F.xxhash64("run_id"), F.lit(1 if carrier == "documents" else 7)) == 0)
    found = allpairs.filtered(few, plan)
    assert rows(found) == rows(allpairs.nested(few, plan)) == rows(allpairs.nested(few, plan, short=True))
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInArrow" in plan and "vlabel" not in plan.split("MapInArrow")[0]
