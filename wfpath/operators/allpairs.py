"""All matching pairs out of two node lists, for safe queries.

``nested`` tests every pair of a run; ``filtered`` first enumerates reachable pairs from the
labels' levels and tests those; ``state_set`` groups nodes by ancestor and state mask, decides on
groups, and expands only the groups that match, or counts without expanding.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wfpath.functions.labels import Decoder, constants, levels, pack, reach_table
from wfpath.operators.pairwise import decided, masked
from wfpath.operators.tiles import Tables
from wfpath.plans.safety import SafePlan
from wfpath.plans.spec import Spec

PAIR = ["run_id", "src", "dst"]


def listed(nodes: DataFrame, part: DataFrame | None) -> DataFrame:
    """The labelled nodes of a list (all nodes if it is None), each once.

    A list with a column ``label`` has to be a choice of the run's own nodes, each once: it is taken as it is.
    """
    if part is not None and "label" in part.columns:
        return part.select("run_id", "node_id", "label")
    own = nodes.select("run_id", "node_id", "label")
    if part is None:
        return own
    return own.join(part.select("run_id", "node_id").dropDuplicates(), ["run_id", "node_id"], "left_semi")


#: Rows of each list in a tile of a join; nodes of each list in a tile whose pairs are tested within a task, if most are found and
#: if few are; and into how many parts a list is cut for these at most, as every part of one is copied for each of the other.
SIDE, FULL, WIDE, PARTS = 1024, 2048, 4096, 64


def nested(nodes: DataFrame, plan: SafePlan, l1: DataFrame | None = None, l2: DataFrame | None = None, side: int | None = None, short: bool = False) -> DataFrame:
    """Every pair of nodes of a run, tested by labels; the work is |l1| times |l2| in each run.

    Both lists of a run are cut by their counted sizes into parts of about ``side`` nodes, and each
    pair of parts is a tile, so a run of any size spreads over tasks; a run of one tile copies nothing.
    ``short``: the runs' lists are short, so that pairs are rows of a join.
    """
    decoder = Decoder(plan)
    u0, v0 = listed(nodes, l1), listed(nodes, l2)
    label = F.col("label") if short else pack(F.col("label"))
    u = masked(u0, decoder, entries=False).select("run_id", F.col("node_id").alias("src"), label.alias("ulabel"), "exits")
    v = masked(v0, decoder, exits=False).select("run_id", F.col("node_id").alias("dst"), label.alias("vlabel"), "entries")
    if not short:
        return _tested(u, v, _grid(u0, v0, ["run_id"], side or WIDE, PARTS), decoder)
    pairs = _tiled(u, v, _grid(u0, v0, ["run_id"], side or SIDE))
    return pairs.where(decided(pairs, decoder)).select(*PAIR)


def _grid(u: DataFrame, v: DataFrame, on: list[str], side: int = SIDE, most: int = 1 << 30) -> DataFrame:
    """For each key that both have: into how many parts of about ``side`` rows, or ``most`` parts, its rows are cut on either side."""
    parts = lambda x, name: x.groupBy(*on).agg(F.least(F.ceil(F.count(F.lit(1)) / side), F.lit(most)).cast("int").alias(name))
    return parts(u, "rows").join(parts(v, "columns"), on)


def _copies(u: DataFrame, v: DataFrame, grid: DataFrame) -> tuple[DataFrame, DataFrame, list[str], int]:
    """Rows of either side (with src, with dst) for each tile of their keys, the tiles' columns, and a number of partitions.

    Each pair of parts is a tile, so keys of any size spread over tasks; a key of one tile copies nothing.
    ``grid`` has keys of either side, rows and columns.
    """
    keys = [c for c in grid.columns if c not in ("rows", "columns")]
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    u = u.join(grid, [k for k in keys if k in u.columns]).withColumn("_row", F.pmod(F.xxhash64("src"), F.col("rows")).cast("int")).withColumn("_column", every("columns")).drop("rows", "columns")
    v = v.join(grid, [k for k in keys if k in v.columns]).withColumn("_column", F.pmod(F.xxhash64("dst"), F.col("columns")).cast("int")).withColumn("_row", every("rows")).drop("rows", "columns")
    # a number is named, as adaptive planning would else put these few rows with their many pairs into one task
    return u, v, [*keys, "_row", "_column"], max(32, int(grid.sparkSession.conf.get("spark.sql.shuffle.partitions")))


def _tiled(u: DataFrame, v: DataFrame, grid: DataFrame) -> DataFrame:
    """Every pair of rows (with src, with dst) of the same keys."""
    u, v, on, n = _copies(u, v, grid)
    # the join is named, as the planner doesn't count copies and would collect them on the driver to broadcast them
    return u.repartition(n, *on).join(v.hint("merge"), on)


def _tested(u: DataFrame, v: DataFrame, grid: DataFrame, decoder: Decoder) -> DataFrame:
    """The pairs of rows (src, packed ulabel, exits; dst, packed vlabel, entries) of the same keys that match.

    The rows of a tile come to a task once, and each pair of them is tested there.
    """
    from wfpath.operators.baseline import ROWS, _whole_runs

    u, v, on, n = _copies(u, v, grid)
    # numbers, then bytes as digits, and the run's name last: no two tiles have one name
    kinds = dict(u.dtypes)
    named = sorted((c for c in on if c != "run_id"), key=lambda c: kinds[c] == "binary")
    tile = F.concat(*[x for c in named for x in (F.hex(c) if kinds[c] == "binary" else F.col(c).cast("string"), F.lit("."))], "run_id")
    row = lambda x, side, name, label, masks: x.select(tile.alias("tile"), F.lit(side).cast("tinyint").alias("side"), "run_id", F.col(name).alias("node_id"), F.col(label).alias("label"), F.col(masks).alias("masks"))
    rows = row(u, 0, "src", "ulabel", "exits").union(row(v, 1, "dst", "vlabel", "entries")).where("tile IS NOT NULL AND label IS NOT NULL")
    tables, most = Tables.of(decoder), ROWS

    def of(held):
        from wfpath.operators.tiles import pairs_of

        return pairs_of(held, tables)

    return rows.repartition(n, "tile").sortWithinPartitions("tile", "label").mapInArrow(_whole_runs(of, most, "tile"), "run_id string, src string, dst string")


def crossed(tiles: DataFrame) -> DataFrame:
    """Every pair of the tiles' lists (srcs, dsts)."""
    return tiles.select("run_id", F.explode("srcs").alias("src"), "dsts").select("run_id", "src", F.explode("dsts").alias("dst"))


def _bits(of: str, upto: str, value: int) -> str:
    """The places up to the top bit of ``upto`` at which ``of`` has this bit."""
    return f"filter(sequence(0, length(bin({upto})) - 1), k -> (shiftright({of}, k) & 1) = {value})"


def lower_half(rows: DataFrame, at: str, tops: DataFrame, keys: list[str]) -> DataFrame:
    """Rows with a ``mid`` for each larger place they can meet: see ``upper_half``.  ``tops`` has the largest place (top) by keys."""
    x = rows.join(tops, keys).where(f"{at} < top")
    return x.withColumn("mid", F.explode(F.expr(f"filter(transform({_bits(at, 'top', 0)}, k -> shiftleft(shiftright({at}, k) | 1, k)), m -> m <= top)"))).drop("top")


def upper_half(rows: DataFrame, at: str) -> DataFrame:
    """Rows with a ``mid`` for each smaller place they can meet.

    Two places i < j share exactly one mid: what their leading bits have in common, then 1, then
    zeros.  So ``i < j`` becomes an equi-join on mid, where every pair that meets is a pair that is
    wanted, and a row is copied at most once for each bit of a place.
    """
    return rows.withColumn("mid", F.explode(F.expr(f"transform({_bits(at, at, 1)}, k -> shiftleft(shiftright({at}, k), k))")))


def _targets(spec: Spec, what: str):
    """Positions that a body position reaches, as an exploded column."""
    first, width, _ = reach_table(spec)
    flat: list[str] = []
    for p in spec.productions:
        for i in range(1, len(p.body) + 1):
            flat.append(" ".join(str(j) for j in range(1, len(p.body) + 1) if (i, j) in p.reach))
    # rows of bodies stand one after another
    starts = [0]
    for p in spec.productions:
        starts.append(starts[-1] + len(p.body))
    rows = F.split(F.lit(";".join(flat)), ";")
    at = F.get(constants([0, *starts[:-1]]), F.col(f"{what}.a")) + F.col(f"{what}.b") - 1
    row = F.get(rows, at.cast("int"))
    return F.when(row != "", F.split(row, " ").cast("array<int>"))


def met(u: DataFrame, v: DataFrame, spec: Spec, keep: tuple[str, ...] = (), d: Decoder | None = None) -> DataFrame:
    """Level rows of two lists that meet on a path: each reachable pair of different nodes once.

    Within a body the rows of the first list are multiplied by the positions they reach, so the meeting is
    an equi-join; in a chain only nodes that lead to the recursive slot (red) meet later members, and
    later members meet only nodes behind the slot (blue), by halves of ranges of members, so that only pairs
    that are found are ever joined.  ``keep``: columns of either list that tests need.  With a decoder, rows
    (with mask and inner) that have no state left where they meet are dropped before, and each pair that meets is
    tested by its labels within a task.
    """
    own = lambda x, name, *more: x.select("run_id", F.col("node_id").alias(name), *more, *[c for c in keep if c in x.columns])
    alive = lambda x, m: x if d is None else x.where(m() != 0)
    body_u = u.where("entry.kind = 0").withColumn("j", F.explode(_targets(spec, "entry"))).withColumn("k", F.col("entry.a"))
    body_u = alive(body_u, lambda: d.same_body(F.col("mask"), F.col("k"), F.col("entry.b"), F.col("j")))
    body_v = alive(v.where("entry.kind = 0").withColumn("j", F.col("entry.b")).withColumn("k", F.col("entry.a")), lambda: F.col("mask"))

    def joined(x: DataFrame, y: DataFrame, on: list[str]) -> DataFrame:
        left, right = own(x, "src", *on[1:]), own(y, "dst", *on[1:])
        return _tiled(left, right, _grid(x, y, on)).select(*PAIR) if d is None else _tested(left, right, _grid(x, y, on, FULL, PARTS), d)

    body = joined(body_u, body_v, ["run_id", "prefix", "k", "j"])
    if not spec.cycles:
        return body
    on = ["run_id", "prefix", "s", "t"]
    chain = lambda x, c, m: alive(x.where(f"entry.kind = 1{c}"), m).select("run_id", "node_id", "prefix", F.col("entry.a").alias("s"), F.col("entry.b").alias("t"), F.col("entry.idx").alias("i"), *[k for k in keep if k in x.columns])
    tops = lambda x: x.groupBy(*on).agg(F.max("i").alias("top"))
    a, b = F.col("onward.a"), F.col("onward.b")
    slot = lambda: F.get(d.slots, a)
    red = chain(u, " AND colour = 'red'", lambda: d.same_body(F.col("inner"), a, b, slot()))
    blue = chain(v, " AND colour = 'blue'", lambda: d.between.backward(F.col("inner"), d.pair(a, slot(), b)))
    us, vs = chain(u, "", lambda: F.col("mask")), chain(v, "", lambda: F.col("mask"))
    later = joined(lower_half(red, "i", tops(vs), on), upper_half(vs, "i"), [*on, "mid"])
    earlier = joined(upper_half(us, "i"), lower_half(blue, "i", tops(us), on), [*on, "mid"])
    return body.union(later).union(earlier)


def reachable(nodes: DataFrame, spec: Spec, l1: DataFrame | None = None, l2: DataFrame | None = None) -> DataFrame:
    """All pairs (run_id, src, dst) with a path, each once; a node reaches itself."""
    u, v = listed(nodes, l1), listed(nodes, l2)
    same = u.select("run_id", "node_id").intersect(v.select("run_id", "node_id")) if l1 is not None or l2 is not None else u.select("run_id", "node_id")
    slim = lambda x: levels(x, spec).select("run_id", "node_id", "prefix", "entry", "colour")
    return met(slim(u), slim(v), spec).union(same.select("run_id", F.col("node_id").alias("src"), F.col("node_id").alias("dst")))


def filtered(nodes: DataFrame, plan: SafePlan, l1: DataFrame | None = None, l2: DataFrame | None = None) -> DataFrame:
    """Reachable pairs from the levels, each tested by labels; nodes carry these to where they meet, so none is looked up again.

    Nodes that have no state left on the level where they would meet don't meet.
    """
    from wfpath.operators.baseline import cut

    spec, d = plan.spec, Decoder(plan)
    u0, v0 = cut(masked(listed(nodes, l1), d, entries=False)), cut(masked(listed(nodes, l2), d, exits=False))
    slim = ["run_id", "node_id", "prefix", "entry", "onward", "colour", "mask", "inner"]
    at = lambda x, masks, label: levels(x, spec).withColumn("mask", F.get(masks, F.col("depth"))).withColumn("inner", F.get(masks, F.col("depth") + 1)).select(*slim, pack(F.col("label")).alias(label), masks)
    found = met(at(u0, "exits", "ulabel"), at(v0, "entries", "vlabel"), spec, ("ulabel", "exits", "vlabel", "entries"), d)
    if not d.accepts_empty:
        return found
    both = u0.select("run_id", "node_id").intersect(v0.select("run_id", "node_id"))
    return found.union(both.select("run_id", F.col("node_id").alias("src"), F.col("node_id").alias("dst")))


def state_set(nodes: DataFrame, plan: SafePlan, l1: DataFrame | None = None, l2: DataFrame | None = None, output: str = "pairs", empty: bool = True) -> DataFrame:
    """Matching pairs by groups of nodes with the same ancestor and the same state mask.

    ``output``: pairs; count (rows run_id, n); exists (runs with a match); sources; targets.
    ``empty``: whether a node of both lists matches itself where the query has the empty word.

    In a chain the masks of both sides are carried to the middle of the range of members where they
    meet, and grouped there: the groups that meet are as many as there are different masks, however
    long the chain, and all outputs but pairs take time in proportion to its length and its bits.
    """
    from wfpath.operators.baseline import cut

    spec, d = plan.spec, Decoder(plan)
    # masks are written once, as each kind of meeting reads them again
    u0 = cut(masked(listed(nodes, l1), d, entries=False))
    v0 = cut(masked(listed(nodes, l2), d, exits=False))
    u = levels(u0, spec).withColumn("mask", F.get("exits", F.col("depth"))).withColumn("inner", F.get("exits", F.col("depth") + 1))
    v = levels(v0, spec).withColumn("mask", F.get("entries", F.col("depth"))).withColumn("inner", F.get("entries", F.col("depth") + 1))
    # states that can still matter; what has none is dropped before the join
    body_u = u.where("entry.kind = 0 AND mask <> 0").withColumn("j", F.explode(_targets(spec, "entry"))).withColumn("k", F.col("entry.a"))
    body_u = body_u.withColumn("m", d.same_body(F.col("mask"), F.col("k"), F.col("entry.b"), F.col("j"))).where("m <> 0")
    body_v = v.where("entry.kind = 0 AND mask <> 0").withColumn("k", F.col("entry.a")).withColumn("j", F.col("entry.b")).withColumn("m", F.col("mask"))
    kinds = [(body_u, body_v, ["k", "j"])]
    if spec.cycles:
        a, b = F.col("onward.a"), F.col("onward.b")
        slot = F.get(d.slots, a)
        on = ["run_id", "prefix", "s", "t"]
        chain = lambda x, m: x.withColumn("s", F.col("entry.a")).withColumn("t", F.col("entry.b")).withColumn("i", F.col("entry.idx")).withColumn("m", m).where("m <> 0").select("run_id", "node_id", *on[1:], "i", "m")
        tops = lambda x: x.groupBy(*on).agg(F.max("i").alias("top"))
        # red: states on entering the next member; blue: states on leaving the next member from which the node is reached
        red = chain(u.where("entry.kind = 1 AND colour = 'red'"), d.same_body(F.col("inner"), a, b, slot))
        blue = chain(v.where("entry.kind = 1 AND colour = 'blue'"), d.between.backward(F.col("inner"), d.pair(a, slot, b)))
        us, vs = chain(u.where("entry.kind = 1"), F.col("mask")), chain(v.where("entry.kind = 1"), F.col("mask"))
        s, t, i, mid, n = F.col("s"), F.col("t"), F.col("i"), F.col("mid"), d.length(F.col("s"))
        into, outof = lambda x: (t + x - 2 + n) % n, lambda x: (t + x - 3 + n) % n
        carried = lambda x, m: x.withColumn("m", m).where("m <> 0").drop("i")
        later_u = carried(lower_half(red, "i", tops(vs), on), d.enter.forward(F.col("m"), d.steps("enter", s, into(i + 1), mid - 1 - i)))
        later_v = carried(upper_half(vs, "i"), d.enter.backward(F.col("m"), d.steps("enter", s, into(mid), i - mid)))
        earlier_u = carried(upper_half(us, "i"), d.leave.forward(F.col("m"), d.steps("leave", s, outof(i), i - mid)))
        earlier_v = carried(lower_half(blue, "i", tops(us), on), d.leave.backward(F.col("m"), d.steps("leave", s, outof(mid), mid - 1 - i)))
        kinds += [(later_u, later_v, ["s", "t", "mid"]), (earlier_u, earlier_v, ["s", "t", "mid"])]
    found = None
    for left, right, keys in kinds:
        on = ["run_id", "prefix", *keys]
        gu = left.groupBy(*on, F.col("m").alias("mu")).agg(F.count(F.lit(1)).alias("nu"))
        gv = right.groupBy(*on, F.col("m").alias("mv")).agg(F.count(F.lit(1)).alias("nv"))
        g = gu.join(gv, on).where(F.col("mu").bitwiseAND(F.col("mv")) != 0)
        lu = left.select(*on, F.col("m").alias("mu"), F.col("node_id").alias("src"))
        rv = right.select(*on, F.col("m").alias("mv"), F.col("node_id").alias("dst"))
        if output == "count":
            part = g.groupBy("run_id").agg(F.sum(F.col("nu") * F.col("nv")).alias("n"))
        elif output == "exists":
            part = g.select("run_id").distinct()
        elif output == "sources":
            part = lu.join(g.select(*on, "mu").distinct(), [*on, "mu"], "left_semi").select("run_id", F.col("src").alias("node_id"))
        elif output == "targets":
            part = rv.join(g.select(*on, "mv").distinct(), [*on, "mv"], "left_semi").select("run_id", F.col("dst").alias("node_id"))
        else:
            parts = lambda n: F.ceil(F.col(n) / SIDE).cast("int")
            part = _tiled(lu, rv, g.select(*on, "mu", "mv", parts("nu").alias("rows"), parts("nv").alias("columns"))).select(*PAIR)
        found = part if found is None else found.union(part)
    if d.accepts_empty and empty:
        both = u0.select("run_id", "node_id").intersect(v0.select("run_id", "node_id"))
        if output == "count":
            found = found.union(both.groupBy("run_id").agg(F.count(F.lit(1)).alias("n")))
        elif output == "exists":
            found = found.union(both.select("run_id"))
        elif output in ("sources", "targets"):
            found = found.union(both)
        else:
            found = found.union(both.select("run_id", F.col("node_id").alias("src"), F.col("node_id").alias("dst")))
    if output == "count":
        return found.groupBy("run_id").agg(F.sum("n").cast("long").alias("n"))
    if output == "exists":
        return found.distinct()
    return found.distinct() if output in ("sources", "targets") else found
