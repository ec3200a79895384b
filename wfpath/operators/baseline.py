"""The methods compared with: product walks over the run, parse-tree joins, rare tags, tag index."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wfpath.operators import allpairs
from wfpath.plans import rpq
from wfpath.plans.rpq import Dfa, Node
from wfpath.plans.spec import Spec
from wfpath.sources.runs import write_index

PAIR = ["run_id", "src", "dst"]
__all__ = ["PAIR", "Pile", "Rounds", "bounded_closure", "closure", "concatenated", "cut", "delta_table", "identity", "ifq_index", "indexed", "join_tree", "product_graph", "product_walk", "rare_tag", "shared_folder", "spread_from", "tag_counts", "write_index"]


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share; one of our own only in local sessions that name none (tests)."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir has to name a folder that all executors share")
    return "file://" + os.path.join(tempfile.gettempdir(), "wfpath-checkpoints")


def cut(df: DataFrame) -> DataFrame:
    """The rows written to the folder that all executors share, and read back: a loop's lineage ends there."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/rows-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


class Pile:
    """A table that a loop adds to: one folder, so that its plan stays one scan however many rounds there are."""

    def __init__(self, first: DataFrame) -> None:
        self.spark, self.schema = first.sparkSession, first.schema
        self.path = f"{shared_folder(self.spark)}/pile-{uuid.uuid4().hex}"
        self.parts = 0
        self.add(first)

    def add(self, df: DataFrame) -> DataFrame:
        """Adds rows; gives just these back, from the folder."""
        path = f"{self.path}/part={self.parts}"
        df.write.parquet(path)
        self.parts += 1
        return self.spark.read.schema(self.schema).parquet(path)

    def rows(self) -> DataFrame:
        return self.spark.read.schema(self.schema).option("recursiveFileLookup", "true").parquet(self.path)


def _empty(df: DataFrame) -> bool:
    return df.limit(1).count() == 0


def delta_table(spark: SparkSession, dfa: Dfa) -> DataFrame:
    return spark.createDataFrame(dfa.table() or [(-1, "", -1)], "q int, tag string, q2 int")


def product_graph(edges: DataFrame, dfa: Dfa) -> DataFrame:
    """The run with a port for each state: run_id, src, q, dst, q2, tag."""
    return edges.join(F.broadcast(delta_table(edges.sparkSession, dfa)), "tag").select("run_id", "src", "q", "dst", "q2", "tag")


#: A step's hops are squared while they have at most so many rows for each edge.
SHORTCUTS = 48
STATE = ["run_id", "at", "q"]


def spread_from(start: DataFrame, graph: DataFrame, most: int = SHORTCUTS, counter: Rounds | None = None) -> DataFrame:
    """Everything that is reached from ``start`` (run_id, src, at, q) over ``graph`` (run_id, at, q, dst, q2), start included.

    Squaring the graph gives hops of exactly 1, 2, 4, ... steps, until there are none as long or they
    grow large against the edges.  The longest are repeated from what they found last until they find
    nothing new; each shorter one then follows once, as any number of steps is some of the longest
    and a sum of different shorter ones.  In a chain hops never outgrow the edges, so the rounds grow
    with the logarithm of its length.
    """
    then = lambda x, y: x.select("run_id", F.col("at").alias("at0"), F.col("q").alias("q0"), F.col("dst").alias("at"), F.col("q2").alias("q")).join(y, STATE).select("run_id", F.col("at0").alias("at"), F.col("q0").alias("q"), "dst", "q2")
    hops = [cut(graph.select(*STATE, "dst", "q2").distinct())]
    edges = hops[0].count()
    size = edges
    while edges and size * 3 <= most * edges:
        longer = cut(then(hops[-1], hops[-1]).distinct())
        size = longer.count()
        if not size:
            break
        hops.append(longer)
        if counter is not None:
            counter.joins += 1
    seen = Pile(start.select("run_id", "src", "at", "q").distinct())

    def spread(front: DataFrame, hop: DataFrame) -> DataFrame:
        if counter is not None:
            counter.rounds += 1
            counter.joins += 1
        step = front.join(hop, STATE).select("run_id", "src", F.col("dst").alias("at"), F.col("q2").alias("q")).distinct()
        return seen.add(step.join(seen.rows(), ["run_id", "src", "at", "q"], "left_anti"))

    front = seen.rows()
    while not _empty(front := spread(front, hops[-1])):
        pass
    for hop in reversed(hops[:-1]):
        spread(seen.rows(), hop)
    return seen.rows()


#: A run is walked within one task if its edges times its starts are at most so many, ...
WITHIN = 4_000_000
#: ... with the runs beside it, of so many rows together, and so many starts at once that they have so many places to reach.
ROWS, PLACES = 200_000, 1 << 25


def product_walk(nodes: DataFrame | None, edges: DataFrame, dfa: Dfa, l1: DataFrame | None = None, l2: DataFrame | None = None, counter: Rounds | None = None) -> DataFrame:
    """Pairs found by walking the run and the automaton together from every source.

    A run of few edges and starts is walked within a task, so that only pairs leave it; the others by hops, several steps a
    round.  A first list that isn't the run's own (has no label) is met with ``nodes`` if these are given.
    """
    graph = product_graph(edges, dfa).select("run_id", F.col("src").alias("at"), "q", "dst", "q2")
    begin = (nodes if l1 is None else l1).select("run_id", F.col("node_id").alias("src")).dropDuplicates()
    if l1 is not None and nodes is not None and "label" not in l1.columns:
        begin = begin.join(nodes.select("run_id", F.col("node_id").alias("src")), ["run_id", "src"], "left_semi")
    counted = lambda x, name: x.groupBy("run_id").agg(F.count(F.lit(1)).alias(name))
    large = counted(edges, "n").join(counted(begin, "starts"), "run_id", "left").where(F.col("n") * F.greatest(F.lit(1), F.coalesce("starts", F.lit(1))) > WITHIN).select("run_id")
    if _empty(large := cut(large)):
        return _walk_within(graph, begin, l2, dfa)
    some = lambda x, how: None if x is None else x.join(large, "run_id", how)
    within = _walk_within(some(graph, "left_anti"), some(begin, "left_anti"), some(l2, "left_anti"), dfa)
    graph, begin = some(graph, "left_semi"), some(begin, "left_semi")
    seen = spread_from(begin.select("run_id", "src", F.col("src").alias("at"), F.lit(0).alias("q")), graph, counter=counter)
    found = seen.where(F.col("q").isin([*sorted(dfa.finals)]) if dfa.finals else F.lit(False)).select("run_id", "src", F.col("at").alias("dst")).distinct()
    return _to(found, l2).union(within)


def _walk_within(graph: DataFrame, begin: DataFrame, l2: DataFrame | None, dfa: Dfa) -> DataFrame:
    """The walk of whole runs in a task, some of them side by side: edges, starts and goals of a run come there together."""
    row = lambda x, kind, at, q, dst, q2: x.select("run_id", F.lit(kind).alias("kind"), F.col(at).alias("at"), q.cast("int").alias("q"), dst.cast("string").alias("dst"), q2.cast("int").alias("q2"))
    none = F.lit(None)
    rows = row(graph, 0, "at", F.col("q"), F.col("dst"), F.col("q2")).union(row(begin, 1, "src", none, none, none))
    if l2 is not None:
        rows = rows.union(row(l2.select("run_id", "node_id").dropDuplicates(), 2, "node_id", none, none, none))
    rows = rows.where("run_id IS NOT NULL AND at IS NOT NULL AND (kind <> 0 OR dst IS NOT NULL)").repartition("run_id").sortWithinPartitions("run_id")
    states = 1 + max([0, *dfa.finals, *[x for q, _, r in dfa.table() for x in (q, r)]])
    finals, every, most, places = sorted(dfa.finals), l2 is None, ROWS, PLACES

    def of(held):
        from wfpath.operators.walks import walked

        return walked(held, states, finals, every, places)

    return rows.mapInArrow(_whole_runs(of, most), "run_id string, src string, dst string")


def _whole_runs(of, most: int, by: str = "run_id"):
    """For mapInArrow, over rows sorted by ``by``: what ``of`` yields for tables of whole runs, of about ``most`` rows or a run."""

    def tasks(batches):
        import pyarrow as pa
        import pyarrow.compute as pc

        held = None
        for batch in batches:
            held = pa.Table.from_batches([batch]) if held is None else pa.concat_tables([held, pa.Table.from_batches([batch])])
            if held.num_rows >= most and (whole := pc.index(held[by], held[by][-1]).as_py()):
                yield from of(held.slice(0, whole))
                held = held.slice(whole)
        if held is not None and held.num_rows:
            yield from of(held)

    return tasks


def _to(pairs: DataFrame, l2: DataFrame | None) -> DataFrame:
    if l2 is None:
        return pairs
    return pairs.join(l2.select("run_id", F.col("node_id").alias("dst")).dropDuplicates(), ["run_id", "dst"], "left_semi").select(*PAIR)


def _from(pairs: DataFrame, l1: DataFrame | None) -> DataFrame:
    if l1 is None:
        return pairs
    return pairs.join(l1.select("run_id", F.col("node_id").alias("src")).dropDuplicates(), ["run_id", "src"], "left_semi").select(*PAIR)


def concatenated(a: DataFrame, b: DataFrame) -> DataFrame:
    x = a.withColumnRenamed("dst", "mid")
    return x.join(b.withColumnRenamed("src", "mid"), ["run_id", "mid"]).select(*PAIR).distinct()


class Rounds:
    """How many rounds fixpoints took, and how many joins and rows a plan made."""

    def __init__(self) -> None:
        self.rounds, self.joins, self.rows = 0, 0, 0


def closure(pairs: DataFrame, mode: str = "semi", counter: Rounds | None = None) -> DataFrame:
    """One or more steps of a relation.

    ``linear`` joins all found so far with the relation each round; ``semi`` only what the last round
    found; ``double`` joins what was found with itself, so rounds grow with the logarithm of the longest chain.
    Where a pair can have one path only and some path is long, all three go on by hops, see ``_closure_of_trees``; the hops of
    short runs are made within a task, see ``_closure_by_runs``.
    """
    base = cut(pairs.distinct())
    size = base.groupBy("run_id").agg(F.count(F.lit(1)).alias("edges"), F.count_if(F.expr("run_id IS NULL OR src IS NULL OR dst IS NULL")).alias("nulls")).agg(F.max("edges").alias("edges"), F.sum("nulls").alias("nulls")).first()
    if size["edges"] and size["edges"] <= HELD and not size["nulls"]:
        paths = _by_runs(base, "longest", "longest long").agg(F.min("longest").alias("least"), F.max("longest").alias("most")).first()
        found = _closure_by_runs(base, mode, paths["most"], counter) if paths["least"] and paths["most"] >= 2 ** (DOUBLED - 1) else None
    else:
        found = _closure_of_trees(base, mode, counter) if _trees(base) else None
    if found is not None:
        return found
    pile = Pile(base)
    front = base
    while True:
        if counter is not None:
            counter.rounds += 1
            counter.joins += 1
        seen = pile.rows()
        step = {"linear": lambda: (seen, base), "semi": lambda: (front, base), "double": lambda: (seen, seen)}[mode]()
        front = pile.add(concatenated(*step).join(seen, PAIR, "left_anti"))
        if _empty(front):
            return pile.rows()


def _trees(pairs: DataFrame) -> bool:
    """Whether no node has two predecessors, or no node has two successors."""
    return any(_empty(pairs.groupBy("run_id", side).count().where("count > 1")) for side in ("dst", "src"))


#: Paths of less than 2^(this - 1) steps go on step by step, in no more rounds than that.
DOUBLED = 6


def _closure_of_trees(base: DataFrame, mode: str, counter: Rounds | None = None) -> DataFrame | None:
    """The closure where a pair has one path: each pair falls out of one join, so none is stored or compared; None on a cycle or if all are short.

    Hops of exactly 1, 2, 4, ... steps have at most a row for each edge.  A path of n steps is y long hops of m
    steps and then x = 1 .. m more, in one way; m is near the root of the longest path.  So only ways of up to m steps and of
    whole long hops are found round by round, and the pairs stream out of the join of the two.  A round doubles the
    steps: ``linear`` joins all found so far with the longest hop, ``semi`` what the last round found with the
    two longest, and ``double`` what was found with the longest of itself.
    """
    on = ["run_id", "mid"]
    then = lambda x, y, n: x.withColumnRenamed("dst", "mid").join(y.select("run_id", F.col("src").alias("mid"), "dst", F.col("n").alias("more")), on).select(*PAIR, n.alias("n"))
    edges = base.count()
    hops = [base.withColumn("n", F.lit(1))]
    while not _empty(longer := cut(then(hops[-1], hops[-1], F.col("n") * 2))):
        if counter is not None:
            counter.joins += 1
        if 2 ** len(hops) > edges:
            return None
        hops.append(longer)

    if len(hops) < DOUBLED:
        return None

    def grown(hops: list[DataFrame]) -> DataFrame:
        """1 .. 2^k of the first hop, k being their number."""
        unit = hops[0].withColumn("n", F.lit(1))
        pile, front = Pile(unit), unit
        for i in range(len(hops)):
            if counter is not None:
                counter.rounds += 1
                counter.joins += 1
            at = lambda k: hops[k].withColumn("n", F.lit(2**k))
            seen = pile.rows()
            step = {"linear": lambda: (seen, at(i)), "semi": lambda i=i: (front, at(i).union(at(i - 1)) if i else at(0)), "double": lambda i=i: (seen, seen.where(F.col("n") == 2**i))}[mode]()  # noqa: B023
            front = pile.add(then(*step, F.col("n") + F.col("more")))
        return pile.rows().select(*PAIR)

    k = max(0, len(hops) // 2 - 1)
    near = grown(hops[:k]) if k else base
    # long hops only to where a path goes on
    onward = base.select("run_id", F.col("src").alias("dst")).distinct()
    far = grown([cut(h.join(onward, ["run_id", "dst"], "left_semi").select(*PAIR, "n")) for h in hops[k:]])
    return _near_and_far(near, far)


def _near_and_far(near: DataFrame, far: DataFrame) -> DataFrame:
    """Short ways, and long ones followed by these."""
    on = ["run_id", "mid"]
    # a number and the join are named as for tiles: a few rows here make many pairs
    n = max(32, int(near.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    pairs = far.withColumnRenamed("dst", "mid").repartition(n, *on).join(near.withColumnRenamed("src", "mid").hint("merge"), on).select(*PAIR)
    return near.union(pairs)


#: Hops are made within a task if no run has more edges: a task takes some hundred bytes for each.
HELD = 1 << 20


def _by_runs(base: DataFrame, what: str, schema: str, *more: str | bool) -> DataFrame:
    """What a function of ``walks`` makes of whole runs, some of them side by side in a task."""

    def of(rows):
        from wfpath.operators import walks

        return getattr(walks, what)(rows, *more)

    return base.select(*PAIR).repartition("run_id").sortWithinPartitions("run_id").mapInArrow(_whole_runs(of, ROWS), schema)


def _closure_by_runs(base: DataFrame, mode: str, longest: int, counter: Rounds | None = None) -> DataFrame:
    """The same closure as by ``_closure_of_trees``, where a task holds a run's edges: its hops and rounds are vectors over nodes, and no job is a round."""
    if counter is not None:
        counter.rounds += longest.bit_length()
        counter.joins += 2 * longest.bit_length() - 1
    # tiles are lists of nodes, so that few rows are shuffled before they make their many pairs
    n = max(32, int(base.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    tiles = _by_runs(base, "far", "run_id string, srcs array<string>, dsts array<string>, tile long", mode).repartition(n, "run_id", "tile")
    return _by_runs(base, "near", "run_id string, src string, dst string", mode).union(allpairs.crossed(tiles))


def bounded_closure(pairs: DataFrame, l1: DataFrame, counter: Rounds | None = None) -> DataFrame:
    """One or more steps of a relation from given sources only."""
    base = cut(pairs.distinct())
    graph = base.select("run_id", F.col("src").alias("at"), F.lit(0).alias("q"), "dst", F.lit(0).alias("q2"))
    first = _from(base, l1).select("run_id", "src", F.col("dst").alias("at"), F.lit(0).alias("q"))
    return spread_from(first, graph, counter=counter).select("run_id", "src", F.col("at").alias("dst"))


def identity(nodes: DataFrame) -> DataFrame:
    return nodes.select("run_id", F.col("node_id").alias("src"), F.col("node_id").alias("dst"))


def join_tree(query: Node, nodes: DataFrame, edges: DataFrame, l1: DataFrame | None = None, l2: DataFrame | None = None, mode: str = "semi", counter: Rounds | None = None) -> DataFrame:
    """The parse tree evaluated bottom-up by joins, unions and fixpoints; a part that occurs again is evaluated once."""
    done: dict[Node, DataFrame] = {}

    def walk(x: Node) -> DataFrame:
        if x not in done:
            done[x] = evaluated(x)
        return done[x]

    def evaluated(x: Node) -> DataFrame:
        match x.kind:
            case "eps":
                return identity(nodes)
            case "none":
                return identity(nodes).limit(0)
            case "any":
                return edges.select(*PAIR).distinct()
            case "tag":
                return edges.where(F.col("tag") == x.tag).select(*PAIR).distinct()
            case "alt":
                out = walk(x.parts[0])
                for p in x.parts[1:]:
                    out = out.union(walk(p))
                return out.distinct()
            case "cat":
                out = walk(x.parts[0])
                for p in x.parts[1:]:
                    out = concatenated(out, walk(p))
                    if counter is not None:
                        counter.joins += 1
                return out
        out = closure(walk(x.parts[0]), mode, counter)
        # every node's pair with itself is in the identity, and a closure has each pair once
        return out if x.kind == "plus" else out.where("src <> dst").union(identity(nodes))

    return _to(_from(walk(query), l1), l2)


def tag_counts(edges: DataFrame) -> dict[str, int]:
    """Edges by tag; the number of tags is the grammar's."""
    return {r["tag"]: r["count"] for r in edges.groupBy("tag").count().collect()}


def rare_tag(query: Node, nodes: DataFrame, edges: DataFrame, spec: Spec, threshold: int = 0, l1: DataFrame | None = None, l2: DataFrame | None = None, counts: dict[str, int] | None = None) -> DataFrame:
    """Cut the query at mandatory tags of its top level; walk backwards and forwards from their edges.

    It is cut at all of them with fewer than ``threshold`` edges, or else at the rarest one.  A query
    without such a tag is refused, as it would be walked as a whole.  What lies between two lists of nodes (a list, or
    the ends of a tag's edges) is walked from the shorter one, as a walk has a row for each start and node reached.
    """
    counts = tag_counts(edges) if counts is None else counts
    parts = list(query.parts) if query.kind == "cat" else [query]
    tagged = [i for i, p in enumerate(parts) if p.kind == "tag"]
    if not tagged:
        raise ValueError("no tag at the top of the query: nothing to start a search from")
    rare = [i for i in tagged if counts.get(parts[i].tag, 0) < threshold] or [min(tagged, key=lambda i: counts.get(parts[i].tag, 0))]
    own = lambda x: x if x is None or "label" in x.columns else x.join(nodes.select("run_id", "node_id"), ["run_id", "node_id"], "left_semi")
    l1, l2 = own(l1), own(l2)
    hits = {i: edges.where(F.col("tag") == parts[i].tag).select(*PAIR).distinct() for i in rare}
    ends = lambda pairs, side: pairs.select("run_id", F.col(side).alias("node_id")).distinct()
    back_edges = edges.select("run_id", F.col("dst").alias("src"), F.col("src").alias("dst"), "tag")

    def walked(part: Node, starts: DataFrame | None, goals: DataFrame | None) -> DataFrame:
        """Pairs of a part from a list to a list (None: all nodes); one of them is the ends of edges, and so the run's own."""
        if starts is not None and (goals is None or starts.count() <= goals.count()):
            return product_walk(None, edges, rpq.compile_(part, spec.tags), starts, goals)
        back = product_walk(None, back_edges, rpq.compile_(rpq.reversed_(part), spec.tags), goals, starts)
        return back.select("run_id", F.col("dst").alias("src"), F.col("src").alias("dst"))

    before = rpq.cat(*parts[: rare[0]])
    if before.kind == "eps":
        out = _from(hits[rare[0]], l1)
    else:
        out = concatenated(walked(before, l1, ends(hits[rare[0]], "src")), hits[rare[0]])
    for a, b in zip(rare, [*rare[1:], None], strict=True):
        between = rpq.cat(*parts[a + 1 : b])
        if between.kind != "eps":
            # read twice, by the walk and by the join with what it finds
            out = cut(out)
            out = concatenated(out, walked(between, ends(out, "dst"), ends(hits[b], "src") if b is not None else l2))
        if b is not None:
            out = concatenated(out, hits[b])
    return _to(out, l2)


def indexed(spark: SparkSession, path: str, tag: str) -> DataFrame:
    return spark.read.schema("run_id string, src string, dst string, tag string").parquet(path).where(F.col("tag") == tag).select(*PAIR)


def ifq_index(tags: list[str], lookup, nodes: DataFrame, spec: Spec, l1: DataFrame | None = None, l2: DataFrame | None = None, hop: str = "linear") -> DataFrame:
    """A passing query from each tag's pairs, consecutive ones joined by reachability labels.

    ``lookup`` gives the pairs of a tag.  ``hop``: linear meets the levels, nested tests every pair of a run.
    """
    from wfpath.plans.safety import compile_rpq

    def reached(a: DataFrame | None, b: DataFrame | None) -> DataFrame:
        return allpairs.reachable(nodes, spec, a, b) if hop == "linear" else allpairs.nested(nodes, compile_rpq(spec, rpq.reach()), a, b)

    ends = lambda pairs, side: pairs.select("run_id", F.col(side).alias("node_id")).distinct()
    if not tags:
        return reached(l1, l2)
    out = None
    for t in tags:
        # each hop is written once, as the next one reads it twice
        pairs = cut(lookup(t))
        before = cut(reached(l1 if out is None else ends(out, "dst"), ends(pairs, "src")))
        out = cut(concatenated(before if out is None else concatenated(out, before), pairs))
    return concatenated(out, cut(reached(ends(out, "dst"), l2)))
