"""General queries: the largest safe parts by labels, the rest by joins; and the choice of a method."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wfpath.operators import allpairs, baseline, pairwise
from wfpath.operators.baseline import PAIR, Rounds
from wfpath.plans import rpq
from wfpath.plans.rpq import Node
from wfpath.plans.safety import SafePlan, UnsafeQuery, compile_rpq, is_safe
from wfpath.plans.spec import Spec
from wfpath.sources.runs import RunData


@dataclass(frozen=True)
class Part:
    """``kind``: safe (decided by labels), tag, any, eps, none, cat, alt, star, plus."""

    kind: str
    query: Node
    parts: tuple[Part, ...] = ()
    plan: SafePlan | None = field(default=None, compare=False)

    def safe_parts(self) -> int:
        return (self.kind == "safe") + sum(p.safe_parts() for p in self.parts)

    def joins(self) -> int:
        return (len(self.parts) - 1 if self.kind == "cat" else int(self.kind in ("star", "plus"))) + sum(p.joins() for p in self.parts)

    def __str__(self) -> str:
        return f"[{self.query}]" if self.kind == "safe" else str(self.query) if not self.parts else f"{self.kind}({', '.join(map(str, self.parts))})"


def decompose(spec: Spec, query: str | Node, strategy: str = "top_down") -> Part:
    """A plan whose safe parts are as large as the strategy finds.

    top_down: whole subtrees from the root; runs: also the longest safe stretches of a concatenation
    and the safe alternatives together; bottom_up: neighbours are merged from the leaves while they
    stay safe.
    """
    node = rpq.rewrite(rpq.parse(query, spec.tags) if isinstance(query, str) else query)

    def safe(x: Node) -> Part | None:
        try:
            return Part("safe", x, plan=compile_rpq(spec, x))
        except UnsafeQuery:
            return None

    def leaf(x: Node) -> Part:
        return Part(x.kind, x)

    def walk(x: Node) -> Part:
        if strategy != "bottom_up" and (found := safe(x)):
            return found
        if not x.parts:
            return safe(x) or leaf(x)
        if x.kind == "cat" and strategy in ("runs", "bottom_up"):
            return Part("cat", x, tuple(_stretches(x.parts)))
        if x.kind == "alt" and strategy in ("runs", "bottom_up"):
            good, bad = [p for p in x.parts if is_safe(spec, p)], [p for p in x.parts if not is_safe(spec, p)]
            together = safe(rpq.alt(*good)) if len(good) > 1 else None
            parts = [together] if together else [safe(p) for p in good]
            parts += [walk(p) for p in bad]
            return parts[0] if len(parts) == 1 else Part("alt", x, tuple(parts))
        return Part(x.kind, x, tuple(walk(p) for p in x.parts))

    def _stretches(parts: tuple[Node, ...]) -> list[Part]:
        out, i = [], 0
        while i < len(parts):
            ends = range(len(parts), i, -1) if strategy == "runs" else range(i + 1, len(parts) + 1)
            best = None
            for j in ends:
                found = safe(rpq.cat(*parts[i:j]))
                if found:
                    best = (j, found)
                    if strategy == "runs":
                        break
                elif strategy == "bottom_up" and best:
                    break
            if best:
                i, part = best
                out.append(part)
            else:
                out.append(walk(parts[i]))
                i += 1
        return out

    found = walk(node)
    if found.kind == "cat" and len(found.parts) == 1:
        return found.parts[0]
    return found


def _tag_set(x: Node) -> list[str] | None:
    """The tags of a query that is one edge of some named tags."""
    if x.kind == "tag":
        return [x.tag]
    return [p.tag for p in x.parts] if x.kind == "alt" and all(p.kind == "tag" for p in x.parts) else None


def _ends(run: RunData, pairs: DataFrame, side: str, tags: list[str] | None = None) -> DataFrame:
    """The end points of a relation of the run as a list with labels; ``tags``: the edges that it begins or ends with."""
    at = pairs.select("run_id", F.col(side).alias("node_id")).distinct()
    own = run.nodes if tags is None else run.part(sorted(run.spec.atoms_at(tags, side)))
    return own.join(at, ["run_id", "node_id"], "left_semi").select("run_id", "node_id", "label")


def _single(part: DataFrame | None) -> bool:
    """Whether a list has at most one node in each run."""
    return part is not None and part.groupBy("run_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").limit(1).count() == 0


def _sources(part: Part, run: RunData, l1: DataFrame | None, l2: DataFrame, counter: Rounds | None) -> DataFrame:
    """run_id, node_id: where a match begins that ends in ``l2``; of a safe part without its pairs.

    Where a list has one node a run, the pairs of both are no more than the other list's nodes, and each is decided by itself.
    """
    tags = _tag_set(part.query)
    if part.kind == "safe" and tags is None:
        if _single(l2) or _single(l1):
            return allpairs.nested(labelled(run, l1, l2), part.plan, l1, l2, short=True).select("run_id", F.col("src").alias("node_id")).distinct()
        return allpairs.state_set(labelled(run, l1, l2), part.plan, l1, l2, "sources")
    return evaluate_plan(part, run, l1, l2, counter).select("run_id", F.col("src").alias("node_id")).distinct()


def _into_one(parts: tuple[Part, ...], run: RunData, l1: DataFrame | None, l2: DataFrame, counter: Rounds | None) -> DataFrame:
    """Pairs of a concatenation whose second list has one node a run: only where matches begin is carried, part by part from the end."""
    at = l2
    for i in range(len(parts) - 1, -1, -1):
        before = None if i == 0 else _tag_set(parts[i - 1].query)
        begin = l1 if i == 0 else baseline.cut(_ends(run, run.tagged(before), "dst", before)) if before else None
        found = baseline.cut(_sources(parts[i], run, begin, at, counter))
        tags = _tag_set(parts[i].query)
        if i == 0:
            at = found
        elif begin is not None:
            # matches begin in this list, which has the labels
            at = begin.join(found, ["run_id", "node_id"], "left_semi")
        else:
            at = _ends(run, found.withColumnRenamed("node_id", "src"), "src", tags)
    return at.select("run_id", F.col("node_id").alias("src")).join(l2.select("run_id", F.col("node_id").alias("dst")), "run_id").select(*PAIR)


def _first_of(parts: tuple[Part, ...], i: int) -> list[str] | None:
    """The tags T if part i and what follows it read ``_*.T._*``: then paths without T do for part i.

    A path by T can be cut at its first edge of T, and what follows that edge is any path.
    """
    after = rpq.cat(*[p.query for p in parts[i + 1 :]])
    if parts[i].query != rpq.reach() or after.kind != "cat" or after.parts[1] != rpq.reach():
        return None
    return _tag_set(after.parts[0])


def _until(run: RunData, tags: list[str], l1: DataFrame, counter: Rounds | None) -> DataFrame:
    """Pairs from a list to where edges of these tags begin, by paths without such edges."""
    graph = run.edges.where(~F.col("tag").isin(tags)).select("run_id", F.col("src").alias("at"), F.lit(0).alias("q"), "dst", F.lit(0).alias("q2"))
    start = l1.select("run_id", F.col("node_id").alias("src"), F.col("node_id").alias("at"), F.lit(0).alias("q"))
    seen = baseline.spread_from(start, graph, counter=counter).select("run_id", "src", F.col("at").alias("dst"))
    return seen.join(run.tagged(tags).select("run_id", F.col("src").alias("dst")).distinct(), ["run_id", "dst"], "left_semi").select(*PAIR)


def _onward(run: RunData, pairs: DataFrame, led: tuple[list[str], str] | None, plan: SafePlan, l2: DataFrame) -> DataFrame:
    """A relation followed by a safe part: sources stand where the relation has led them, so matches aren't joined through that place.

    ``led``: tags and side of the edges that the relation's ends lie at.
    """
    own = run.nodes if led is None else run.part(sorted(run.spec.atoms_at(*led)))
    stood = baseline.cut(pairs.select("run_id", F.col("src"), F.col("dst").alias("node_id")).join(own.select("run_id", "node_id", "label"), ["run_id", "node_id"]))
    goal = allpairs.listed(run.nodes if "label" not in l2.columns else l2, l2)
    found = allpairs.state_set(goal, plan, stood.select("run_id", F.col("src").alias("node_id"), "label"), goal, empty=False)
    if 0 in plan.dfa.finals:
        found = found.union(stood.select("run_id", "src", F.col("node_id").alias("dst")).join(goal.select("run_id", F.col("node_id").alias("dst")), ["run_id", "dst"], "left_semi").select(*PAIR))
    several = stood.groupBy("run_id", "src").agg(F.count(F.lit(1)).alias("n")).where("n > 1").limit(1).count()
    return found.distinct() if several else found


def evaluate_plan(part: Part, run: RunData, l1: DataFrame | None = None, l2: DataFrame | None = None, counter: Rounds | None = None) -> DataFrame:
    """Pairs of a plan.  End points pass sideways: what a part is asked for is what its neighbour can meet."""
    ends = lambda pairs, side: pairs.select("run_id", F.col(side).alias("node_id")).distinct()
    tags = _tag_set(part.query)
    if tags is not None:
        return baseline._to(baseline._from(run.tagged(tags).select(*PAIR).distinct(), l1), l2)
    match part.kind:
        case "safe":
            return allpairs.state_set(labelled(run, l1, l2), part.plan, l1, l2)
        case "alt":
            out = evaluate_plan(part.parts[0], run, l1, l2, counter)
            for p in part.parts[1:]:
                out = out.union(evaluate_plan(p, run, l1, l2, counter))
            return out.distinct()
        case "cat":
            if counter is not None:
                counter.joins += len(part.parts) - 1
            if _single(l2):
                return _into_one(part.parts, run, l1, l2, counter)
            # from the end with a list, or the left
            out = None
            if l1 is None and l2 is not None:
                for i, p in enumerate(reversed(part.parts)):
                    last = i == len(part.parts) - 1
                    own = baseline.cut(evaluate_plan(p, run, l1 if last else None, l2 if out is None else ends(out, "src"), counter))
                    out = own if out is None else baseline.concatenated(own, out)
                return out
            led = None
            for i, p in enumerate(part.parts):
                last, first = i == len(part.parts) - 1, _first_of(part.parts, i)
                begin = l1 if out is None else ends(out, "dst")
                if last and p.kind == "safe" and led is not None and l2 is not None:
                    return _onward(run, out, led, p.plan, l2)
                if first and begin is not None:
                    own, led = _until(run, first, begin, counter), (first, "src")
                else:
                    own, led = evaluate_plan(p, run, begin, l2 if last else None, counter), (_tag_set(p.query), "dst") if _tag_set(p.query) else None
                own = baseline.cut(own)
                out = own if out is None else baseline.concatenated(out, own)
            return out
        case "star" | "plus":
            inner = evaluate_plan(part.parts[0], run, None, None, counter)
            out = baseline.closure(inner, "semi" if l1 is not None else "double", counter) if l1 is None else baseline.bounded_closure(inner, l1, counter)
            out = out if part.kind == "plus" else out.union(baseline.identity(run.nodes if l1 is None else allpairs.listed(l1 if "label" in l1.columns else run.nodes, l1))).distinct()
            return baseline._to(baseline._from(out, l1), l2)
    return baseline._to(baseline._from(baseline.join_tree(part.query, run.nodes, run.edges), l1), l2)


@dataclass(frozen=True)
class Choice:
    method: str
    reason: str


def choose(spec: Spec, query: str | Node, counts: dict[str, int], size1: int, size2: int, n_nodes: int, threshold: int = 1000) -> Choice:
    """A method from tag counts and list sizes: no query is run to find out."""
    node = rpq.rewrite(rpq.parse(query, spec.tags) if isinstance(query, str) else query)
    if any(counts.get(t, 0) == 0 for t in mandatory(node)):
        return Choice("none", "a tag that every match needs has no edge")
    passing = passing_tags(node)
    if passing and sum(counts.get(t, 0) for t in passing) * 20 < min(size1, size2):
        return Choice("index", "its tags have few edges against the lists")
    if is_safe(spec, node):
        return Choice("nested", "short lists") if size1 * size2 <= 4 * n_nodes else Choice("state_set", "safe")
    if any(counts.get(t, 0) < threshold for t in _top_tags(node)) and not any(counts.get(t, 0) >= threshold for t in _top_tags(node)):
        return Choice("rare_tag", "unsafe, with a rare tag at its top")
    plan = decompose(spec, node, "runs")
    return Choice("decompose", f"unsafe, with {plan.safe_parts()} safe parts") if plan.safe_parts() else Choice("joins", "unsafe, and no part is safe")


def mandatory(x: Node) -> set[str]:
    """Tags that every word of the query holds."""
    match x.kind:
        case "tag":
            return {x.tag}
        case "cat":
            return set().union(*map(mandatory, x.parts))
        case "alt":
            return set.intersection(*map(mandatory, x.parts))
        case "plus":
            return mandatory(x.parts[0])
    return set()


def _tags_of(x: Node) -> set[str] | None:
    """The tags that a query names; None if it also takes edges of any tag, or names none."""
    if x.kind == "tag":
        return {x.tag}
    found = [_tags_of(p) for p in x.parts if p.kind not in ("eps", "none")]
    return None if x.kind == "any" or not found or None in found else set().union(*found)


def passing_tags(x: Node) -> list[str] | None:
    """The tags of a passing query, or None for another one."""
    if x == rpq.reach():
        return []
    if x.kind != "cat" or len(x.parts) % 2 == 0 or any(p != rpq.reach() for p in x.parts[::2]) or any(p.kind != "tag" for p in x.parts[1::2]):
        return None
    return [p.tag for p in x.parts[1::2]]


def _top_tags(x: Node) -> list[str]:
    return [p.tag for p in (x.parts if x.kind == "cat" else (x,)) if p.kind == "tag"]


def labelled(run: RunData, l1: DataFrame | None, l2: DataFrame | None) -> DataFrame:
    """The run's nodes, for a method that reads labels only: where both lists bring theirs, no other node is derived or read."""
    return l1 if l1 is not None and l2 is not None and "label" in l1.columns and "label" in l2.columns else run.nodes


def evaluate(run: RunData, query: str | Node, l1: DataFrame | None = None, l2: DataFrame | None = None, method: str = "auto", threshold: int = 1000) -> DataFrame:
    """All pairs (run_id, src, dst) of a query by a named method, or by the chosen one."""
    spec = run.spec
    node = rpq.rewrite(rpq.parse(query, spec.tags) if isinstance(query, str) else query)
    if method == "auto":
        n = run.nodes.count()
        method = choose(spec, node, baseline.tag_counts(run.edges), l1.count() if l1 is not None else n, l2.count() if l2 is not None else n, n, threshold).method
    match method:
        case "none":
            return baseline.identity(run.nodes).limit(0)
        case "nested" | "filtered" | "state_set":
            return getattr(allpairs, method)(labelled(run, l1, l2), compile_rpq(spec, node), l1, l2)
        case "walk":
            return baseline.product_walk(labelled(run, l1, l2), run.edges, rpq.compile_(node, spec.tags), l1, l2)
        case "joins" | "joins_linear" | "joins_double":
            tags = _tags_of(node)
            return baseline.join_tree(node, run.places, run.edges if tags is None else run.tagged(sorted(tags)), l1, l2, {"joins": "semi"}.get(method, method.removeprefix("joins_")))
        case "rare_tag":
            return baseline.rare_tag(node, labelled(run, l1, l2), run.edges, spec, threshold, l1, l2)
        case "index" | "index_nested":
            tags = passing_tags(node)
            if tags is None:
                raise ValueError("the tag index answers passing queries only")
            lookup = lambda t: run.edges.where(F.col("tag") == t).select(*PAIR)
            return baseline.ifq_index(tags, lookup, run.nodes, spec, l1, l2, "linear" if method == "index" else "nested")
        case "decompose" | "decompose_runs" | "decompose_bottom_up":
            strategy = {"decompose": "top_down"}.get(method, method.removeprefix("decompose_"))
            return evaluate_plan(decompose(spec, node, strategy), run, l1, l2)
    raise ValueError(f"no method {method!r}")


def holds(run: RunData, query: str | Node, pairs: DataFrame, method: str = "auto") -> DataFrame:
    """run_id, src, dst, holds: by labels if the query is safe, else from the pairs' end points as lists."""
    try:
        if method in ("auto", "labels"):
            return pairwise.holds(pairs, run.nodes, compile_rpq(run.spec, query))
    except UnsafeQuery:
        if method == "labels":
            raise
        method = "decompose_runs"
    l1 = pairs.select("run_id", F.col("src").alias("node_id")).distinct()
    l2 = pairs.select("run_id", F.col("dst").alias("node_id")).distinct()
    found = evaluate(run, query, l1, l2, method).withColumn("found", F.lit(True))
    return pairs.join(found, PAIR, "left").select(*PAIR, F.coalesce("found", F.lit(False)).alias("holds"))
