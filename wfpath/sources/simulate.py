"""Simulated runs of a specification, and labels from a derivation log."""

from __future__ import annotations

import random
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wfpath.functions.labels import member, pos
from wfpath.operators.baseline import cut
from wfpath.plans.spec import Spec
from wfpath.sources.runs import RunData

NODE = "run_id string, node_id string, module string, label array<struct<kind:tinyint,a:int,b:int,idx:bigint>>"
EDGE = "run_id string, src string, dst string, tag string"


def derive(spec: Spec, target: int, seed: int, focus: int | None = None) -> tuple[list[tuple], list[tuple]]:
    """Nodes (name, module, label) and edges (src, dst, tag) of one run of about ``target`` edges.

    Productions are drawn at random; recursion goes on while the run is short.  With ``focus`` only
    that cycle goes on (and as long as needed), all others end at once.
    """
    rng = random.Random(seed)
    nodes: list[tuple] = []
    edges: list[tuple] = []
    count = 0
    recursive = {k for c in spec.cycles for k, _ in c.slots}
    leads = {c.number: set(c.modules) for c in spec.cycles}
    made = 0

    def toward(module: str) -> bool:
        return focus is not None and bool((spec._reachable(module) | {module}) & leads[focus])

    def pick(module: str, chain):
        options = spec.of(module)
        ends = [p for p in options if p.number not in recursive]
        on = [p for p in options if p.number in recursive]
        own = spec.place.get(module, (None, 0))[0]
        go = on and made < target and (own == focus if focus is not None else rng.random() < 0.9)
        if go:
            return on[0]
        choices = ends or options
        if focus is not None:
            leading = lambda some: [p for p in some if any(m in spec.composite and m != module and toward(m) for m in p.body)]
            # a recursion that alone leads to the focus goes on once
            choices = leading(choices) or (leading(on) if own != focus and chain and chain[2] == 1 else []) or choices
        return rng.choice(choices)

    # a node waiting for expansion: module, label, chain member (or None), and where its first and last nodes are told
    first: dict[int, str] = {}
    last: dict[int, str] = {}
    todo: list[tuple] = [(0, spec.start, [], None)]
    serial = 1
    bodies: list[tuple[int, object, dict[int, int]]] = []
    while todo:
        me, module, label, chain = todo.pop()
        if module not in spec.composite:
            count += 1
            name = f"m{count}.{module}"
            nodes.append((name, module, label))
            first[me] = last[me] = name
            continue
        if module in spec.place and chain is None:
            c, t = spec.place[module]
            chain = (c, t, 1)
            label = [*label, (1, c, t, 1)]
        p = pick(module, chain)
        made += len(p.edges)
        slot = dict(spec.cycles[chain[0] - 1].slots).get(p.number) if chain else None
        ids = {}
        for i, m in enumerate(p.body, 1):
            ids[i] = serial
            if i == slot:
                c, t, n = chain
                todo.append((serial, m, [*label[:-1], (1, c, t, n + 1)], (c, t, n + 1)))
            else:
                todo.append((serial, m, [*label, (0, p.number, i, 0)], None))
            serial += 1
        bodies.append((me, p, ids))
    for me, p, ids in reversed(bodies):
        first[me], last[me] = first[ids[p.source]], last[ids[p.sink]]
    for _, p, ids in bodies:
        edges += [(last[ids[u]], first[ids[v]], t) for u, v, t in p.edges]
    return nodes, edges


def simulate(spark: SparkSession, spec: Spec, target: int, seed: int = 0, runs: int = 1, focus: int | None = None) -> RunData:
    """``runs`` simulated runs, each made in a task of its own."""

    def nodes_of(batches: Iterator[pd.DataFrame]):
        for pdf in batches:
            for i in pdf["id"]:
                nodes, _ = derive(spec, target, seed + int(i), focus)
                yield pd.DataFrame([(f"y{seed + i}", n, m, [dict(zip(("kind", "a", "b", "idx"), e, strict=True)) for e in label]) for n, m, label in nodes], columns=["run_id", "node_id", "module", "label"])

    def edges_of(batches: Iterator[pd.DataFrame]):
        for pdf in batches:
            for i in pdf["id"]:
                _, edges = derive(spec, target, seed + int(i), focus)
                yield pd.DataFrame([(f"y{seed + i}", *e) for e in edges], columns=["run_id", "src", "dst", "tag"])

    ids = spark.range(runs)
    return RunData(ids.mapInPandas(nodes_of, NODE), ids.mapInPandas(edges_of, EDGE), spec)


def labels_from_log(log: DataFrame, spec: Spec) -> DataFrame:
    """Labels of atomic executions from a derivation log: run_id, exec, parent, prod, pos, module.

    ``prod`` and ``pos`` say in which production of the parent's expansion an execution stands; a
    root has a null parent.  Members of a chain first learn their distance from its head, by
    doubling the steps they look back; then labels pass down once per level of the parse tree.
    """
    slots = {(k, i): c.number for c in spec.cycles for k, i in c.slots}
    entered = {m: t for m, (c, t) in spec.place.items()}
    code = F.col("prod").cast("bigint") * (1 << 16) + F.col("pos")
    inner = code.isin([(k << 16) + i for k, i in slots]) if slots else F.lit(False)
    cycle_of = F.coalesce(*[F.when(F.col("module") == m, c) for m, (c, _) in spec.place.items()]) if spec.place else F.lit(None).cast("int")
    offset_of = F.coalesce(*[F.when(F.col("module") == m, t) for m, t in entered.items()]) if entered else F.lit(None).cast("int")
    x = log.select("run_id", "exec", "parent", "prod", "pos", "module", inner.alias("on"), cycle_of.alias("cycle"), offset_of.alias("offset"))
    # doubling: every member points back; a head points at itself
    far = cut(x.where("cycle IS NOT NULL").select("run_id", "exec", F.when(F.col("on"), F.col("parent")).otherwise(F.col("exec")).alias("back"), F.when(F.col("on"), 1).otherwise(0).cast("long").alias("steps")))
    while True:
        other = far.select("run_id", F.col("exec").alias("back"), F.col("back").alias("back2"), F.col("steps").alias("more"))
        new = cut(far.join(other, ["run_id", "back"]).select("run_id", "exec", F.col("back2").alias("back"), (F.col("steps") + F.col("more")).alias("steps")))
        moved = new.join(far.select("run_id", "exec", F.col("steps").alias("before")), ["run_id", "exec"]).where("steps <> before").limit(1).count()
        far = new
        if not moved:
            break
    heads = x.where("cycle IS NOT NULL AND NOT `on`").select("run_id", F.col("exec").alias("head"), "parent", "prod", "pos", "cycle", "offset")
    placed = far.select("run_id", "exec", F.col("back").alias("head"), "steps").join(heads, ["run_id", "head"])
    # an execution stands under its parent; a chain member under its head's parent
    under = placed.select("run_id", "exec", F.col("parent").alias("above"), "prod", "pos", "cycle", "offset", (F.col("steps") + 1).alias("idx"))
    plain = x.where("cycle IS NULL").select("run_id", "exec", F.col("parent").alias("above"), "prod", "pos", F.lit(None).cast("int").alias("cycle"), F.lit(None).cast("int").alias("offset"), F.lit(None).cast("long").alias("idx"))
    tree = cut(under.union(plain))
    own = F.when(F.col("prod").isNull(), F.array().cast("array<struct<kind:tinyint,a:int,b:int,idx:bigint>>")).otherwise(F.array(pos(F.col("prod"), F.col("pos"))))
    chain = F.concat(own, F.when(F.col("cycle").isNotNull(), F.array(_member())).otherwise(F.array().cast("array<struct<kind:tinyint,a:int,b:int,idx:bigint>>")))
    level = cut(tree.where("above IS NULL").select("run_id", "exec", chain.alias("label")))
    found = level
    while True:
        below = tree.join(level.select("run_id", F.col("exec").alias("above"), F.col("label").alias("upper")), ["run_id", "above"])
        level = cut(below.select("run_id", "exec", F.concat("upper", chain).alias("label")))
        if level.limit(1).count() == 0:
            break
        found = found.union(level)
    atoms = x.where(~F.col("module").isin([*spec.composite])).select("run_id", "exec", "module")
    return atoms.join(found, ["run_id", "exec"]).select("run_id", F.col("exec").alias("node_id"), "module", "label")


def _member():
    return F.struct(F.lit(1).cast("tinyint").alias("kind"), F.col("cycle").cast("int").alias("a"), F.col("offset").cast("int").alias("b"), F.col("idx").cast("bigint").alias("idx"))


__all__ = ["derive", "labels_from_log", "member", "simulate"]
