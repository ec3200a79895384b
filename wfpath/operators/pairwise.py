"""Does a matching path lead from one node to the other?  Decided from two labels."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wfpath.functions.labels import Decoder, array_kernel
from wfpath.plans import rpq
from wfpath.plans.safety import SafePlan, compile_rpq
from wfpath.plans.spec import Spec

KEYS = ["run_id", "node_id"]


def masked(nodes: DataFrame, decoder: Decoder, exits: bool = True, entries: bool = True) -> DataFrame:
    """Nodes with their state masks: one pass over the labels, whatever the number of pairs to come."""
    out = nodes.select("run_id", "node_id", "label")
    if exits:
        out = out.withColumn("exits", decoder.exits(F.col("label")))
    if entries:
        out = out.withColumn("entries", decoder.entries(F.col("label")))
    return out


def decided(pairs: DataFrame, decoder: Decoder) -> Column:
    """The decision for rows with ulabel, exits (of src), vlabel, entries (of dst)."""
    return decoder.holds({"label": F.col("ulabel"), "exits": F.col("exits")}, {"label": F.col("vlabel"), "entries": F.col("entries")})


def holds(pairs: DataFrame, nodes: DataFrame, plan: SafePlan, kernel: str = "auto") -> DataFrame:
    """run_id, src, dst, holds for every pair of nodes (duplicates stay; a node that isn't in the run gives false)."""
    use_columns = kernel == "columns" or (kernel == "auto" and plan.dfa.n <= 62)
    if use_columns:
        decoder = Decoder(plan)
        # masks only of nodes that some pair names; the join that follows reuses this partitioning
        named = lambda side: nodes.join(pairs.select("run_id", F.col(side).alias("node_id")), KEYS, "left_semi")
        u = masked(named("src"), decoder, entries=False).select("run_id", F.col("node_id").alias("src"), F.col("label").alias("ulabel"), "exits")
        v = masked(named("dst"), decoder, exits=False).select("run_id", F.col("node_id").alias("dst"), F.col("label").alias("vlabel"), "entries")
    else:
        u = nodes.select("run_id", F.col("node_id").alias("src"), F.col("label").alias("ulabel"))
        v = nodes.select("run_id", F.col("node_id").alias("dst"), F.col("label").alias("vlabel"))
    x = pairs.select("run_id", "src", "dst").join(u, ["run_id", "src"], "left").join(v, ["run_id", "dst"], "left")
    known = F.col("ulabel").isNotNull() & F.col("vlabel").isNotNull()
    if use_columns:
        found = F.when(known, decided(x, decoder)).otherwise(False)
    else:
        none = F.array().cast("array<struct<kind:tinyint,a:int,b:int,idx:bigint>>")
        found = known & array_kernel(plan)(F.coalesce("ulabel", none), F.coalesce("vlabel", none))
    return x.select("run_id", "src", "dst", found.alias("holds"))


def reaches(pairs: DataFrame, nodes: DataFrame, spec: Spec, kernel: str = "auto") -> DataFrame:
    """Plain reachability: any path at all, and none from a node to itself is needed."""
    return holds(pairs, nodes, compile_rpq(spec, rpq.reach()), kernel)
