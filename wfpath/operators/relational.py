"""Relational operators around the methods: top-k, as-of joins, witnesses, and the SQL front."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from wfpath.functions.labels import LABEL, pack
from wfpath.operators import baseline, general
from wfpath.plans import rpq
from wfpath.plans.safety import is_safe
from wfpath.plans.spec import Spec
from wfpath.sources.runs import RunData


def top_sources(pairs: DataFrame, k: int, by_run: bool = False) -> DataFrame:
    """The ``k`` sources with the most targets, of all or of each run: run_id, src, n; ties go to the smaller name."""
    counted = pairs.groupBy("run_id", "src").agg(F.count(F.lit(1)).alias("n"))
    if not by_run:
        return counted.orderBy(F.desc("n"), "run_id", "src").limit(k)
    rank = F.row_number().over(Window.partitionBy("run_id").orderBy(F.desc("n"), "src"))
    return counted.withColumn("rank", rank).where(F.col("rank") <= k).drop("rank")


def module_cube(pairs: DataFrame, nodes: DataFrame) -> DataFrame:
    """Pairs by module of source and target, with all subtotals."""
    named = lambda end, name: nodes.select("run_id", F.col("node_id").alias(end), F.col("module").alias(name))
    x = pairs.join(named("src", "src_module"), ["run_id", "src"]).join(named("dst", "dst_module"), ["run_id", "dst"])
    return x.cube("src_module", "dst_module").agg(F.count(F.lit(1)).alias("n"))


def as_of(left: DataFrame, right: DataFrame, keys: list[str], at: str, value: str) -> DataFrame:
    """``left`` with the ``value`` of the last row of ``right`` with the same keys that isn't later; null without one.

    Both are put together and scanned once in order, so no pair of rows is ever compared.
    """
    names = [c for c in left.columns if c not in (*keys, at)]
    a = left.select(*keys, at, F.struct(*names).alias("_row"), F.lit(None).cast(right.schema[value].dataType).alias("_value"), F.lit(1).alias("_side"))
    b = right.select(*keys, at, F.lit(None).cast(a.schema["_row"].dataType).alias("_row"), F.col(value).alias("_value"), F.lit(0).alias("_side"))
    w = Window.partitionBy(*keys).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    x = a.union(b).withColumn("_last", F.last("_value", ignorenulls=True).over(w)).where("_side = 1")
    return x.select(*keys, at, "_row.*", F.col("_last").alias(value))


def within_range(left: DataFrame, right: DataFrame, keys: list[str], at: str, other: str, width: int) -> DataFrame:
    """Pairs with the same keys and ``other`` - ``at`` in [0, width): an equi-join on buckets of that width and their neighbours."""
    a = left.withColumn("_bucket", F.explode(F.array(F.floor(F.col(at) / width), F.floor(F.col(at) / width) + 1)))
    b = right.withColumn("_bucket", F.floor(F.col(other) / width))
    return a.join(b, [*keys, "_bucket"]).where((F.col(other) >= F.col(at)) & (F.col(other) < F.col(at) + width)).drop("_bucket")


def witnesses(run: RunData, query: str, l1: DataFrame | None = None, l2: DataFrame | None = None) -> DataFrame:
    """For each matching pair the tags of a shortest matching path, the first in order among those: run_id, src, dst, tags.

    The run and the automaton are walked together step by step, and of the ways to a state the least
    is kept; a state is never walked on twice.
    """
    dfa = rpq.compile_(rpq.rewrite(rpq.parse(query, run.spec.tags)), run.spec.tags)
    graph = baseline.cut(baseline.product_graph(run.edges, dfa).select("run_id", F.col("src").alias("at"), "q", "dst", "q2", "tag"))
    begin = (run.nodes if l1 is None else l1).select("run_id", F.col("node_id").alias("src")).distinct()
    pile = baseline.Pile(begin.select("run_id", "src", F.col("src").alias("at"), F.lit(0).alias("q"), F.array().cast("array<string>").alias("tags")))
    front, state = pile.rows(), ["run_id", "src", "at", "q"]
    while True:
        step = front.join(graph, ["run_id", "at", "q"]).select("run_id", "src", F.col("dst").alias("at"), F.col("q2").alias("q"), F.concat("tags", F.array("tag")).alias("tags"))
        step = step.groupBy(*state).agg(F.min("tags").alias("tags"))
        front = pile.add(step.join(pile.rows().select(*state), state, "left_anti"))
        if front.limit(1).count() == 0:
            break
    ends = pile.rows().where(F.col("q").isin([*sorted(dfa.finals)]) if dfa.finals else F.lit(False))
    best = ends.groupBy("run_id", "src", F.col("at").alias("dst")).agg(F.min(F.struct(F.size("tags").alias("n"), "tags")).alias("best")).select("run_id", "src", "dst", "best.tags")
    return best if l2 is None else best.join(l2.select("run_id", F.col("node_id").alias("dst")).distinct(), ["run_id", "dst"], "left_semi")


class LabelLevels:
    """A table function: the entries of a label, one row for each level."""

    def eval(self, label):
        for depth, e in enumerate(label or []):
            yield depth, e["kind"], e["a"], e["b"], e["idx"]


def register(spark: SparkSession, run: RunData, specs: dict[str, Spec], prefix: str = "run") -> None:
    """The SQL front: views ``<prefix>_node`` and ``<prefix>_edge``, and functions.

    ``spec_safe(name, query)``: the verdict; ``label_key(label)`` in the view: the packed label;
    ``label_levels(label)``: a table function.
    """
    run.nodes.withColumn("label_key", F.lower(F.hex(pack(F.col("label"))))).createOrReplaceTempView(f"{prefix}_node")
    run.edges.createOrReplaceTempView(f"{prefix}_edge")
    spark.udf.register("spec_safe", lambda name, query: is_safe(specs[name], query), "boolean")
    spark.udtf.register("label_levels", F.udtf(LabelLevels, returnType="depth int, kind int, a int, b int, idx bigint"))


def answered(spark: SparkSession, run: RunData, query: str, view: str, method: str = "auto") -> None:
    """The answer of a path query as a view for SQL."""
    general.evaluate(run, query, method=method).createOrReplaceTempView(view)


__all__ = ["LABEL", "as_of", "answered", "module_cube", "register", "top_sources", "within_range", "witnesses"]
