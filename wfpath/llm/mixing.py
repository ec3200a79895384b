"""Operator 1: mixing sources to target weights by weighted fair queueing.

Each source's documents stand in a shuffled order (by the MD5 of their id); a source that is
granted more than it has is gone through again.  A copy of a document gets a virtual finish time:
the tokens of its source up to its end, divided by the source's target.  All copies are sorted by
that time over ranges of it, and the sort is cut where the total budget is spent.  Every source's
clock runs at its target, so when the budget is spent each has been served its target but for a
document.  The one document that the budget ends in is cut there, or rounded to all or nothing
with ``whole=True``.

Nothing but a row per source is ever ordered in one task: both sorts run in explicit ranges
(of the hash and of the finish time), and only totals per range are added up.

Nulls and edge cases: a null text has size 0; null sources form one source, the last one; rows
that share doc_id and source are one document with the summed size; documents of size 0 are
never taken; without words all targets are 0.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from wfpath.llm import shared

WORD = r"[^\x20\x09-\x0D]+"
WEIGHTS = (5, 2, 1)
SHARE, CEILING = 1.5, 2
RANGES = 1024


def sizes(docs: DataFrame) -> DataFrame:
    """doc_id, source and the number of words of each document."""
    n = F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long")
    return docs.select("doc_id", F.col("source").cast("string").alias("source"), n.alias("n")).groupBy("doc_id", "source").agg(F.sum("n").alias("size"))


def targets(sized: DataFrame, weights=WEIGHTS, share: float = SHARE, ceiling: int = CEILING) -> DataFrame:
    """source, source_size, target: shares by weight, filled up to ``ceiling`` times each source's size.

    One row a source.  Sorted by the level at which each fills up, the water level is the first
    that no remaining source exceeds.
    """
    by_source = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    place = F.row_number().over(Window.orderBy(F.asc_nulls_last("source"))) - 1
    cycle = F.array(*[F.lit(int(w)).cast("long") for w in weights])
    x = by_source.withColumn("w", F.element_at(cycle, (place % len(weights) + 1).cast("int")))
    x = x.withColumn("cap", F.col("source_size") * ceiling).withColumn("full_at", F.col("cap") / F.col("w"))
    rising = Window.orderBy("full_at", F.asc_nulls_last("source"))
    before, after = rising.rowsBetween(Window.unboundedPreceding, -1), rising.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    everything = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    x = x.withColumn("budget", F.sum("source_size").over(everything) * F.lit(share))
    x = x.withColumn("level", (F.col("budget") - F.coalesce(F.sum("cap").over(before), F.lit(0))) / F.sum("w").over(after))
    x = x.withColumn("water", F.min(F.when(F.col("level") <= F.col("full_at"), F.struct("full_at", "level"))).over(everything)["level"])
    return x.select("source", "source_size", F.when(F.col("water").isNull() | (F.col("cap") <= F.col("water") * F.col("w")), F.col("cap").cast("double")).otherwise(F.col("water") * F.col("w")).alias("target"))


def schedule(sized: DataFrame, goal: DataFrame, ceiling: int = CEILING) -> DataFrame:
    """Copies in service order: doc_id, source, size, copy, finish, served, before (tokens served earlier)."""
    shuffled = sized.withColumn("key", F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")))).withColumn("part", F.substring("key", 1, 3))
    queued = shared.running_total(shuffled, "part", ["key", F.asc_nulls_first("doc_id")], "size", "ahead", groups=["source"])
    g = goal.withColumnRenamed("source", "_source")
    x = queued.join(g, queued["source"].eqNullSafe(g["_source"])).drop("_source")
    x = x.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(ceiling - 1))))
    x = x.where("size > 0").withColumn("finish", (F.col("copy") * F.col("source_size") + F.col("ahead") + F.col("size")) / F.col("target"))
    x = x.withColumn("range", F.floor(F.col("finish") * RANGES))
    # ranges that begin behind the end of the budget are left out before the sort: it needs no order there
    limit = goal.agg(F.round(F.sum("target")).cast("long").alias("n")).first()["n"] or 0
    per_range = x.groupBy("range").agg(F.sum("size").alias("in_range"))
    upto = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    needed = per_range.select("range", F.coalesce(F.sum("in_range").over(upto), F.lit(0)).alias("base")).where(F.col("base") < limit)
    x = x.join(needed, "range")
    order = Window.partitionBy("range").orderBy("finish", F.asc_nulls_last("source"), F.asc_nulls_first("doc_id"), "copy").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    x = x.withColumn("before", F.col("base") + F.sum("size").over(order) - F.col("size"))
    x = x.withColumn("served", F.least(F.col("size"), F.lit(limit) - F.col("before")))
    return x.where("served > 0").select("doc_id", "source", "size", "copy", "finish", "before", "served")


def mixed(docs: DataFrame, whole: bool = True, weights=WEIGHTS, share: float = SHARE, ceiling: int = CEILING) -> DataFrame:
    """The mix itself: the rows of ``docs``, each as often as it is served.

    With ``whole`` the document that the budget ends in counts if at least half of it is served;
    otherwise its text is cut after the words served.
    """
    sized = shared.materialised(sizes(docs))
    copies = schedule(sized, targets(sized, weights, share, ceiling), ceiling)
    if whole:
        copies = copies.where(2 * F.col("served") >= F.col("size")).withColumn("served", F.col("size"))
    copies = copies.select(F.col("doc_id").alias("_d"), F.col("source").alias("_s"), F.col("served").alias("_served"), F.col("size").alias("_size"))
    out = docs.join(copies, docs["doc_id"].eqNullSafe(copies["_d"]) & docs["source"].cast("string").eqNullSafe(copies["_s"]))
    if not whole:
        # spaces and words in turn; the words served are joined again by what stood between them
        parts = F.expr(r"regexp_extract_all(text, '[\\x20\\x09-\\x0D]*[^\\x20\\x09-\\x0D]+', 0)")
        cut = F.array_join(F.slice(parts, F.lit(1), F.col("_served").cast("int")), "")
        out = out.withColumn("text", F.when(F.col("_served") < F.col("_size"), cut).otherwise(F.col("text")))
    return out.select(*[docs[c] if c != "text" or whole else F.col("text") for c in docs.columns])


def op1_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, size, source_size, target, taken (and source) of every document."""
    sized = shared.materialised(sizes(shared.load(spark, sf_dir, "documents").select("doc_id", "text", "source")))
    goal = shared.materialised(targets(sized))
    took = schedule(sized, goal).groupBy(F.col("doc_id").alias("_d"), F.col("source").alias("_s")).agg(F.sum("served").alias("taken"))
    x = sized.join(goal.withColumnRenamed("source", "_g"), sized["source"].eqNullSafe(F.col("_g")))
    x = x.join(took, x["doc_id"].eqNullSafe(took["_d"]) & x["source"].eqNullSafe(took["_s"]), "left")
    return x.select("doc_id", "source", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"))


ORACLE = r"""
WITH sized AS (
  SELECT doc_id, source, CAST(sum(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))) AS BIGINT) AS size
  FROM documents GROUP BY doc_id, source),
src AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sized GROUP BY source),
weighed AS (
  SELECT *, [5, 2, 1][CAST((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS BIGINT)] AS w FROM src),
capped AS (SELECT *, 2 * source_size AS cap, CAST(2 * source_size AS DOUBLE) / w AS full_at FROM weighed),
levels AS (
  SELECT *, ((SELECT sum(source_size) FROM capped) * CAST(1.5 AS DOUBLE)
             - coalesce(sum(cap) OVER (ORDER BY full_at, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
            / CAST(sum(w) OVER (ORDER BY full_at, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS DOUBLE) AS level
  FROM capped),
water AS (SELECT arg_min(level, full_at) AS water FROM levels WHERE level <= full_at),
goal AS (
  SELECT source, source_size, CASE WHEN water IS NULL OR cap <= water * w THEN CAST(cap AS DOUBLE) ELSE water * w END AS target
  FROM levels, water),
queued AS (
  SELECT s.*, g.source_size, g.target,
         CAST(sum(size) OVER (PARTITION BY s.source ORDER BY md5(CAST(doc_id AS VARCHAR)), doc_id ROWS UNBOUNDED PRECEDING) AS BIGINT) - size AS ahead
  FROM sized s JOIN goal g ON s.source IS NOT DISTINCT FROM g.source),
copies AS (
  SELECT *, CAST(copy * source_size + ahead + size AS DOUBLE) / target AS finish
  FROM queued, (VALUES (0), (1)) AS c(copy) WHERE size > 0),
sorted AS (
  SELECT *, sum(size) OVER (ORDER BY finish, source NULLS LAST, doc_id, copy ROWS UNBOUNDED PRECEDING) - size AS before FROM copies),
served AS (
  SELECT doc_id, source, sum(greatest(0, least(size, (SELECT round(sum(target)) FROM goal) - before))) AS taken
  FROM sorted GROUP BY doc_id, source)
SELECT q.doc_id, q.source, q.size, q.source_size, q.target, CAST(coalesce(taken, 0) AS BIGINT) AS taken
FROM queued q LEFT JOIN served v ON q.doc_id IS NOT DISTINCT FROM v.doc_id AND q.source IS NOT DISTINCT FROM v.source
"""
