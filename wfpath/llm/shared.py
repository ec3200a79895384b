"""What the operators share: intermediate tables, ranks over ranges, components of link graphs."""

from __future__ import annotations

import os
import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share; one of our own only where the session names none (tests)."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir has to name a folder that all executors share")
    own = os.path.join(tempfile.gettempdir(), "wfpath-checkpoints")
    os.makedirs(own, exist_ok=True)
    return f"file://{own}"


def materialised(df: DataFrame) -> DataFrame:
    """``df`` written to the shared folder and read back: its lineage ends there, and any executor can read it."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.stored_at = path
    return out


def dropped(*tables: DataFrame) -> None:
    """Removes materialised tables that only other materialised ones were made from: nothing will read them again."""
    for df in tables:
        spark = df.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(df.stored_at)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def running_total(df: DataFrame, bucket: str, order: list[Column | str], amount: str, name: str, groups: list[str] | None = None) -> DataFrame:
    """Adds ``name``: the sum of ``amount`` over all rows before this one, by ``groups``, bucket, then ``order``.

    ``bucket`` is an explicit range of the order that bounds what one task sorts; only a total per
    bucket is summed across buckets, and that table has groups times buckets rows.  The order has
    to be total within a bucket.
    """
    groups = groups or []
    keys = [*groups, bucket]
    totals = df.groupBy(*keys).agg(F.sum(amount).alias("_sum"))
    whole = Window.partitionBy(*groups).orderBy(bucket) if groups else Window.orderBy(bucket)
    before = totals.withColumn("_base", F.coalesce(F.sum("_sum").over(whole.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("_sum")
    inner = Window.partitionBy(*keys).orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    out = df.withColumn(name, F.sum(amount).over(inner) - F.col(amount))
    on = None
    for k in keys:
        same = out[k].eqNullSafe(before[k])
        on = same if on is None else on & same
    joined = out.join(before, on)
    return joined.select(*[out[c] for c in out.columns if c != name], (out[name] + before["_base"]).alias(name))


def sampled(df: DataFrame, keys: list[str], most: int) -> DataFrame:
    """About ``most`` rows of ``df`` (all, if it has no more): those whose keys have the smallest hashes.

    A threshold on the hash decides, so no task orders rows, and a rerun draws the same.
    """
    share = min(1.0, most / max(1, df.count()))
    if share == 1.0:
        return df
    return df.where(F.pmod(F.xxhash64(F.lit(77), *keys), F.lit(1 << 40)) < F.lit(int(share * (1 << 40))))


#: A key with more than this share of the counted rows is met by broadcast; there are fewer such keys than its inverse.
HOT = 1 / 512


def joined_by_count(rows: DataFrame, counted: DataFrame, keys: list[str], times: str) -> DataFrame:
    """``rows`` with what ``counted`` says of their keys (none twice); ``times`` is how many of the rows have the key.

    Keys with a share of the rows above HOT, fewer than 512, are broadcast, so that no task gets all
    rows of one of them; the others meet by a shuffle.  ``times`` itself is left out.
    """
    total = counted.agg(F.sum(times).alias("n")).first()["n"] or 0
    hot = counted.where(F.col(times) > F.lit(total * HOT)).drop(times)
    rest = counted.where(F.col(times) <= F.lit(total * HOT)).drop(times)
    cold = rows.join(F.broadcast(hot.select(*keys)), keys, "left_anti").join(rest, keys)
    return cold.unionByName(rows.join(F.broadcast(hot), keys))


def _forest(batches, a: str, b: str):
    """Links reduced to a spanning star per local component: at most a row for each id."""
    for batch in batches:
        x = np.concatenate([batch.column(batch.schema.get_field_index(a)).to_numpy(), batch.column(batch.schema.get_field_index(b)).to_numpy()])
        ids, at = np.unique(x, return_inverse=True)
        root = local_components(len(ids), at[: batch.num_rows], at[batch.num_rows :])
        other = np.flatnonzero(root != np.arange(len(ids)))
        yield pa.RecordBatch.from_arrays([pa.array(ids[root[other]]), pa.array(ids[other])], [a, b])


def local_components(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """For n items and links a-b, the smallest item of each one's component."""
    label = np.arange(n)
    while len(a):
        low = np.minimum(label[a], label[b])
        before = label.copy()
        np.minimum.at(label, label[a], low)
        np.minimum.at(label, label[b], low)
        np.minimum.at(label, a, low)
        np.minimum.at(label, b, low)
        while True:
            up = label[label]
            if np.array_equal(up, label):
                break
            label = up
        if np.array_equal(before, label):
            break
    return label


def components(links: DataFrame, a: str = "a", b: str = "b", rounds: int = 60) -> DataFrame:
    """Connected components of a link table: rows (id, component), component the smallest id reachable.

    Alternates two steps until nothing changes: every neighbour of an id joins the smallest id of
    its neighbourhood (larger ones, then smaller ones).  Each step is an aggregation with map-side
    combine and a join, so hub ids are never gathered in one task; the links are cut to a local
    spanning forest first.  A change is counted, no links come to the driver.
    """
    spark = links.sparkSession
    edges = links.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).where("a <> b")
    edges = edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    edges = materialised(edges.mapInArrow(lambda it: _forest(it, "a", "b"), "a long, b long").distinct())
    for _ in range(rounds):
        both = edges.select(F.col("a").alias("u"), F.col("b").alias("v")).union(edges.select(F.col("b").alias("u"), F.col("a").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("m").alias("a"), F.col("v").alias("b")).where("a <> b").distinct()
        low2 = large.groupBy(F.col("b").alias("u")).agg(F.min("a").alias("m"))
        hung = large.join(low2, large["b"] == low2["u"]).select(F.col("m").alias("x"), F.col("a").alias("y"), F.col("u").alias("z"))
        small = hung.select(F.explode(F.array(F.struct(F.col("x").alias("a"), F.col("y").alias("b")), F.struct(F.col("x").alias("a"), F.col("z").alias("b")))).alias("e")).select("e.a", "e.b").where("a <> b").distinct()
        new = materialised(small)
        # both steps keep the components; a star forest, where no id hangs on two others or on one that hangs, is their fixpoint
        ends = new.select(F.col("a").alias("x"), F.lit(None).cast("long").alias("on")).union(new.select(F.col("b").alias("x"), F.col("a").alias("on")))
        ends = ends.groupBy("x").agg(F.count(F.lit(1)).alias("n"), F.count("on").alias("hung"), F.min("on").alias("lo"), F.max("on").alias("hi"))
        unsettled = ends.where("hung > 0 AND (n > hung OR lo <> hi)").limit(1).count()
        edges = new
        if not unsettled:
            break
    else:
        raise RuntimeError("the components did not settle")
    return edges.select(F.col("b").alias("id"), F.col("a").alias("component")).union(edges.select(F.col("a").alias("id"), F.col("a").alias("component")).distinct())
