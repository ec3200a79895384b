"""Operator 4: URL filters: rules first, then logistic regression on hashed character n-grams.

The model reads n-grams of 3 to 5 bytes of the host and of the path (apart from each other),
hashed into 2**15 weights, and is trained on the driver from a small labelled URL table; its size
is bounded by ``most`` rows, those with the smallest hash.  Scoring is a pass over host and path.

Nulls and edge cases: a null url, or one without '://', has an empty host and path, fits no rule
and gets the verdict of the model's bias; repeated rows are judged one by one; with no labelled
rows the model allows everything.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from wfpath.llm import shared
from wfpath.llm import textbytes as tb

#: The rules of the query, as (verdict, host and path).
RULES = (("allow", "com/"), ("block", "example.com/en/"), ("allow", "www.example.com/en/"), ("block", "net/es/"), ("block", "net/fr/"))
BITS, SIZES, MOST = 15, (3, 4, 5), 20_000
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def parted(url: Column) -> tuple[Column, Column]:
    """Host and path of a url."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.expr("substring(_url, instr(_url, '://') + 3)")).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return F.coalesce(F.translate(host, UPPER, LOWER), F.lit("")), F.coalesce(path, F.lit(""))


def ruled(host: Column, path: Column, rules: Sequence[tuple[str, str]]) -> tuple[Column, Column]:
    """The longest rule that fits and its verdict; null where none fits."""
    rule = verdict = F.lit(None).cast("string")
    for what, text in sorted(rules, key=lambda r: (len(r[1]), r[1])):  # the last tested first
        h, _, p = text.partition("/")
        fits = ((host == h) | host.endswith("." + h)) & path.startswith("/" + p)
        rule, verdict = F.when(fits, F.lit(text)).otherwise(rule), F.when(fits, F.lit(what)).otherwise(verdict)
    return rule, verdict


def grams(columns: Sequence[pa.Array]) -> tuple[np.ndarray, np.ndarray]:
    """Hashed n-grams of each row's columns: the slots of all rows, and which row each belongs to."""
    slots, owners = [], []
    for c, column in enumerate(columns):
        data, offsets = tb.texts_of(column)
        n = len(offsets) - 1
        marked = np.zeros(len(data) + 2 * n, np.uint64)  # a mark before and after each text
        where = np.repeat(np.arange(n), np.diff(offsets))
        marked[np.arange(len(data)) + 2 * where + 1] = data
        begin = offsets[:-1] + 2 * np.arange(n)
        marked[begin], marked[offsets[1:] + 2 * np.arange(n) + 1] = 256, 257
        owner = np.repeat(np.arange(n), np.diff(offsets) + 2)
        for size in SIZES:
            if len(marked) < size:
                continue
            h = np.zeros(len(marked) - size + 1, np.uint64)
            for j in range(size):
                h = h * np.uint64(0x100000001B3) + marked[j : len(marked) - size + 1 + j]
            same = owner[size - 1 :] == owner[: len(h)]
            h = tb.mix(h + np.uint64((c * 8 + size) << 48))
            slots.append((h[same] >> np.uint64(64 - BITS)).astype(np.int64))
            owners.append(owner[: len(h)][same])
    if not slots:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate(slots), np.concatenate(owners)


def logits(weights: np.ndarray, slots: np.ndarray, owners: np.ndarray, n: int) -> np.ndarray:
    """Bias plus the weights of a row's n-grams over the root of their number."""
    count = np.maximum(np.bincount(owners, minlength=n), 1)
    return weights[-1] + np.bincount(owners, weights[slots], minlength=n) / np.sqrt(count)


def train(host: Sequence[str], path: Sequence[str], block: np.ndarray, rounds: int = 150, rate: float = 0.5, decay: float = 1e-5) -> np.ndarray:
    """Weights by full-batch gradient steps with a rate per weight; the last weight is the bias."""
    n, weights = len(host), np.zeros((1 << BITS) + 1)
    if n == 0:
        weights[-1] = -1.0
        return weights
    slots, owners = grams([pa.array(host, pa.string()), pa.array(path, pa.string())])
    scale = 1 / np.sqrt(np.maximum(np.bincount(owners, minlength=n), 1))
    # both classes weigh the same, however many rows each has
    share = np.where(block > 0.5, 0.5 / max(block.mean(), 1 / n), 0.5 / max(1 - block.mean(), 1 / n))
    seen = np.full(len(weights), 1e-8)
    for _ in range(rounds):
        off = 1 / (1 + np.exp(-np.clip(logits(weights, slots, owners, n), -30, 30))) - block
        off = off * share
        slope = np.empty(len(weights))
        slope[:-1] = np.bincount(slots, (off * scale)[owners], minlength=1 << BITS) / n + decay * weights[:-1]
        slope[-1] = off.mean()
        seen += slope**2
        weights -= rate * slope / np.sqrt(seen)
    return weights


def labelled_sample(labelled: DataFrame, most: int = MOST) -> tuple[list[str], list[str], np.ndarray]:
    """About ``most`` different labelled urls (host, path, block), drawn by their hash; all of them if there are no more."""
    known = shared.materialised(labelled.select("host", "path", "block").distinct())
    rows = sorted((r["host"], r["path"], float(r["block"])) for r in shared.sampled(known, ["host", "path"], most).collect())
    return [r[0] for r in rows], [r[1] for r in rows], np.array([r[2] for r in rows])


def filtered(pages: DataFrame, rules: Sequence[tuple[str, str]] = RULES, labelled: DataFrame | None = None, most: int = MOST) -> DataFrame:
    """page_id, host, path, rule, verdict of every url.  Without ``labelled`` the urls that rules decide are the labelled table."""
    x = pages.select("page_id", F.col("url").cast("string").alias("_url"))
    host, path = parted(F.col("_url"))
    x = x.withColumn("host", host).withColumn("path", path)
    rule, verdict = ruled(F.col("host"), F.col("path"), rules)
    x = x.withColumn("rule", rule).withColumn("ruled", verdict).drop("_url")
    if labelled is None:
        labelled = x.where("ruled IS NOT NULL").select("host", "path", (F.col("ruled") == "block").alias("block"))
    weights = train(*labelled_sample(labelled, most)).astype(np.float32)

    def judge(batches):
        for batch in batches:
            col = lambda k: batch.column(batch.schema.get_field_index(k))
            parts = [np.zeros(0, bool)]
            sizes = np.diff(tb.texts_of(col("path"))[1]) + np.diff(tb.texts_of(col("host"))[1])
            for a, b in tb.slices(np.r_[0, np.cumsum(sizes)], 1 << 19):
                parts.append(logits(weights, *grams([col("host").slice(a, b - a), col("path").slice(a, b - a)]), b - a) >= 0)
            own = pa.array(np.where(np.concatenate(parts), "block", "allow"), pa.string())
            yield pa.RecordBatch.from_arrays([col("page_id"), col("host"), col("path"), col("rule"), pc.coalesce(col("ruled"), own)], ["page_id", "host", "path", "rule", "verdict"])

    kind = x.schema["page_id"].dataType.simpleString()
    return x.mapInArrow(judge, f"page_id {kind}, host string, path string, rule string, verdict string")


def op4_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """page_id, host, path, rule and verdict of every page."""
    return filtered(shared.load(spark, sf_dir, "pages").select("page_id", "url"))
