"""Operator 10: substring deduplication by Rabin-Karp hashes of fixed-length word windows.

A word is removed if a window of ``SIZE`` words that covers it also starts in a document with a
smaller id.  Every window of every text is hashed, and the windows are counted in Spark by their
hashes.  One row a window would shuffle as many rows as there are words, so neighbours are first
combined, without loss: a *run* is a stretch of windows whose smallest 8-word hash is the same, and
a row for it carries that hash, a hash of the sequence of its windows' hashes, and their number.
Equal windows have the same smallest hash, so

1. runs whose smallest hash occurs in one document only hold no repeat and are dropped;
2. runs of the same windows are counted as wholes: all but those of the smallest document go;
3. where one smallest hash has runs of different windows, one document's run of each is taken apart
   and its windows (by two hashes, 64 bits each) are counted one by one.

``combine=False`` counts every window as a row of its own, with the same result.

All are aggregations with map-side combine and joins on hashes, hot keys by broadcast, so a passage
that stands in a third of all documents is a few rows for each task.  Repeated windows merge into
maximal intervals, which join the texts once.

Nulls and edge cases: a null text has no words; a null doc_id has no order, so its text neither
loses words nor takes them; rows with the same doc_id and text are one document; a text with
fewer words than a window keeps all.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wfpath.llm import shared
from wfpath.llm import textbytes as tb

SIZE, GRAM = 50, 8
RUN = "v long, h long, n int, doc long, rid int, s int"


def signed(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64))


def keyed(docs: DataFrame) -> DataFrame:
    """doc, rid (a hash of the text, so that rows that share an id but not the text stay apart) and the text."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    return docs.select(F.col("doc_id").cast("long").alias("doc"), F.hash(text).alias("rid"), text.alias("text"))


def columns(batch: pa.RecordBatch, *names: str) -> list[pa.Array]:
    return [batch.column(batch.schema.get_field_index(k)) for k in names]


def runs(texts: DataFrame, size: int = SIZE, combine: bool = True) -> DataFrame:
    """The runs of every text: smallest hash v, hash h of its windows' hashes, number n of windows, first word s.

    Without ``combine`` each window is a run: v and h are its two hashes.
    """

    def scan(batches):
        for batch in batches:
            doc, rid, text = columns(batch, "doc", "rid", "text")
            data, offsets = tb.texts_of(text)
            for a, b in tb.slices(offsets):
                starts, ends, first = tb.word_bounds(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                words = tb.word_hashes(data[offsets[a] : offsets[b]], starts, ends)
                at, hashes = tb.inside(first, size), tb.rolling(words, size)
                if combine:
                    v, s, n = tb.runs_of_minima(tb.rolling(words, GRAM), at, size - GRAM + 1)
                    h = tb.spans(hashes, s, s + n)
                else:
                    v, h, s, n = hashes[at], tb.rolling(words, size, True)[at], at, np.ones(len(at), np.int64)
                if len(v):
                    owner = np.searchsorted(first, s, "right") - 1
                    of = pa.array(owner + a)
                    yield pa.RecordBatch.from_arrays([signed(v), signed(h), pa.array(n, pa.int32()), doc.take(of), rid.take(of), pa.array(s - first[owner], pa.int32())], ["v", "h", "n", "doc", "rid", "s"])

    return texts.mapInArrow(scan, RUN)


def repeats(texts: DataFrame, size: int = SIZE, combine: bool = True) -> DataFrame:
    """Windows to remove as ranges of their starts: doc, rid, s, n."""
    found = shared.materialised(runs(texts, size, combine))
    per_hash = found.groupBy("v").agg(F.count(F.lit(1)).alias("times"), F.min("doc").alias("d0"), F.max("doc").alias("d1"), F.min("h").alias("h0"), F.max("h").alias("h1"), F.min("n").alias("n0"), F.max("n").alias("n1"))
    common = shared.materialised(per_hash.where("d0 <> d1").select("v", "times", ((F.col("h0") != F.col("h1")) | (F.col("n0") != F.col("n1"))).alias("differ")))
    likely = shared.materialised(shared.joined_by_count(found, common, ["v"], "times"))
    shared.dropped(found, common)
    content = shared.materialised(likely.groupBy("v", "h", "n").agg(F.count(F.lit(1)).alias("times"), F.min("doc").alias("least")))
    placed = shared.joined_by_count(likely, content, ["v", "h", "n"], "times")
    whole = placed.where("least < doc").select("doc", "rid", "s", "n")
    open_runs = placed.where("least = doc AND differ").groupBy("doc", "rid").agg(F.collect_list(F.struct("s", "n")).alias("runs"))

    def single(batches):
        for batch in batches:
            doc, rid, text, lists = columns(batch, "doc", "rid", "text", "runs")
            data, offsets = tb.texts_of(text)
            flat, per = lists.flatten(), np.diff(np.asarray(lists.offsets))
            s_all, n_all = flat.field("s").to_numpy(zero_copy_only=False).astype(np.int64), flat.field("n").to_numpy(zero_copy_only=False).astype(np.int64)
            upto = np.r_[0, np.cumsum(per)]
            for a, b in tb.slices(offsets):
                starts, ends, first = tb.word_bounds(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                words = tb.word_hashes(data[offsets[a] : offsets[b]], starts, ends)
                s, n = s_all[upto[a] : upto[b]], n_all[upto[a] : upto[b]]
                owner = np.repeat(np.arange(b - a), per[a:b])
                stop = np.cumsum(n)
                at = np.arange(int(stop[-1]) if len(stop) else 0) + np.repeat(first[owner] + s - (stop - n), n)
                of = np.repeat(owner, n)
                yield pa.RecordBatch.from_arrays([signed(tb.rolling(words, size)[at]), signed(tb.rolling(words, size, True)[at]), doc.take(pa.array(of + a)), rid.take(pa.array(of + a)), pa.array(at - first[of], pa.int32())], ["k1", "k2", "doc", "rid", "s"])

    hashed = shared.materialised(texts.join(open_runs, ["doc", "rid"]).select("doc", "rid", "text", "runs").mapInArrow(single, "k1 long, k2 long, doc long, rid int, s int"))
    first = hashed.groupBy("k1", "k2").agg(F.count(F.lit(1)).alias("times"), F.min("doc").alias("least"), F.max("doc").alias("most")).where("least <> most").drop("most")
    one = shared.joined_by_count(hashed, shared.materialised(first), ["k1", "k2"], "times").where("least < doc").select("doc", "rid", "s", F.lit(1).alias("n"))
    return whole.union(one)


def marked(docs: DataFrame, size: int = SIZE, combine: bool = True) -> DataFrame:
    """Every document with the ranges to remove: doc, rid, text, marks (array of s, n; null if none)."""
    texts = keyed(docs)
    known = texts.where("doc IS NOT NULL")
    marks = repeats(known, size, combine).groupBy("doc", "rid").agg(F.collect_list(F.struct("s", "n")).alias("marks"))
    joined = known.join(marks, ["doc", "rid"], "left").select("doc", "rid", "text", "marks")
    kind = joined.schema["marks"].dataType
    return joined.union(texts.where("doc IS NULL").select("doc", "rid", "text", F.lit(None).cast(kind).alias("marks")))


def removed_mask(n: int, marks: list[dict], size: int) -> np.ndarray:
    """Which of n words or bytes the marked windows cover."""
    edge = np.zeros(n + 1, np.int64)
    s = np.array([m["s"] for m in marks], np.int64)
    np.add.at(edge, s, 1)
    np.subtract.at(edge, np.minimum(s + np.array([m["n"] for m in marks], np.int64) + size - 1, n), 1)
    return np.cumsum(edge[:-1]) > 0


def kept_words(text: str, marks, size: int) -> tuple[list[bytes], int]:
    """The words that stay, and how many there were."""
    words = text.encode().split()
    if not marks:
        return words, len(words)
    gone = removed_mask(len(words), marks, size)
    return [w for w, g in zip(words, gone.tolist(), strict=True) if not g], len(words)


def deduplicated(docs: DataFrame, size: int = SIZE, combine: bool = True) -> DataFrame:
    """doc_id and the text without its repeated windows (words joined by one space)."""

    def cut(batches):
        for batch in batches:
            doc, text, marks = columns(batch, "doc", "text", "marks")
            out = [b" ".join(kept_words(t.as_py(), m.as_py(), size)[0]).decode() for t, m in zip(text, marks, strict=True)]
            yield pa.RecordBatch.from_arrays([doc, pa.array(out, pa.string())], ["doc_id", "text"])

    return marked(docs, size, combine).mapInArrow(cut, "doc_id long, text string")


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 of every document."""

    def digest(batches):
        for batch in batches:
            doc, text, marks = columns(batch, "doc", "text", "marks")
            total, gone, sha = [], [], []
            for t, m in zip(text, marks, strict=True):
                words, n = kept_words(t.as_py(), m.as_py(), SIZE)
                total.append(n)
                gone.append(n - len(words))
                sha.append(hashlib.sha256(b" ".join(words)).hexdigest())
            yield pa.RecordBatch.from_arrays([doc, pa.array(total, pa.int64()), pa.array(gone, pa.int64()), pa.array(sha, pa.string())], ["doc_id", "n_words", "n_removed", "kept_sha256"])

    docs = shared.load(spark, sf_dir, "documents").select("doc_id", "text")
    return marked(docs).mapInArrow(digest, "doc_id long, n_words long, n_removed long, kept_sha256 string")
