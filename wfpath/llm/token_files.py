"""Operator 6: token ids in binary files, coded by an adaptive context-mixing range coder.

Documents are range-partitioned by doc_id and sorted.  Every task writes groups: the ids of some
documents, cut into coder blocks, beside the documents' ids and lengths.  The groups are kept in
Parquet files (part, seq, doc_ids, n_tokens, blocks), so Spark's committer makes a task's output
appear whole or not at all, and any store that Spark writes will do.  Part and seq give the order;
where a document begins in the whole sequence follows from the groups' totals.

Nulls and edge cases: a null or empty text is its end id alone; a null doc_id comes first; rows
that share a doc_id stay apart, in the order of their texts; an empty table gives files without
groups.
"""

from __future__ import annotations

import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wfpath.llm import shared, token_coder, tokens
from wfpath.llm import textbytes as tb

END_ID, GROUP = 2, 6 << 20
FORMAT = "part int, seq int, n_ids long, doc_ids array<long>, n_tokens array<long>, blocks array<binary>"


def write(docs: DataFrame, path: str, end_id: int = END_ID, vocabulary: str = tokens.VOCABULARY, block: int = token_coder.BLOCK) -> None:
    """Writes the ids of all texts, in ascending doc_id order, to ``path``."""
    ordered = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    ordered = ordered.repartitionByRange(F.asc_nulls_first("doc_id")).sortWithinPartitions(F.asc_nulls_first("doc_id"), F.asc_nulls_first("text"))

    def code(batches):
        part, seq = TaskContext.get().partitionId(), 0
        for batch in batches:
            text, of = batch.column(batch.schema.get_field_index("text")), batch.column(batch.schema.get_field_index("doc_id"))
            for a, b in tb.slices(tb.texts_of(text)[1], GROUP):
                ids, at = tokens.encode(text.slice(a, b - a), end_id, vocabulary)
                row = {"part": [part], "seq": [seq], "n_ids": [len(ids)], "doc_ids": [of.slice(a, b - a)], "n_tokens": [np.diff(at)], "blocks": [token_coder.encode(ids, block)]}
                types = [pa.int32(), pa.int32(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.binary())]
                yield pa.RecordBatch.from_arrays([pa.array([x.to_pylist() if isinstance(x, pa.Array) else x for x in v], t) for v, t in zip(row.values(), types, strict=True)], list(row))
                seq += 1

    ordered.mapInArrow(code, FORMAT).write.parquet(path)


def read(spark: SparkSession, path: str, with_ids: bool = False) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 (and ids) of every document, decoded from the files."""
    groups = spark.read.schema(FORMAT).parquet(path)
    # one row a group: its place among all ids
    heads = shared.running_total(groups.select("part", "seq", "n_ids"), "part", ["seq"], "n_ids", "begin").select("part", "seq", "begin")
    placed = groups.join(heads, ["part", "seq"])

    def restore(batches):
        for batch in batches:
            for row in batch.to_pylist():
                ids = token_coder.decode(row["blocks"])
                if len(ids) != row["n_ids"]:
                    raise ValueError("a group has not the number of ids that it states")
                lengths = np.array(row["n_tokens"], np.int64)
                ends = np.cumsum(lengths)
                raw = memoryview(ids.astype("<u4")).cast("B")
                crc = [zlib.crc32(raw[4 * (e - n) : 4 * e]) for e, n in zip(ends.tolist(), lengths.tolist(), strict=True)]
                cols = [pa.array(row["doc_ids"], pa.int64()), pa.array(row["begin"] + ends - lengths), pa.array(lengths), pa.array(crc, pa.int64())]
                names = ["doc_id", "start", "n_tokens", "ids_crc32"]
                if with_ids:
                    cols.append(pa.ListArray.from_arrays(pa.array(np.r_[0, ends], pa.int32()), pa.array(ids.astype(np.int64))))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(cols, names)

    return placed.mapInArrow(restore, "doc_id long, start long, n_tokens long, ids_crc32 long" + (", ids array<long>" if with_ids else ""))


def op6_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Writes the ids of every document to files and returns what they hold: doc_id, start, n_tokens, ids_crc32."""
    path = f"{shared.shared_folder(spark)}/token-files-{uuid.uuid4().hex}"
    write(shared.load(spark, sf_dir, "documents").select("doc_id", "text"), path)
    return read(spark, path)
