"""Operator 7: suffix-array deduplication of repeated byte strings.

A byte belongs to a repeat if a string of ``SIZE`` bytes that covers it starts anywhere else.  A
suffix array over all bytes of a corpus can't be sorted in one place, and needn't be: strings
that are equal have the same smallest 64-byte hash, so suffixes are dealt by it.

1. Neighbouring starts with the same smallest hash form a run; runs whose hash occurs once in
   the corpus (and only once within the run) repeat nothing and are dropped.
2. Runs of equal content are combined: one of them stands for all in what follows, and the others
   are repeats as wholes.
3. The different contents that share a smallest hash form a collection, which gets its suffix
   order to the depth of SIZE (prefix doubling, ties by position), for each position its previous
   and next smaller positions in that order, and the longest previous factor as the longer of the
   common prefixes with those two.  A factor that reaches SIZE has an earlier copy at its source,
   and the source a later one.
4. A collection of more than ``LARGEST`` bytes is cut into finer ones before: starts are dealt by
   how far behind them the smallest hash stands, in ranges of 17 and then of 1, and by the bytes
   that all strings of such a range share.  Equal strings stay together at each cut, and the same
   three steps follow, so no task holds an unbounded collection.

``keep_first`` removes only what has an earlier copy (in the order of doc_id and position); the
query removes every copy.  Strings are judged on the input, not on what is left.

Nulls and edge cases: a null text is empty; rows with the same doc_id and text are one document;
a null doc_id comes after all others; shorter texts than SIZE keep all bytes; a text made of one
repeated letter is a single run and goes through its suffix array.  Texts over 4 MB are scanned
in overlapping parts.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wfpath.llm import shared
from wfpath.llm import textbytes as tb
from wfpath.llm.substring_dedup import columns, removed_mask, signed

SIZE, GRAM = 200, 64
LARGEST, TOGETHER = 4 << 20, 1 << 20
#: How many distances of the smallest hash a finer collection spans, level by level.
FINER = (17, 1)
PART = 4 << 20
RUN = "v long, h long, n int, again boolean, doc long, rid int, s int"
LAST = (1 << 63) - 1


def keyed(docs: DataFrame) -> DataFrame:
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    return docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST)).alias("doc"), F.col("doc_id").isNull().alias("nameless"), F.hash(text).alias("rid"), text.alias("text"))


def parts(offsets: np.ndarray, size: int):
    """Rows [a, b) and bytes [from, to) to scan at once: several texts, or a part of a long one."""
    for a, b in tb.slices(offsets):
        lo, hi = int(offsets[a]), int(offsets[b])
        if b - a > 1 or hi - lo <= PART:
            yield a, b, lo, hi
        else:
            for at in range(lo, hi - size + 1, PART):
                yield a, b, at, min(hi, at + PART + size - 1)


def scanned(data: np.ndarray, bounds: np.ndarray, size: int, gram: int):
    """Runs of a part: smallest hash, hash of the bytes, first start, number, and whether the smallest hash is there twice."""
    grams = tb.byte_grams(data, gram)
    width = size - gram + 1
    v, s, n = tb.runs_of_minima(grams, tb.inside(bounds, size), width)
    if not len(v):
        return v, v, s, n, np.zeros(0, bool)
    view = np.lib.stride_tricks.sliding_window_view(grams, width)
    again = np.empty(len(v), bool)
    for a in range(0, len(v), 4096):
        c = slice(a, a + 4096)
        low = s[c] + (view[s[c]] == v[c, None]).argmax(axis=1)
        top = s[c] + n[c] - 1
        again[c] = low != top + width - 1 - (view[top][:, ::-1] == v[c, None]).argmax(axis=1)
    return v, tb.spans(tb._TABLE[data], s, s + n + size - 1), s, n, again


def runs(texts: DataFrame, size: int = SIZE, gram: int = GRAM) -> DataFrame:
    def scan(batches):
        for batch in batches:
            doc, rid, text = columns(batch, "doc", "rid", "text")
            data, offsets = tb.texts_of(text)
            for a, b, lo, hi in parts(offsets, size):
                bounds = np.clip(offsets[a : b + 1], lo, hi) - lo
                v, h, s, n, again = scanned(data[lo:hi], bounds, size, gram)
                if len(v):
                    owner = np.searchsorted(bounds, s, "right") - 1
                    of = pa.array(owner + a)
                    at = s + lo - offsets[owner + a]
                    yield pa.RecordBatch.from_arrays([signed(v), signed(h), pa.array(n, pa.int32()), pa.array(again), doc.take(of), rid.take(of), pa.array(at, pa.int32())], ["v", "h", "n", "again", "doc", "rid", "s"])

    return texts.mapInArrow(scan, RUN)


def ranks(data: np.ndarray, size: int) -> tuple[list[int], list[np.ndarray]]:
    """The ranks of all suffixes by their first symbols, equal prefixes alike, by prefix doubling: depths and ranks up to ``size``."""
    n = len(data)
    padded = np.zeros(n + 8, np.uint16)
    padded[:n] = data
    wide = np.zeros(n, np.uint64)
    depths = [min(4, size)]
    for j in range(depths[0]):
        wide = (wide << np.uint64(16)) | padded[j : j + n].astype(np.uint64)
    found = [np.unique(wide, return_inverse=True)[1].astype(np.int32)]
    while depths[-1] < size:
        step = min(depths[-1], size - depths[-1])
        pair = found[-1].astype(np.int64) * (n + 1)
        pair[: n - step] += found[-1][step:] + 1
        found.append(np.unique(pair, return_inverse=True)[1].astype(np.int32))
        depths.append(depths[-1] + step)
    return depths, found


def smaller_neighbours(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each element of a sequence of different numbers: where the nearest smaller ones before and after it stand (-1: nowhere).

    Everything between an element and its candidate is larger than it; a candidate that is larger
    too is replaced by its own candidate, so distances double.
    """

    def before(y: np.ndarray) -> np.ndarray:
        at = np.arange(-1, len(y) - 1)
        live = np.flatnonzero(at >= 0)
        live = live[y[at[live]] > y[live]]
        while len(live):
            at[live] = at[at[live]]
            live = live[at[live] >= 0]
            live = live[y[at[live]] > y[live]]
        return at

    after = len(x) - 1 - before(x[::-1])[::-1]
    return before(x), np.where(after == len(x), -1, after)


def common(depths: list[int], found: list[np.ndarray], i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """The common prefixes of suffixes i and j, as far as the ranks' depth (j = -1: none); short of it, a lower bound to 3 symbols."""
    n = len(found[0])
    length = np.where((j >= 0) & (found[-1][i] == found[-1][j]), depths[-1], 0)
    for depth, rank in zip(depths[-2::-1], found[-2::-1], strict=True):
        a, b = i + length, j + length
        fits = (j >= 0) & (length + depth <= depths[-1]) & (a < n) & (b < n)
        fits &= rank[np.where(fits, a, 0)] == rank[np.where(fits, b, 0)]
        length = length + np.where(fits, depth, 0)
    return length


def previous_factors(data: np.ndarray, at: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """The longest previous factor (up to ``size``) of each start ``at`` among those starts, and its source (a place in ``at``).

    ``at`` is sorted.  Starts with equal prefixes stand by position in the suffix order, so of
    several copies each but the last is the source of the next.
    """
    depths, found = ranks(data, size)
    order = np.lexsort((at, found[-1][at]))
    previous, following = smaller_neighbours(order)
    factor, source = np.zeros(len(at), np.int64), np.full(len(at), -1)
    for side in (previous, following):
        other = np.where(side >= 0, order[side], -1)
        length = common(depths, found, at[order], np.where(side >= 0, at[other], -1))
        better = length > factor[order]
        factor[order[better]], source[order[better]] = length[better], other[better]
    return factor, source


def copies(data: np.ndarray, at: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Which starts have an earlier copy of their string, and which a later one."""
    factor, source = previous_factors(data, at, size)
    earlier, later = factor >= size, np.zeros(len(at), bool)
    later[source[earlier]] = True
    return earlier, later


def longest_previous_factors(data: bytes) -> np.ndarray:
    """The longest previous factor of every position of one text, in full length."""
    symbols = np.frombuffer(data, np.uint8).astype(np.uint16) + 1
    if not len(symbols):
        return np.zeros(0, np.int64)
    order = np.argsort(ranks(symbols, max(len(symbols), 1))[1][-1], kind="stable")
    out = np.zeros(len(symbols), np.int64)
    for side in smaller_neighbours(order):
        for i, k in zip(order.tolist(), side.tolist(), strict=True):
            j, length = int(order[k]), 0
            while k >= 0 and i + length < len(symbols) and symbols[i + length] == symbols[j + length]:
                length += 1
            out[i] = max(out[i], length)
    return out


def _collections(batches, size: int, keep_first: bool):
    """Runs in the order of v, put together to about TOGETHER bytes of whole collections; marks of the lone ones."""
    held: list[dict] = []
    weight = 0

    def marks():
        lengths = np.array([len(x["bytes"]) for x in held])
        stops = np.cumsum(lengths + 1)
        data = np.zeros(int(stops[-1]), np.uint16)
        begin = stops - lengths - 1
        for x, a, n in zip(held, begin.tolist(), lengths.tolist(), strict=True):
            data[a : a + n] = np.frombuffer(x["bytes"], np.uint8).astype(np.uint16) + 1
        starts = lengths - size + 1
        at = np.arange(int(starts.sum())) + np.repeat(begin - (np.cumsum(starts) - starts), starts)
        earlier, later = copies(data, at, size)
        hit = earlier if keep_first else earlier | later
        new = np.flatnonzero(hit & ~np.r_[False, hit[:-1] & (np.diff(at) == 1)])
        stop = np.flatnonzero(hit & ~np.r_[hit[1:] & (np.diff(at) == 1), False])
        which = np.searchsorted(begin, at[new], "right") - 1
        out = [(held[w]["doc"], held[w]["rid"], held[w]["s"] + int(a - begin[w]), int(b - a) + 1) for w, a, b in zip(which.tolist(), at[new].tolist(), at[stop].tolist(), strict=True)]
        cols = list(zip(*out, strict=True)) or [(), (), (), ()]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int32(), pa.int32(), pa.int32()), strict=True)], ["doc", "rid", "s", "n"])

    for batch in batches:
        for row in batch.to_pylist():
            if held and weight > TOGETHER and row["v"] != held[-1]["v"]:
                yield marks()
                held, weight = [], 0
            held.append(row)
            weight += len(row["bytes"])
    if held:
        yield marks()


def _contexts(size: int):
    """The bytes of wanted runs: rows (doc, rid, text, runs) to rows (v, doc, rid, s, large, bytes)."""

    def cut(batches):
        for batch in batches:
            doc, rid, text, wished = columns(batch, "doc", "rid", "text", "runs")
            data, offsets = tb.texts_of(text)
            cols: list[list] = [[], [], [], [], [], []]
            weight = 0
            for i in range(batch.num_rows):
                for r in wished[i].as_py():
                    at = int(offsets[i]) + r["s"]
                    for c, x in zip(cols, (r["v"], doc[i].as_py(), rid[i].as_py(), r["s"], r["large"], data[at : at + r["n"] + size - 1].tobytes()), strict=True):
                        c.append(x)
                    weight += r["n"] + size
                if weight > 4 << 20:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, _CUT, strict=True)], _NAMES)
                    cols, weight = [[], [], [], [], [], []], 0
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, _CUT, strict=True)], _NAMES)

    return cut


def finer(data: np.ndarray, size: int, gram: int, span: int) -> tuple[np.ndarray, ...]:
    """Runs of one context by the place of the leftmost smallest hash and its distance in ranges of ``span``.

    Hash of what all strings of the range share (and of the range), hash of the run's bytes, first start, number.
    """
    grams = tb.byte_grams(data, gram)
    starts, width = np.arange(len(data) - size + 1), size - gram + 1
    low = tb.sliding_min(grams, width)
    place = np.empty(len(starts), np.int64)
    view = np.lib.stride_tricks.sliding_window_view(grams, width)
    for a in range(0, len(starts), 4096):
        place[a : a + 4096] = starts[a : a + 4096] + (view[a : a + 4096] == low[a : a + 4096, None]).argmax(axis=1)
    part = (place - starts) // span
    new = np.flatnonzero(np.r_[True, (place[1:] != place[:-1]) | (part[1:] != part[:-1])])
    n = np.diff(np.r_[new, len(starts)])
    values, p, k = tb._TABLE[data], place[new], part[new]
    # a last range may reach beyond the farthest distance, where no string lies
    far = np.minimum((k + 1) * span, width) - 1
    shared_bytes = tb.spans(values, p - k * span, p - far + size)
    return tb.mix(shared_bytes + tb.mix(k.astype(tb.U64) + tb.U64(span << 16))), tb.spans(values, new, new + n + size - 1), new, n


def refined(contexts: DataFrame, size: int, gram: int, span: int) -> DataFrame:
    """The runs of large collections' contexts, dealt more finely."""

    def scan(batches):
        for batch in batches:
            for row in batch.to_pylist():
                v, h, s, n = finer(np.frombuffer(row["bytes"], np.uint8), size, gram, span)
                many = len(v)
                yield pa.RecordBatch.from_arrays([signed(v), signed(h), pa.array(n, pa.int32()), pa.array(np.zeros(many, bool)), pa.array(np.full(many, row["doc"])), pa.array(np.full(many, row["rid"]), pa.int32()), pa.array(s + row["s"], pa.int32())], ["v", "h", "n", "again", "doc", "rid", "s"])

    return contexts.mapInArrow(scan, RUN)


def repeats(texts: DataFrame, size: int = SIZE, gram: int = GRAM, keep_first: bool = False, largest: int = LARGEST) -> DataFrame:
    """Starts to remove, as ranges: doc, rid, s, n."""
    found, out = shared.materialised(runs(texts, size, gram)), None
    for span in (*FINER, 0):
        per_hash = found.groupBy("v").agg(F.count(F.lit(1)).alias("times"), F.max("again").alias("again"))
        per_hash = shared.materialised(per_hash.where("times > 1 OR again").select("v", "times"))
        likely = shared.materialised(shared.joined_by_count(found, per_hash, ["v"], "times"))
        shared.dropped(found, per_hash)
        content = likely.groupBy("v", "h", "n").agg(F.count(F.lit(1)).alias("times"), F.min(F.struct("doc", "rid", "s")).alias("least"), F.max("again").alias("again"))
        content = shared.materialised(content)
        per_collection = content.groupBy("v").agg(F.count(F.lit(1)).alias("kinds"), F.sum(F.col("n") + size - 1).alias("bytes"), F.max("again").alias("any_again"))
        whole = shared.joined_by_count(likely, content.where("times > 1").select("v", "h", "n", "times", "least"), ["v", "h", "n"], "times")
        if keep_first:
            whole = whole.where(F.struct("doc", "rid", "s") > F.col("least"))
        mixed = content.join(per_collection.where("kinds > 1 OR any_again"), "v")
        large = (F.col("bytes") > largest) & F.lit(span > 0)
        wanted = mixed.select("v", F.col("least.doc").alias("doc"), F.col("least.rid").alias("rid"), F.struct(F.col("least.s").alias("s"), "n", "v", large.alias("large")).alias("run"))
        lists = wanted.groupBy("doc", "rid").agg(F.collect_list("run").alias("runs"))
        contexts = shared.materialised(texts.select("doc", "rid", "text").join(lists, ["doc", "rid"]).mapInArrow(_contexts(size), "v long, doc long, rid int, s int, large boolean, bytes binary"))
        small = contexts.where("NOT large").drop("large").repartition("v").sortWithinPartitions("v", "doc", "rid", "s")
        marks = whole.select("doc", "rid", "s", "n").union(small.mapInArrow(lambda it: _collections(it, size, keep_first), "doc long, rid int, s int, n int"))
        out = marks if out is None else out.union(marks)
        if not span or not contexts.where("large").limit(1).count():
            return out
        # copies of a large collection's runs were combined above: all of them, but not what stands for them, are marked
        found = shared.materialised(refined(contexts.where("large"), size, gram, span))
    return out


_CUT = (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.bool_(), pa.binary())
_NAMES = ["v", "doc", "rid", "s", "large", "bytes"]


def marked(docs: DataFrame, size: int = SIZE, gram: int = GRAM, keep_first: bool = False) -> DataFrame:
    """Every document with the ranges of starts to remove: doc, rid, text, marks."""
    texts = keyed(docs)
    marks = repeats(texts, size, gram, keep_first).groupBy("doc", "rid").agg(F.collect_list(F.struct("s", "n")).alias("marks"))
    return texts.join(marks, ["doc", "rid"], "left").select("doc", "nameless", "rid", "text", "marks")


def kept_bytes(data: bytes, marks, size: int) -> tuple[bytes, int, int]:
    """What stays, how many bytes go, and in how many maximal stretches."""
    if not marks:
        return data, 0, 0
    s = np.array([m["s"] for m in marks], np.int64)
    s, e = tb.merged(s, s + np.array([m["n"] for m in marks], np.int64) + size - 1)
    kept, at = [], 0
    for a, b in zip(s.tolist(), e.tolist(), strict=True):
        kept.append(data[at:a])
        at = b
    kept.append(data[at:])
    return b"".join(kept), int((e - s).sum()), len(s)


def deduplicated(docs: DataFrame, size: int = SIZE, gram: int = GRAM, keep_first: bool = True) -> DataFrame:
    """``docs`` with later copies of repeated strings cut from the texts; all columns as they were.

    A stretch that begins or ends within a character is narrowed to whole characters.  A null text stays null.
    """
    marks = repeats(keyed(docs), size, gram, keep_first).groupBy("doc", "rid").agg(F.collect_list(F.struct("s", "n")).alias("_marks"))
    marks = marks.select(F.col("doc").alias("_doc"), F.col("rid").alias("_rid"), "_marks")
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    joined = docs.withColumn("_key", F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST))).withColumn("_hash", F.hash(text))
    joined = joined.join(marks, (F.col("_key") == F.col("_doc")) & (F.col("_hash") == F.col("_rid")), "left").drop("_key", "_hash", "_doc", "_rid")
    schema = docs.schema

    def cut(batches):
        for batch in batches:
            names = batch.schema.names
            at = names.index("text")
            texts, marks_of = batch.column(at).to_pylist(), batch.column(names.index("_marks")).to_pylist()
            for i, m in enumerate(marks_of):
                if m and texts[i]:
                    data = np.frombuffer(texts[i].encode(), np.uint8)
                    gone = removed_mask(len(data), m, size)
                    tail = (data & 0xC0) == 0x80
                    # a character goes only if all its bytes go
                    char = np.cumsum(~tail) - 1
                    stays = np.zeros(int(char[-1]) + 1, bool)
                    stays[char[~gone]] = True
                    texts[i] = data[stays[char]].tobytes().decode()
            cols = [pa.array(texts, batch.schema.field(at).type) if k == at else batch.column(k) for k in range(len(names)) if names[k] != "_marks"]
            yield pa.RecordBatch.from_arrays(cols, [x for x in names if x != "_marks"])

    return joined.mapInArrow(cut, schema)


def op7_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of every document."""

    def digest(batches):
        for batch in batches:
            doc, nameless, text, marks = columns(batch, "doc", "nameless", "text", "marks")
            rows = []
            for t, m in zip(text, marks, strict=True):
                data = t.as_py().encode()
                kept, gone, many = kept_bytes(data, m.as_py(), SIZE)
                rows.append((len(data), gone, many, hashlib.sha256(kept).hexdigest()))
            cols = list(zip(*rows, strict=True)) or [(), (), (), ()]
            ids = pa.array([None if x else d for d, x in zip(doc.to_pylist(), nameless.to_pylist(), strict=True)], pa.int64())
            yield pa.RecordBatch.from_arrays([ids, *[pa.array(c, pa.int64()) for c in cols[:3]], pa.array(cols[3], pa.string())], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    docs = shared.load(spark, sf_dir, "documents").select("doc_id", "text")
    return marked(docs).mapInArrow(digest, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")
