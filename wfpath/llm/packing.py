"""Operator 8: best-fit packing by a configuration linear program over the length histogram.

Only the histogram of piece lengths (at most ``capacity`` numbers) comes to the driver.  The
program asks for the fewest sequences whose configurations cover it.  Multiplicative weights price
the lengths, a knapsack dynamic program finds the dearest way to fill one sequence without taking
a length more often than it is left, a fraction of what is left is covered by it, and the weights
of the lengths in it fall.  The fractions are rounded down once, and only what the rounding leaves
is packed best-fit decreasing, on the histogram too.  The plan says for ranges of the rank of a
piece among those of its length where it goes, so placing all pieces is one ranking and one lookup.

Nulls and edge cases: a null or empty text is its end id alone; rows that share a doc_id are
packed one by one; an empty table gives no rows.
"""

from __future__ import annotations

import bisect
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wfpath.llm import shared, tokens
from wfpath.llm import textbytes as tb

CAPACITY, END_ID, RANKS = 4096, 1, 256
#: Rounds at most; how fast weights fall; the share of the scarcest length that a step covers; lengths priced in a
#: round; how full a configuration has to be; draws without such a one before the rest is left to best fit.
ROUNDS, RATE, WIDTH, DRAWN, FULL, PATIENCE = 5000, 1.0, 0.9, 32, 0.998, 60


def dearest(prices: np.ndarray, lengths: np.ndarray, most: np.ndarray, capacity: int) -> dict[int, int]:
    """How often to take each length, at most ``most`` times, so that a sequence is worth most (bounded knapsack).

    A length that may be taken n times stands for bundles of 1, 2, 4, ... and the rest of it.
    """
    bundles = []
    for length, price, n in zip(lengths.tolist(), prices.tolist(), np.minimum(most, capacity // lengths).tolist(), strict=True):
        size = 1
        while n > 0:
            size = min(size, n)
            bundles.append((length, price, size))
            n, size = n - size, 2 * size
    best = np.zeros(capacity + 1)
    taken = np.zeros((len(bundles), capacity + 1), bool)
    for i, (length, price, size) in enumerate(bundles):
        w = length * size
        with_it = best[: capacity + 1 - w] + price * size
        np.greater(with_it, best[w:], out=taken[i, w:])
        np.maximum(best[w:], with_it, out=best[w:])
    found: dict[int, int] = {}
    room = capacity
    for i in range(len(bundles) - 1, -1, -1):
        if taken[i, room]:
            length, _, size = bundles[i]
            found[length] = found.get(length, 0) + size
            room -= length * size
    return found


def fractional(counts: np.ndarray, capacity: int, rounds: int = ROUNDS, rate: float = RATE, width: float = WIDTH) -> tuple[dict[tuple[tuple[int, int], ...], float], float]:
    """The covering program by multiplicative weights: configurations with how many sequences of each, and a lower bound.

    The program asks for the fewest sequences whose configurations cover every length's count.  A
    length's weight falls with the share of its count that is covered, and a price is the weight for
    each token of it.  A round prices a draw of lengths (all of them where they are few), which
    differs from round to round, and takes the configuration that is worth most; no length is taken
    more often than it is left.  A step covers the share ``width`` of what is left of the scarcest
    length of the configuration, but one sequence at least, so weights move by bounded factors.
    The bound is the dual value of the volume prices, or the number of lengths over half a sequence.
    """
    left = counts.astype(float)
    chosen: dict[tuple[tuple[int, int], ...], float] = {}
    total = float((left * np.arange(capacity + 1)).sum())
    bound = max(total / capacity, float(left[capacity // 2 + 1 :].sum()))
    rng = np.random.default_rng(0)
    poor = 0
    for _ in range(rounds):
        lengths = np.flatnonzero(left >= 1)
        if not len(lengths) or poor > PATIENCE:
            break
        if len(lengths) > DRAWN:
            volume = left[lengths] * lengths
            lengths = np.sort(rng.choice(lengths, DRAWN, replace=False, p=volume / volume.sum()))
        share = left[lengths] / counts[lengths]
        config = dearest(lengths * np.exp(rate * (share - 1)), lengths, np.floor(left[lengths]).astype(np.int64), capacity)
        at = np.array(list(config))
        often = np.array(list(config.values()), float)
        if (at * often).sum() < FULL * capacity:
            # a draw without a full configuration: another may have one
            poor += 1
            continue
        poor = 0
        step = max(1.0, width * float((left[at] / often).min()))
        left[at] -= often * step
        key = tuple(sorted(config.items(), reverse=True))
        chosen[key] = chosen.get(key, 0.0) + step
    return chosen, bound


def best_fit(counts: np.ndarray, capacity: int) -> list[tuple[tuple[tuple[int, int], ...], int]]:
    """Best-fit decreasing on the histogram: (configuration, how many sequences).  Equal sequences stay one group."""
    rooms: dict[int, list[tuple[tuple, int]]] = {}
    order: list[int] = []

    def put(room: int, config: tuple, many: int) -> None:
        if room not in rooms:
            rooms[room] = []
            bisect.insort(order, room)
        rooms[room].append((config, many))

    for length in range(capacity, 0, -1):
        left = int(counts[length])
        while left:
            at = bisect.bisect_left(order, length)
            if at < len(order):
                room = order[at]
                config, many = rooms[room].pop()
                if not rooms[room]:
                    del rooms[room], order[at]
                fit = max(1, min(room // length, -(-left // many)))
                if fit * many <= left:
                    put(room - fit * length, (*config, (length, fit)), many)
                    left -= fit * many
                else:
                    used = left // fit
                    if used == 0:
                        fit, used = left, 1
                    put(room - fit * length, (*config, (length, fit)), used)
                    if many > used:
                        put(room, config, many - used)
                    left -= fit * used
            else:
                fit = capacity // length
                if left >= fit:
                    put(capacity - fit * length, ((length, fit),), left // fit)
                    left %= fit
                else:
                    put(capacity - left * length, ((length, left),), 1)
                    left = 0
    return [group for room in order for group in rooms[room]]


def plan(counts: np.ndarray, capacity: int = CAPACITY) -> list[tuple[tuple[tuple[int, int], ...], int]]:
    """Configurations and how many sequences of each, covering the histogram exactly.

    The program's fractions are rounded down once; best-fit decreasing packs what they leave.
    """
    left, groups = counts.copy(), []
    for config, many in fractional(counts, capacity)[0].items():
        whole = min([int(many), *(int(left[v]) // k for v, k in config)])
        if whole > 0:
            for v, k in config:
                left[v] -= k * whole
            groups.append((config, whole))
    return groups + best_fit(left, capacity)


def ranges(groups) -> dict[str, np.ndarray]:
    """The plan as sorted ranges: pieces of a length with rank from ``first`` on go to these sequences."""
    rows, cursor, base = [], {}, 0
    for config, many in groups:
        offset = 0
        for length, often in config:
            rows.append((length, cursor.get(length, 0), base, often, offset))
            cursor[length] = cursor.get(length, 0) + often * many
            offset += length * often
        base += many
    rows.sort()
    cols = np.array(rows, np.int64).reshape(-1, 5).T
    return dict(zip(("length", "first", "base", "often", "offset"), cols, strict=True))


def place(lengths: np.ndarray, ranks: np.ndarray, table: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Sequence and offset of pieces by length and rank."""
    key = (table["length"] << 44) | table["first"]
    at = np.searchsorted(key, (lengths << 44) | ranks, "right") - 1
    j = ranks - table["first"][at]
    often = table["often"][at]
    return table["base"][at] + j // often, table["offset"][at] + lengths * (j % often)


def pieces(docs: DataFrame, capacity: int = CAPACITY, end_id: int = END_ID, vocabulary: str = tokens.VOCABULARY) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 of every piece of every whole text."""
    keep = docs.select("doc_id", F.col("text").cast("string").alias("text"))

    def cut(batches):
        for batch in batches:
            text, ids_of = batch.column(batch.schema.get_field_index("text")), batch.column(batch.schema.get_field_index("doc_id"))
            offsets = tb.texts_of(text)[1]
            for a, b in tb.slices(offsets, tokens.SLICE):
                ids, at = tokens.encode(text.slice(a, b - a), end_id, vocabulary)
                total = np.diff(at)
                many = -(-total // capacity)
                which = np.repeat(np.arange(b - a), many)
                piece = tokens.spread(np.zeros(b - a, np.int64), many)
                start = piece * capacity
                length = np.minimum(capacity, total[which] - start)
                begin = at[which] + start
                raw = memoryview(ids.astype("<u4")).cast("B")
                crc = [zlib.crc32(raw[4 * s : 4 * (s + n)]) for s, n in zip(begin.tolist(), length.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([ids_of.slice(a, b - a).take(pa.array(which)), pa.array(piece, pa.int32()), pa.array(start), pa.array(length), pa.array(crc, pa.int64())], ["doc_id", "piece", "start", "length", "ids_crc32"])

    kind = keep.schema["doc_id"].dataType.simpleString()
    return keep.mapInArrow(cut, f"doc_id {kind}, piece int, start long, length long, ids_crc32 long")


def packed(docs: DataFrame, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """Every piece with its sequence and its offset there."""
    cut = shared.materialised(pieces(docs, capacity, end_id))
    counts = np.zeros(capacity + 1, np.int64)
    for r in cut.groupBy("length").count().collect():  # at most ``capacity`` rows
        counts[r["length"]] = r["count"]
    table = ranges(plan(counts, capacity))
    shared_table = docs.sparkSession.sparkContext.broadcast(table)  # ranges of lengths: bounded by capacity, not by rows
    dealt = cut.withColumn("one", F.lit(1).cast("long")).withColumn("part", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(RANKS)))
    ranked = shared.running_total(dealt, "part", [F.asc_nulls_first("doc_id"), "piece", "ids_crc32"], "one", "rank", groups=["length"])

    def put(batches):
        for batch in batches:
            col = lambda k: batch.column(batch.schema.get_field_index(k))
            sequence, offset = place(col("length").to_numpy(zero_copy_only=False), col("rank").to_numpy(zero_copy_only=False), shared_table.value)
            names = ["doc_id", "piece", "start", "length", "ids_crc32"]
            yield pa.RecordBatch.from_arrays([*[col(k) for k in names], pa.array(sequence), pa.array(offset)], [*names, "sequence_id", "offset"])

    kind = cut.schema["doc_id"].dataType.simpleString()
    return ranked.select("doc_id", "piece", "start", "length", "ids_crc32", "rank").mapInArrow(put, f"doc_id {kind}, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")


def op8_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset of every piece."""
    return packed(shared.load(spark, sf_dir, "documents").select("doc_id", "text"))
