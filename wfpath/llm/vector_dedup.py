"""Operator 9: embedding near-duplicates by product quantisation with coarse inverted lists.

A bounded sample trains coarse centroids and, on the residuals, codebooks for sub-spaces; then
every vector is indexed: its list, its codes, and the length of what the codes miss.  As a query
it visits all lists whose cell is within ``reach`` of it, measured to the plane between its own
centroid and the other.  In a list the distance to a coded vector is a sum of table entries; by
the triangle inequality a pair can only be close if that distance differs from what the codes
miss by at most the radius, so this filter loses nothing.  What passes is compared by exact cosine
in double precision.

Equal vectors are one class with a size.  A list is cut into pieces of bounded size, for the
vectors indexed there and for the queries that visit it, and every pair of pieces is a group of
its own; a task holds one piece of the index while queries stream by.  Links are counted, and
only a spanning star per piece is kept of them.

Recall comes from ``reach`` alone: at the full radius it is 1; the default trades the few close
pairs that lie straight across a boundary.

Nulls and edge cases: a vector that is null, empty or zero or holds a null or non-finite
component links with nothing; vectors of different lengths never link; a null vec_id gets the
smallest id of its component, or null; rows that share a vec_id are vectors of their own.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wfpath.llm import shared
from wfpath.llm.substring_dedup import columns

#: Vectors that train the index (or 32 for each list, if that is more), lists at most, codes of a sub-space and its width.
SAMPLE, LISTS, CODES, WIDTH = 20_000, 4096, 64, 8
PIECE, VISITS, AT_ONCE = 4096, 16_384, 256
SIMILAR, REACH = 0.9, 0.14
LAST = (1 << 63) - 1


def matrix(column: pa.Array, dim: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dim)


def unit(x: np.ndarray) -> np.ndarray:
    top = np.abs(x).max(axis=1, keepdims=True)
    x = x / np.where(top > 0, top, 1)
    return x / np.maximum(np.sqrt((x * x).sum(axis=1, keepdims=True)), 1e-300)


def means(x: np.ndarray, k: int, rounds: int = 12, seed: int = 3) -> np.ndarray:
    """k centroids by Lloyd's iterations from a fixed random start; an empty one keeps its place."""
    rng = np.random.default_rng(seed)
    centres = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        near = nearest(x, centres)
        count = np.bincount(near, minlength=len(centres))
        total = np.zeros_like(centres)
        np.add.at(total, near, x)
        centres = np.where(count[:, None] > 0, total / np.maximum(count, 1)[:, None], centres)
    return centres


def squared(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.maximum((x * x).sum(1)[:, None] - 2 * x @ y.T + (y * y).sum(1)[None], 0)


def nearest(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return np.concatenate([squared(x[i : i + 4096], centres).argmin(axis=1) for i in range(0, len(x), 4096)]) if len(x) else np.zeros(0, np.int64)


class Index:
    """Coarse centroids and codebooks; all of fixed size."""

    def __init__(self, sample: np.ndarray, lists: int) -> None:
        n, self.dim = sample.shape
        self.centres = means(sample, max(1, min(lists, n // 16)))
        self.cuts = list(range(0, self.dim, WIDTH)) + [self.dim]
        rest = sample - self.centres[nearest(sample, self.centres)]
        self.books = [means(rest[:, a:b], CODES, 8) for a, b in zip(self.cuts[:-1], self.cuts[1:], strict=True)]
        self.apart = np.sqrt(squared(self.centres, self.centres))

    def coded(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """List, codes, and the length of what the codes miss."""
        at = nearest(x, self.centres)
        rest = x - self.centres[at]
        codes = np.stack([nearest(rest[:, a:b], book) for a, b, book in zip(self.cuts[:-1], self.cuts[1:], self.books, strict=True)], axis=1).astype(np.uint8)
        told = np.concatenate([book[codes[:, m]] for m, book in enumerate(self.books)], axis=1)
        return at, codes, np.sqrt(((rest - told) ** 2).sum(axis=1))

    def visits(self, x: np.ndarray, reach: float) -> np.ndarray:
        """Which lists each query visits."""
        d = squared(x, self.centres)
        at = d.argmin(axis=1)
        own = d[np.arange(len(x)), at]
        return (d - own[:, None]) <= 2 * reach * self.apart[at] + 1e-12

    def tables(self, q: np.ndarray, at: int) -> list[np.ndarray]:
        """Squared distances of queries, seen from a list's centroid, to every code of every sub-space."""
        rest = q - self.centres[at]
        return [squared(rest[:, a:b], book) for a, b, book in zip(self.cuts[:-1], self.cuts[1:], self.books, strict=True)]


def classes(vectors: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Rows (vec, k1, k2) of all usable vectors, and one row (k1, k2, dim, size, least, embedding) for equal ones."""
    v = vectors.select(F.coalesce(F.col("vec_id").cast("long"), F.lit(LAST)).alias("vec"), F.col("embedding").cast("array<double>").alias("e"))
    fine = F.forall("e", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))) & F.exists("e", lambda x: x != 0)
    v = v.where(F.col("e").isNotNull() & (F.size("e") > 0)).where(fine)
    v = v.withColumn("k1", F.xxhash64("e")).withColumn("k2", F.xxhash64(F.lit(1), "e", F.lit(2)))
    c = v.groupBy("k1", "k2").agg(F.count(F.lit(1)).alias("size"), F.min("vec").alias("least"), F.first("e").alias("e"))
    return v.select("vec", "k1", "k2"), c.withColumn("dim", F.size("e"))


def _compare(batches, index: Index, similar: float):
    """Groups in order, indexed rows (role 0) before queries: counts of links, and stars that keep the components."""
    radius = float(np.sqrt(max(0.0, 2 - 2 * similar))) + 1e-9
    group, ids, sizes, held, codes, miss, label = None, [], [], [], [], [], None
    out: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

    def stars():
        other = np.flatnonzero(label != np.arange(len(label)))
        out.append((ids[other], ids[label[other]], np.zeros(len(other), np.int64)))

    for batch in batches:
        cols = [batch.column(k).to_numpy(zero_copy_only=False) for k in range(5)]
        key = np.stack(cols[:3], axis=1)
        edges = np.flatnonzero(np.r_[True, (np.diff(key, axis=0) != 0).any(axis=1) | (np.diff(cols[3]) != 0), True]) if batch.num_rows else [0]
        vectors = unit(matrix(batch.column(6), index.dim)) if batch.num_rows else np.zeros((0, index.dim))
        for s, e in zip(edges[:-1], edges[1:], strict=True):
            now = tuple(key[s])
            if now != group:
                if label is not None:
                    stars()
                group, ids, sizes, held, label = now, np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros((0, index.dim)), None
            k, n, x = batch.column(4).slice(s, e - s).to_numpy(), batch.column(5).slice(s, e - s).to_numpy(), vectors[s:e]
            if cols[3][s] == 0:
                ids, sizes, held = np.r_[ids, k], np.r_[sizes, n], np.vstack([held, x])
                continue
            if not len(ids):
                continue
            if label is None:
                label = np.arange(len(ids))
                at, codes, miss = index.coded(held)
            for a in range(0, len(k), AT_ONCE):
                q, qk = x[a : a + AT_ONCE], k[a : a + AT_ONCE]
                seen = np.zeros((len(q), len(ids)))
                for m, table in enumerate(index.tables(q, int(now[0]))):
                    seen += table[:, codes[:, m]]
                i, j = np.nonzero((np.abs(np.sqrt(seen) - miss) <= radius) & (qk[:, None] != ids[None]))
                near = np.zeros(len(i), bool)
                for c in range(0, len(i), 65_536):
                    near[c : c + 65_536] = np.einsum("ij,ij->i", q[i[c : c + 65_536]], held[j[c : c + 65_536]]) >= similar
                i, j = i[near], j[near]
                count = np.bincount(i, sizes[j], minlength=len(q)).astype(np.int64)
                root = shared.local_components(len(ids) + len(q), np.r_[j, np.arange(len(ids))], np.r_[i + len(ids), label])
                label = root[: len(ids)]
                linked = np.flatnonzero(count)
                out.append((qk[linked], ids[root[len(ids) + linked]], count[linked]))
        while out:
            yield _links(out.pop())
    if label is not None:
        stars()
    while out:
        yield _links(out.pop())


def _links(columns_) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns_], ["a", "b", "n"])


def linked(reps: DataFrame, dim: int, similar: float = SIMILAR, reach: float = REACH) -> DataFrame:
    """Link rows (a, b, n) between classes of one dimension: n counts a's links, (a, b) rows keep the components."""
    spark = reps.sparkSession
    # lists grow with the root of the vectors, so a list does too; the sample that trains them is bounded
    lists = max(1, min(LISTS, int(np.sqrt(reps.count()))))
    sample = shared.sampled(reps.select("k1", "e"), ["k1"], max(SAMPLE, 32 * lists)).orderBy("k1").toArrow()
    index = Index(unit(matrix(sample.column("e").combine_chunks(), dim)) if len(sample) else np.ones((1, dim)) / np.sqrt(dim), lists)
    shared_index = spark.sparkContext.broadcast(index)

    def spread(batches):
        own = shared_index.value
        for batch in batches:
            k, size, e = columns(batch, "k1", "size", "e")
            x = unit(matrix(e, dim)) if batch.num_rows else np.zeros((0, dim))
            for a in range(0, len(x), 1024):
                part = x[a : a + 1024]
                i, at = np.nonzero(own.visits(part, reach))
                home = nearest(part, own.centres)
                which = np.r_[np.arange(len(part)), i] + a
                role = np.r_[np.zeros(len(part), np.int8), np.ones(len(i), np.int8)]
                yield pa.RecordBatch.from_arrays([pa.array(np.r_[home, at].astype(np.int32)), pa.array(role), k.take(pa.array(which)), size.take(pa.array(which)), e.take(pa.array(which))], ["list", "role", "k1", "size", "e"])

    rows = shared.materialised(reps.select("k1", "size", "e").mapInArrow(spread, "list int, role byte, k1 long, size long, e array<double>"))
    # at most LISTS rows: how many pieces each list is cut into
    counted = rows.groupBy("list").agg(F.sum(F.when(F.col("role") == 0, 1).otherwise(0)).alias("n"), F.sum(F.col("role").cast("long")).alias("q")).collect()
    cuts = {r["list"]: (-(-r["n"] // PIECE) or 1, -(-r["q"] // VISITS) or 1) for r in counted}
    pieces = spark.createDataFrame([(a, p, q) for a, (p, q) in cuts.items()] or [(0, 1, 1)], "list int, pieces int, parts int")
    x = rows.join(F.broadcast(pieces), "list")
    h = F.xxhash64("k1", F.lit(5))
    own_piece, own_part = F.pmod(h, F.col("pieces")).cast("int"), F.pmod(h, F.col("parts")).cast("int")
    every = lambda n: F.sequence(F.lit(0), F.col(n) - 1)
    x = x.withColumn("piece", F.explode(F.when(F.col("role") == 0, F.array(own_piece)).otherwise(every("pieces"))))
    x = x.withColumn("part", F.explode(F.when(F.col("role") == 1, F.array(own_part)).otherwise(every("parts"))))
    x = x.select("list", "piece", "part", F.col("role").cast("int").alias("role"), "k1", "size", "e")
    x = x.repartition("list", "piece", "part").sortWithinPartitions("list", "piece", "part", "role", "k1")
    return x.mapInArrow(lambda it: _compare(it, shared_index.value, similar), "a long, b long, n long")


def near_duplicates(vectors: DataFrame, similar: float = SIMILAR, reach: float = REACH) -> DataFrame:
    """vec_id, n_links, component_id, kept of every row."""
    members, reps = classes(vectors)
    members, reps = shared.materialised(members), shared.materialised(reps)
    links = None
    for r in reps.select("dim").distinct().orderBy("dim").collect():
        some = linked(reps.where(F.col("dim") == r["dim"]), r["dim"], similar, reach)
        links = some if links is None else links.union(some)
    if links is None:
        links = vectors.sparkSession.createDataFrame([], "a long, b long, n long")
    links = shared.materialised(links)
    counts = links.groupBy("a").agg(F.sum("n").alias("n")).select(F.col("a").alias("k1"), "n")
    comps = shared.materialised(shared.components(links.where("a <> b"), "a", "b"))
    smallest = comps.join(reps, comps["id"] == reps["k1"]).groupBy("component").agg(F.min("least").alias("component_id"))
    named = comps.join(smallest, "component").select(F.col("id").alias("k1"), "component_id")
    found = reps.select("k1", "k2", "size", "least").join(counts, "k1", "left").join(named, "k1", "left")
    found = found.select("k1", "k2", (F.col("size") - 1 + F.coalesce("n", F.lit(0))).alias("n_links"), F.coalesce("component_id", "least").alias("component_id"))
    usable = members.join(found, ["k1", "k2"]).select("vec", "n_links", "component_id")
    fine = _usable(vectors)
    rest = vectors.where(~fine).select(F.coalesce(F.col("vec_id").cast("long"), F.lit(LAST)).alias("vec"), F.lit(0).cast("long").alias("n_links")).withColumn("component_id", F.col("vec"))
    named_or_null = lambda c: F.when(F.col(c) != LAST, F.col(c))
    out = usable.union(rest).select(named_or_null("vec").alias("vec_id"), "n_links", named_or_null("component_id").alias("component_id"))
    return out.withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


def _usable(vectors: DataFrame):
    e = F.col("embedding").cast("array<double>")
    fine = F.forall(e, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))) & F.exists(e, lambda x: x != 0)
    return F.coalesce(F.col("embedding").isNotNull() & (F.size(e) > 0) & fine, F.lit(False))


def op9_vector_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vec_id, n_links, component_id, kept of every embedding."""
    return near_duplicates(shared.load(spark, sf_dir, "embeddings").select("vec_id", "embedding"))
