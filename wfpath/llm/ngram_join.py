"""Operator 5: n-gram Jaccard join by partitioning the universe of shingles.

Sets of sizes x and y with a Jaccard similarity of at least 4/5 differ in at most (x + y) / 9
shingles.  Sizes fall into bands; for each band the universe of shingle hashes is cut into
segments.  If a set's segments are allotted numbers that sum to more than the largest difference,
one segment differs by less than its number (pigeonhole).  A segment with number 1 is found by
the hash of the set's subset there; number 2 also needs the hashes of the subset with one shingle
deleted, on both sides.  Allocation follows the cost: an empty subset gets 0 (everyone has it), a
lone shingle 1, and larger subsets 2 in bands of small sets, where deletions are few and subsets
would be too small to tell sets apart, and 1 elsewhere.  A set is indexed with all its segments in
its own band.  If its partners may lie in the next band, it is looked up there with only as many
segments as it needs, the largest first, as those meet the fewest false candidates.

Shingles that many documents share would fill whole segments alike in documents that have
nothing else in common.  A bounded sample names the most common ones; these have segments of
their own, which get 0 as long as a set's other segments suffice, and are used only by sets that
need them.  Which shingles are named changes the cost, never the result: a pair is found by the
other segments if either set has enough of those, and else both sets use all.

The number of segments leaves six standard deviations for empty ones.  A set that has too few
filled segments all the same is found through its single shingles instead (``_rest``), so nothing
is lost.

Equal sets are one class.  In a bucket of equal signatures members are compared with a pivot,
then with a member drawn for the bucket, not with each other; only where a bucket still holds
members of different components after that are the pairs across components compared too.  So a group of near copies costs about as
many comparisons as it has members, and no link between components is lost.

Nulls and edge cases: a null text, or one without words, has no shingles, and links with nothing;
one to four words are one shingle; a null doc_id is compared like others and gets the smallest id
of its component, or null; rows that share a doc_id are one document.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from wfpath.llm import shared
from wfpath.llm import textbytes as tb
from wfpath.llm.substring_dedup import columns, signed
from wfpath.llm.suffix_dedup import LAST, keyed
from wfpath.llm.tokens import spread

WORDS, DELETIONS_UP_TO, MARGIN, PARITY_WORDS = 5, 60, 6.0, 8
SAMPLE, COMMON, COMMON_FROM, ROUNDS = 8192, 1 << 18, 3, 2
U64 = np.uint64


class Bands:
    """Bands of set sizes: bounds, segments, and the number that segments are allotted."""

    def __init__(self, largest: int = 1 << 28, margin: float = MARGIN, deletions_up_to: int = DELETIONS_UP_TO) -> None:
        low, self.low, self.high = 1, [], []
        while low <= largest:
            high = max(low, low * 25 // 16)
            self.low.append(low)
            self.high.append(high)
            low = high + 1
        self.low, self.high = np.array(self.low), np.array(self.high)
        self.deletions = self.high <= deletions_up_to
        self.segments = np.array([self._segments(c, margin) for c in range(len(self.low))])

    def most(self, size, band):
        """The largest difference from a partner in this band."""
        return (size + np.minimum(self.high[band], size * 5 // 4)) // 9

    def _segments(self, c: int, margin: float) -> int:
        high = int(self.high[c])
        if high <= 8:
            return 1
        if self.deletions[c]:
            return max(3, -(-high // 3))
        sizes = np.unique(np.linspace(max(1, self.low[c] * 0.8), high, 6).astype(int))
        m = int(self.most(high, c)) + 1

        def enough(m: int) -> bool:
            empty = np.exp(-sizes / m)
            mean, deviation = m * (1 - empty), np.sqrt(np.maximum(m * (empty - (1 + sizes / m) * empty**2), 1e-9))
            return bool((mean - margin * deviation >= self.most(sizes, c) + 1).all())

        while not enough(m):
            m += max(1, m // 64)
        return m

    def of(self, sizes: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.high, sizes)


_bands: dict[tuple, Bands] = {}


def bands(margin: float = MARGIN) -> Bands:
    return _bands.setdefault((margin,), Bands(margin=margin))


def shingles(data: np.ndarray, offsets: np.ndarray, size: int = WORDS) -> tuple[np.ndarray, np.ndarray]:
    """The distinct shingle hashes of each text, text by text, and the text of each."""
    starts, ends, first = tb.word_bounds(data, offsets)
    words = tb.word_hashes(data, starts, ends, lower=True)
    grams, at = tb.windows(words, first, size)
    owner = np.searchsorted(first, at, "right") - 1
    short = np.flatnonzero((np.diff(first) > 0) & (np.diff(first) < size))
    if len(short):
        lone = tb.spans(words, first[short], first[short + 1])
        grams, owner = np.concatenate([grams, lone]), np.concatenate([owner, short])
    if not len(grams):
        return grams, owner
    keys = tb.mix(grams + owner.astype(U64) * U64(0x9E3779B97F4A7C15))
    at = np.unique(keys, return_index=True)[1]
    at = at[np.argsort(owner[at], kind="stable")]
    return grams[at], owner[at]


def _sums(x: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
    out = np.zeros(n, U64)
    np.add.at(out, owner, x)
    return out


def _signature(total: np.ndarray, band: np.ndarray, segment: np.ndarray) -> np.ndarray:
    return tb.mix(total + band.astype(U64) * U64(0xA24BAED4963EE407) + segment.astype(U64) * U64(0x9FB21C651E98DF25))


def signatures(grams: np.ndarray, owner: np.ndarray, sizes: np.ndarray, band: np.ndarray, b: Bands, probe: bool, common: np.ndarray):
    """Signatures of sets in the given bands, the set of each, whether each set is covered, and how many segments it could spare.

    The sets have ``sizes`` > 0 and their shingles stand set by set; ``common`` marks common shingles;
    with ``probe`` only as many segments as needed.
    """
    n = len(sizes)
    m = b.segments[band]
    base = 2 * (np.cumsum(m) - m)
    # each set has its m segments of other shingles, then m of common ones
    segment = ((grams >> U64(32)) * m[owner].astype(U64) >> U64(32)).astype(np.int64) + np.where(common, m[owner], 0)
    at = base[owner] + segment
    inner = tb.mix(grams ^ U64(0x5851F42D4C957F2D))
    cells = 2 * int(m.sum())
    total = _sums(inner, at, cells)
    count = np.bincount(at, minlength=cells)
    of = np.repeat(np.arange(n), 2 * m)
    own_segment = np.arange(cells) - base[of]
    shared = own_segment >= m[of]
    deep = b.deletions[band]
    worth = np.where(deep[of], np.minimum(count, 2), np.minimum(count, 1))
    need = b.most(sizes, band) + 1
    alone = np.bincount(of, np.where(shared, 0, worth), minlength=n) >= need
    worth[shared & alone[of]] = 0
    had = np.bincount(of, worth, minlength=n).astype(np.int64)
    covered = had >= need
    # with deletions several signatures stand for a segment, so none may be left out
    spare = np.where(deep | ~covered, 0, had - need)
    used = worth > 0
    if probe:
        order = np.lexsort((-count, shared, of))
        before = np.cumsum(worth[order]) - worth[order]
        before -= np.repeat(before[base], 2 * m)
        used[order[before >= need[of]]] = False
    f = np.flatnonzero(used)
    sig, whose = [_signature(total[f], band[of[f]], own_segment[f])], [of[f]]
    d = np.flatnonzero(deep[owner] & used[at] & (count[at] >= 2))
    if len(d):
        sig.append(_signature(total[at[d]] - inner[d], band[owner[d]], segment[d]))
        whose.append(owner[d])
    return np.concatenate(sig), np.concatenate(whose), covered, spare


def common_shingles(texts: DataFrame, n_docs: int, size: int = WORDS, sample: int = SAMPLE, most: int = COMMON) -> np.ndarray:
    """Hashes of shingles in several documents of a sample of about ``sample``: at most ``most``, the commonest first; sorted."""
    every = max(1, n_docs // sample)

    def scan(batches):
        for batch in batches:
            data, offsets = tb.texts_of(*columns(batch, "text"))
            for a, b in tb.slices(offsets):
                yield pa.RecordBatch.from_arrays([signed(shingles(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], size)[0])], ["shingle"])

    some = texts.where(F.pmod(F.xxhash64("doc", "rid"), F.lit(every)) == 0)
    counted = some.select("text").mapInArrow(scan, "shingle long").groupBy("shingle").count().where(F.col("count") >= COMMON_FROM)
    counted = shared.materialised(counted)
    # the lowest count from which on there are at most ``most``: only those come to the driver
    above = counted.groupBy("count").agg(F.count(F.lit(1)).alias("n")).select("count", F.sum("n").over(Window.orderBy(F.desc("count"))).alias("upto"))
    lowest = above.where(F.col("upto") <= most).agg(F.min("count").alias("c")).first()["c"]
    found = counted.where(F.col("count") >= (lowest if lowest is not None else 1 << 62)).select("shingle").toArrow().column("shingle").to_numpy()
    shared.dropped(counted)
    return np.sort(found.astype(np.int64).view(U64))


def described(texts: DataFrame, size: int = WORDS) -> DataFrame:
    """doc, rid, n (shingles), two hashes of the set, and its parity bits."""

    def scan(batches):
        for batch in batches:
            doc, rid, text = columns(batch, "doc", "rid", "text")
            data, offsets = tb.texts_of(text)
            for a, b in tb.slices(offsets):
                grams, owner = shingles(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], size)
                k = b - a
                yield pa.RecordBatch.from_arrays([doc.slice(a, k), rid.slice(a, k), pa.array(np.bincount(owner, minlength=k), pa.int64()), signed(set_key(grams, owner, k)), signed(_sums(tb.mix(grams * U64(0xD1342543DE82EF95)), owner, k)), parities(grams, owner, k)], ["doc", "rid", "n", "g", "g2", "bits"])

    return texts.mapInArrow(scan, "doc long, rid int, n long, g long, g2 long, bits array<long>")


def parities(grams: np.ndarray, owner: np.ndarray, n: int) -> pa.Array:
    """For each set 512 bits, each the parity of the number of its shingles there.

    Two sets differ by at least as many shingles as their bits differ, so a pair with too many
    different bits is no candidate.
    """
    bits = np.zeros(n * PARITY_WORDS, U64)
    slot = grams & U64(64 * PARITY_WORDS - 1)
    np.bitwise_xor.at(bits, owner * PARITY_WORDS + (slot >> U64(6)).astype(np.int64), U64(1) << (slot & U64(63)))
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1) * PARITY_WORDS, pa.int32()), signed(bits))


def set_key(grams: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
    return tb.mix(_sums(tb.mix(grams), owner, n))


def signed_sets(texts: DataFrame, known: np.ndarray, size: int = WORDS, margin: float = MARGIN) -> DataFrame:
    """Signature rows: sig, role (0 indexed, 1 looked up, 2 a set that isn't covered), g; ``known`` are the common shingles."""
    told = texts.sparkSession.sparkContext.broadcast(known)  # at most COMMON hashes

    def scan(batches):
        b, often = bands(margin), told.value
        for batch in batches:
            data, offsets = tb.texts_of(*columns(batch, "text"))
            for lo, hi in tb.slices(offsets):
                grams, owner = shingles(data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo], size)
                if not len(grams):
                    continue
                # one text for each different set of the slice
                keys = set_key(grams, owner, hi - lo)
                sizes = np.bincount(owner, minlength=hi - lo)
                chosen = np.zeros(hi - lo, bool)
                filled = np.flatnonzero(sizes)
                chosen[filled[np.unique(keys[filled], return_index=True)[1]]] = True
                number = np.cumsum(chosen) - 1
                keep = chosen[owner]
                grams, owner = grams[keep], number[owner[keep]]
                keys, sizes = keys[chosen], sizes[chosen]
                band = b.of(sizes)
                common = often[np.minimum(np.searchsorted(often, grams), len(often) - 1)] == grams if len(often) else np.zeros(len(grams), bool)
                for probe in (False, True):
                    some = np.ones(len(sizes), bool) if not probe else sizes * 5 // 4 > b.high[band]
                    if not some.any():
                        continue
                    renumber = np.cumsum(some) - 1
                    mine = some[owner]
                    sig, whose, covered, spare = signatures(grams[mine], renumber[owner[mine]], sizes[some], band[some] + probe, b, probe, common[mine])
                    k = keys[some]
                    role = np.full(len(sig), int(probe), np.int8)
                    lost = np.flatnonzero(~covered)
                    yield pa.RecordBatch.from_arrays([signed(np.r_[sig, k[lost]]), pa.array(np.r_[role, np.full(len(lost), 2, np.int8)], pa.int8()), signed(np.r_[k[whose], k[lost]]), pa.array(np.r_[np.zeros(len(whose), np.int32) if probe else spare[whose], np.zeros(len(lost), np.int32)], pa.int32())], ["sig", "role", "g", "spare"])

    return texts.select("text").mapInArrow(scan, "sig long, role byte, g long, spare int")


def _buckets(batches):
    """Rows in the order of sig, role, g: those of signatures with several sets, with the pivot of each (an indexed set)."""
    last_sig = last_g = pivot = None
    pivot_spare = 0
    alone = None  # the pivot's own row waits for company
    for batch in batches:
        sig, g, role = (batch.column(batch.schema.get_field_index(k)).to_numpy(zero_copy_only=False) for k in ("sig", "g", "role"))
        spare = batch.column(batch.schema.get_field_index("spare")).to_numpy(zero_copy_only=False)
        if not len(sig):
            continue
        new = np.r_[sig[0] != last_sig if last_sig is not None else True, sig[1:] != sig[:-1]]
        same = ~new & (g == np.r_[last_g if last_g is not None else g[0], g[:-1]])
        head = np.maximum.accumulate(np.where(new, np.arange(len(sig)), -1))
        pivots = np.where(head >= 0, g[head], pivot if pivot is not None else 0)
        indexed = np.where(head >= 0, role[head] == 0, pivot is not None)
        own = g == pivots
        member = indexed & ~own & ~same
        # a bucket's pivot is told once, before its first other member
        many = np.flatnonzero(member)
        bucket = head[many]
        firsts = many[np.r_[True, bucket[1:] != bucket[:-1]]] if len(many) else many
        told = firsts[(head[firsts] >= 0) | (alone is not None)] if len(firsts) else firsts
        yield pa.RecordBatch.from_arrays(
            [pa.array(np.r_[sig[told], sig[many]]), pa.array(np.r_[pivots[told], pivots[many]].astype(np.int64)), pa.array(np.r_[pivots[told], g[many]].astype(np.int64)), pa.array(np.r_[np.zeros(len(told), np.int8), role[many]], pa.int8()), pa.array(np.r_[np.where(head[told] >= 0, spare[head[told]], pivot_spare), spare[many]], pa.int32())],
            ["sig", "pivot", "g", "role", "spare"],
        )
        if head[-1] >= 0:
            pivot, pivot_spare = int(g[head[-1]]) if role[head[-1]] == 0 else None, int(spare[head[-1]])
            alone = True if pivot is not None and not (len(many) and bucket[-1] == head[-1]) else None
        elif len(many):
            alone = None
        last_sig, last_g = sig[-1], g[-1]


def _verified(batches):
    """Pairs whose sets reach the similarity, from the sorted hashes of both."""
    for batch in batches:
        da, db, sa, sb = columns(batch, "da", "db", "sa", "sb")
        keep = np.zeros(batch.num_rows, bool)
        for i, (x, y) in enumerate(zip(sa, sb, strict=True)):
            a, b = np.frombuffer(x.as_buffer(), U64), np.frombuffer(y.as_buffer(), U64)
            if len(a) > len(b):
                a, b = b, a
            at = np.minimum(np.searchsorted(b, a), len(b) - 1)
            common = int((b[at] == a).sum())
            keep[i] = 100 * common >= 80 * (len(a) + len(b) - common)
        at = pa.array(np.flatnonzero(keep))
        yield pa.RecordBatch.from_arrays([da.take(at), db.take(at)], ["da", "db"])


def linked(texts: DataFrame, size: int = WORDS, margin: float = MARGIN) -> tuple[DataFrame, DataFrame]:
    """Every document's set (doc, rid, n, g, g2), and the components of the documents that link (id, component)."""
    described_docs = shared.materialised(described(texts, size))
    classes = described_docs.where("n > 0").groupBy("g", "g2", "n").agg(F.min(F.struct("doc", "rid")).alias("least"), F.first("bits").alias("bits"))
    classes = shared.materialised(classes.select("g", "g2", "n", "least.doc", "least.rid", "bits"))
    rows = signed_sets(texts, common_shingles(texts, described_docs.count(), size), size, margin)
    rows = rows.repartition("sig").sortWithinPartitions("sig", "role", "g")
    buckets = shared.materialised(rows.mapInArrow(_tagged, "sig long, pivot long, g long, role byte, spare int"))
    uncovered = buckets.where("role = 2").select("g").distinct()
    # an indexed set may spare some segments: those with the fullest buckets.  It is active in the others,
    # and meets every member there; buckets that it has to itself count as met
    weighed = buckets.where("role < 2").join(buckets.where("role < 2").groupBy("sig").agg(F.count(F.lit(1)).alias("members")), "sig")
    fullest = F.row_number().over(Window.partitionBy("g", "role").orderBy(F.desc("members"), "sig"))
    weighed = shared.materialised(weighed.withColumn("active", fullest > F.col("spare")).drop("spare"))
    any_active = weighed.groupBy("sig").agg(F.max("active").alias("used")).where("used").select("sig")
    all_buckets, buckets = buckets, shared.materialised(weighed.join(any_active, "sig"))
    shared.dropped(weighed)
    rest = shared.materialised(_rest(texts, uncovered, size)) if uncovered.limit(1).count() else None

    def sets(batches):
        for batch in batches:
            g, n, doc, text = columns(batch, "g", "n", "doc", "text")
            data, offsets = tb.texts_of(text)
            for a, b in tb.slices(offsets):
                grams, owner = shingles(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], size)
                cuts = np.searchsorted(owner, np.arange(b - a + 1))
                out = [np.sort(grams[s:e]).tobytes() for s, e in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([g.slice(a, b - a), n.slice(a, b - a), doc.slice(a, b - a), pa.array(out, pa.binary())], ["g", "n", "doc", "hashes"])

    # the sets of all that share a bucket with another, once
    wanted = buckets.select("g")
    if rest is not None:
        wanted = wanted.union(rest.select("a")).union(rest.select("b"))
    chosen = classes.join(wanted.distinct(), "g").select("g", "n", "doc", "rid")
    arrays = texts.select("doc", "rid", "text").join(chosen, ["doc", "rid"]).select("g", "n", "doc", "text").mapInArrow(sets, "g long, n long, doc long, hashes binary")
    arrays = shared.materialised(arrays)
    shared.dropped(all_buckets)
    side = lambda x: arrays.select(F.col("g").alias(x), F.col("n").alias(f"n{x}"), F.col("doc").alias(f"d{x}"), F.col("hashes").alias(f"s{x}"))
    slim = lambda x: arrays.select(F.col("g").alias(x), F.col("n").alias(f"n{x}"))

    def compared(pairs: DataFrame) -> DataFrame:
        """The linked ones of pairs of set keys (a, b), as pairs of documents."""
        fit = pairs.join(slim("a"), "a").join(slim("b"), "b").where("5 * least(na, nb) >= 4 * greatest(na, nb)").select("a", "b").distinct()
        return shared.materialised(fit.join(side("a"), "a").join(side("b"), "b").select("da", "db", "sa", "sb").mapInArrow(_verified, "da long, db long"))

    by_set = classes.select("g", "doc", "n", "bits")

    def open_rows(rows: DataFrame, comps: DataFrame) -> DataFrame:
        """The rows of buckets that still hold several components."""
        place = by_set.join(comps, by_set["doc"] == comps["id"], "left").select("g", "n", "bits", "component")
        x = rows.select("sig", "g", "role", "active").join(place, "g").withColumn("component", F.coalesce(F.col("component").cast("string"), F.concat(F.lit("g"), F.col("g").cast("string"))))
        mixed = x.groupBy("sig").agg(F.min("component").alias("c0"), F.max("component").alias("c1")).where("c0 <> c1").select("sig")
        return shared.materialised(x.join(mixed, "sig").select("sig", "g", "role", "active", "component", "n", "bits"))

    def cross(x: DataFrame, other: DataFrame, tested: DataFrame) -> DataFrame:
        """Pairs of rows of a bucket in different components that haven't been compared."""
        other = other.select("sig", F.col("g").alias("h"), F.col("component").alias("d"), F.col("role").alias("r"), F.col("n").alias("m"), F.col("bits").alias("others"))
        apart = sum((F.bit_count(F.get("bits", i).bitwiseXOR(F.get("others", i))) for i in range(1, PARITY_WORDS)), F.bit_count(F.get("bits", 0).bitwiseXOR(F.get("others", 0))))
        p = x.where("active").join(other, "sig").where("component <> d AND role + r < 2 AND 5 * least(n, m) >= 4 * greatest(n, m)").where(9 * apart <= F.col("n") + F.col("m")).select(F.least("g", "h").alias("a"), F.greatest("g", "h").alias("b"))
        return shared.materialised(p.distinct().join(tested, ["a", "b"], "left_anti"))

    def drawn(x: DataFrame, number: int) -> DataFrame:
        """One indexed row of each bucket, another one in each bucket and round."""
        one = x.where("role = 0").groupBy("sig").agg(F.min(F.struct(F.xxhash64("g", "sig", F.lit(number)).alias("o"), "g", "component", "n", "bits")).alias("one"))
        return one.select("sig", "one.g", "one.component", "one.n", "one.bits", F.lit(0).cast("byte").alias("role"))

    voted = buckets.where("active AND g <> pivot").groupBy("g", "pivot").agg(F.count(F.lit(1)).alias("votes"))
    best = voted.groupBy("g").agg(F.max(F.struct("votes", "pivot")).alias("best")).select(F.least("g", "best.pivot").alias("a"), F.greatest("g", "best.pivot").alias("b")).distinct()
    tested = shared.materialised(best if rest is None else best.union(rest).distinct())
    links = compared(tested)
    comps = shared.components(links, "da", "db")
    x = open_rows(buckets, comps)
    # members meet a drawn one of their bucket, until few are left apart; those meet all of other components
    for number in range(ROUNDS + 1):
        more = cross(x, drawn(x, number) if number < ROUNDS else x, tested)
        if more.limit(1).count():
            links = links.union(compared(more))
            tested = tested.union(more)
            comps = shared.components(links, "da", "db")
        if number < ROUNDS:
            x = open_rows(x, comps)
    return described_docs, comps


def _tagged(batches):
    """Buckets, and beside them the sets that aren't covered (role 2 rows)."""

    def plain():
        for batch in batches:
            role = batch.column(batch.schema.get_field_index("role")).to_numpy(zero_copy_only=False)
            lost = np.flatnonzero(role == 2)
            if len(lost):
                g = batch.column(batch.schema.get_field_index("g")).take(pa.array(lost))
                found.append(pa.RecordBatch.from_arrays([g, g, g, pa.array(np.full(len(lost), 2, np.int8)), pa.array(np.zeros(len(lost), np.int32))], ["sig", "pivot", "g", "role", "spare"]))
                batch = batch.take(pa.array(np.flatnonzero(role != 2)))
            yield batch

    found: list[pa.RecordBatch] = []
    for out in _buckets(plain()):
        yield from found
        found.clear()
        yield out
    yield from found


def _rest(texts: DataFrame, uncovered: DataFrame, size: int) -> DataFrame:
    """Candidate pairs of the sets that aren't covered, through their single shingles."""

    def single(batches):
        for batch in batches:
            data, offsets = tb.texts_of(*columns(batch, "text"))
            for a, b in tb.slices(offsets):
                grams, owner = shingles(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], size)
                yield pa.RecordBatch.from_arrays([signed(set_key(grams, owner, b - a)[owner]), signed(grams)], ["g", "shingle"])

    every = texts.select("text").mapInArrow(single, "g long, shingle long").distinct()
    few = every.join(uncovered, "g", "left_semi").select(F.col("g").alias("h"), "shingle")
    return every.join(few, "shingle").where("g <> h").select(F.least("g", "h").alias("a"), F.greatest("g", "h").alias("b")).distinct()


def joined_documents(docs: DataFrame, size: int = WORDS, margin: float = MARGIN) -> DataFrame:
    """doc_id, n_shingles, component_id of every row."""
    texts = keyed(docs)
    sets, comps = linked(texts, size, margin)
    classes = shared.materialised(sets.where("n > 0").groupBy("g", "g2", "n").agg(F.count(F.lit(1)).alias("times"), F.min("doc").alias("least")))
    filled = shared.joined_by_count(sets.where("n > 0").drop("bits"), classes, ["g", "g2", "n"], "times")
    x = filled.unionByName(sets.where("n = 0").drop("bits").withColumn("least", F.lit(None).cast("long")))
    x = x.join(comps, x["least"] == comps["id"], "left")
    component = F.coalesce("component", "least", "doc")
    null_last = lambda c: F.when(c != LAST, c)
    return x.select(null_last(F.col("doc")).alias("doc_id"), F.col("n").alias("n_shingles"), null_last(component).alias("component_id"))


def first_of_each(docs: DataFrame) -> DataFrame:
    """``docs`` with one document of each component: the one with the smallest id."""
    found = joined_documents(docs.select("doc_id", "text"))
    later = found.where("component_id <> doc_id OR (doc_id IS NULL AND component_id IS NOT NULL)").select(F.col("doc_id").alias("_later")).distinct()
    return docs.join(later, docs["doc_id"].eqNullSafe(later["_later"]), "left_anti")


def op5_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_shingles, component_id of every document."""
    return joined_documents(shared.load(spark, sf_dir, "documents").select("doc_id", "text"))
