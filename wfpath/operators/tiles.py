"""Pairs of two lists of labelled nodes, decided one by one in numpy within a task."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

from wfpath.functions.labels import WIDTH, Decoder

#: Pairs in a batch that leaves a task, pairs tested at once, pairs from which a block is tested by itself, and cells of a table.
OUT, ONCE, LARGE, CELLS = 50_000, 1 << 16, 1 << 14, 1 << 26


@dataclass(frozen=True)
class Tables:
    """A decoder's relations as arrays: a row of masks for each relation."""

    states: int
    empty: bool
    enter: np.ndarray
    leave: np.ndarray
    between: np.ndarray
    width: np.ndarray
    pair_first: np.ndarray
    lengths: np.ndarray
    slots: np.ndarray
    longest: int
    #: way -> base, before and period of each cycle and phase
    power: dict[str, np.ndarray]

    @staticmethod
    def of(d: Decoder) -> Tables:
        rows = lambda x: np.array([*x.flat, *[0] * d.plan.dfa.n], np.int64).reshape(-1, d.plan.dfa.n)
        lengths, slots = (np.array(x, np.int64) for x in d.cycles)
        return Tables(d.plan.dfa.n, d.accepts_empty, *map(rows, (d.enter, d.leave, d.between)), np.array(d.width), np.array(d.pair_first), lengths, slots, d.longest, {way: np.array(x, np.int64) for way, x in d.cells.items()})

    def forward(self, rows: np.ndarray, mask: np.ndarray, number: np.ndarray) -> np.ndarray:
        out = np.zeros(np.broadcast_shapes(mask.shape, number.shape), np.int64)
        for q in range(self.states):
            out |= np.where(mask >> q & 1 == 1, rows[number, q], 0)
        return out

    def backward(self, rows: np.ndarray, mask: np.ndarray, number: np.ndarray) -> np.ndarray:
        out = np.zeros(len(mask), np.int64)
        for q in range(self.states):
            out |= np.where(rows[number, q] & mask != 0, 1 << q, 0)
        return out

    def pair(self, k: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Number of the relation between two positions of a body; the last, which is empty, for places that aren't in it."""
        w = self.width[k]
        return np.where((i > 0) & (j > 0) & (i <= w) & (j <= w), self.pair_first[k] + (i - 1) * w + j - 1, len(self.between) - 1)

    def powers(self, way: str, cycle: np.ndarray, phase: np.ndarray, mask: np.ndarray, most: int) -> np.ndarray:
        """Masks after 0 .. most slots of a cycle: a row for each of these, ``most`` + 1 columns."""
        base, before, period = self.power[way][cycle * self.longest + phase].T
        rounds = int((before + period).max(initial=1))
        value = self.forward(getattr(self, way), mask[:, None], np.minimum(base[:, None] + np.arange(rounds), len(getattr(self, way)) - 1))
        count = np.arange(most + 1)
        return np.stack([value[i, np.where(count < b + p, count, b + (count - b) % p)] for i, (b, p) in enumerate(zip(before, period, strict=True))]) if len(mask) else np.zeros((0, most + 1), np.int64)


@dataclass(frozen=True)
class Level:
    """The entries of all rows at a depth; kind is -1 where a label has none."""

    kind: np.ndarray
    a: np.ndarray
    b: np.ndarray
    idx: np.ndarray
    mask: np.ndarray


def _levels(rows: pa.Table) -> list[Level]:
    """The entries and masks of packed labels by depth, and one depth more that has none."""
    label = pa.concat_arrays([x.cast(pa.large_binary()) for x in rows["label"].chunks])
    bounds = np.frombuffer(label.buffers()[1], np.int64)[label.offset : label.offset + len(label) + 1]
    e = np.frombuffer(label.buffers()[2] or b"", np.uint8)[bounds[0] : bounds[-1]].reshape(-1, WIDTH).astype(np.int64)
    number = lambda i, j: sum(e[:, k] << 8 * (j - 1 - k) for k in range(i, j))
    entries = [number(0, 1), number(1, 3), number(3, 5), number(5, 10)]
    first, size = (bounds[:-1] - bounds[0]) // WIDTH, np.diff(bounds) // WIDTH
    lists = pa.concat_arrays([x.cast(pa.large_list(pa.int64())) for x in rows["masks"].chunks])
    values, at = lists.values.to_numpy(zero_copy_only=False), np.frombuffer(lists.buffers()[1], np.int64)[lists.offset : lists.offset + len(lists)]
    out = []
    for d in range(int(size.max(initial=0)) + 1):
        has = np.flatnonzero(size > d)
        column = lambda source, begin, none: _filled(len(size), none, has, source[begin[has] + d])  # noqa: B023, E731
        out.append(Level(*[column(x, first, -1 if k == 0 else 0) for k, x in enumerate(entries)], column(values, at, 0)))
    return out


def _filled(n: int, none: int, at: np.ndarray, values: np.ndarray) -> np.ndarray:
    out = np.full(n, none, np.int64)
    out[at] = values
    return out


def _classes(*columns: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The first row of each kind of row, and each row's kind."""
    code = np.zeros(len(columns[0]), np.int64)
    for c in columns:
        code = np.unique(code * (int(c.max(initial=0)) + 1) + c if 0 <= int(c.min(initial=0)) and int(c.max(initial=0)) < 1 << 31 else code * len(c) + np.unique(c, return_inverse=True)[1], return_inverse=True)[1]
    _, first, kind = np.unique(code, return_index=True, return_inverse=True)
    return first, kind


def _blocks(u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Rows (from, to, from, to) of the numbers that two sorted lists both have."""
    both = np.intersect1d(u, v)
    return np.stack([np.searchsorted(x, both, side) for x in (u, v) for side in ("left", "right")], 1).reshape(-1, 4)


def _pieces(blocks: np.ndarray, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Large blocks cut where ``u`` and where ``v`` change, without the pieces where these are equal."""
    out = []
    for a0, a1, b0, b1 in blocks:
        cuts = [[int(i), *(np.flatnonzero(np.diff(x[i:j])) + i + 1).tolist(), int(j)] for x, i, j in ((u, a0, a1), (v, b0, b1))]
        out += [(i, j, k, m) for i, j in zip(cuts[0], cuts[0][1:], strict=False) for k, m in zip(cuts[1], cuts[1][1:], strict=False) if u[i] != v[k]]
    return np.array(out, np.int64).reshape(-1, 4)


def _pairs(blocks: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All pairs of many small blocks."""
    sizes = (blocks[:, 1] - blocks[:, 0]) * (blocks[:, 3] - blocks[:, 2])
    group = (np.cumsum(sizes) - sizes) // ONCE
    for some in np.split(np.arange(len(blocks)), np.flatnonzero(np.diff(group)) + 1):
        size = sizes[some]
        k = np.repeat(some, size)
        p = np.arange(len(k)) - np.repeat(np.cumsum(size) - size, size)
        wide = (blocks[:, 3] - blocks[:, 2])[k]
        yield blocks[k, 0] + p // wide, blocks[k, 2] + p % wide


def _hits(blocks: np.ndarray, off: np.ndarray, place: np.ndarray, halves: list[tuple[np.ndarray, np.ndarray]]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """The pairs of the blocks for which a table's mask at ``off`` + ``place`` meets the goal's: each pair is looked up."""
    sizes = (blocks[:, 1] - blocks[:, 0]) * (blocks[:, 3] - blocks[:, 2])
    for a0, a1, b0, b1 in blocks[sizes >= LARGE]:
        step = max(1, ONCE // (b1 - b0))
        for i in range(a0, a1, step):
            at = off[i : min(i + step, a1), None] + place[None, b0:b1]
            found = np.flatnonzero(_met(at, b0, b1, halves))
            if len(found):
                yield i + found // (b1 - b0), b0 + found % (b1 - b0)
    if len(small := blocks[(sizes < LARGE) & (sizes > 0)]):
        for i, j in _pairs(small):
            at = off[i] + place[j]
            met = np.zeros(len(i), bool)
            for table, goal in halves:
                met |= table.take(at, mode="clip") & goal[j] != 0
            yield i[met], j[met]


def _met(at: np.ndarray, b0: int, b1: int, halves: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    met = None
    for table, goal in halves:
        own = (table.take(at, mode="clip") & goal[b0:b1]) != 0
        met = own if met is None else met | own
    return met


def matched(rows: pa.Table, t: Tables) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs (row of side 0, row of side 1) of a tile that match.

    ``rows`` (tile, side, label, masks), sorted by tile and packed label, are whole tiles.  Two labels part at the first depth
    where their entries differ.  Rows that agree up to there, and then stand in the same body or chain, are a block, so each pair is
    tested at one depth only (and is none if it is in no block).  A test takes the mask that the first node has on its way to the
    second's place, from a table by kind of first node and place or distance, and meets it with the second's mask.
    """
    levels, n = _levels(rows), t.states
    tile = pa.concat_arrays(rows["tile"].chunks).dictionary_encode().indices.to_numpy()
    side = rows["side"].to_numpy()
    differs = lambda *columns: np.concatenate([[True], np.any([c[1:] != c[:-1] for c in columns], axis=0)]) if len(tile) else np.zeros(0, bool)
    apart = differs(tile)
    for d, (here, after) in enumerate(zip(levels, levels[1:], strict=False)):
        group = np.cumsum(apart | differs(here.kind, here.a, np.where(here.kind == 1, here.b, 0)))
        u, v = (np.flatnonzero((side == k) & (here.kind >= 0)) for k in (0, 1))
        apart = apart | differs(here.kind, here.a, here.b, here.idx)
        blocks = _blocks(group[u], group[v])
        if not len(blocks):
            continue
        chain_u, chain_v = here.kind[u] == 1, here.kind[v] == 1
        # v: its place, and the masks that meet it from its own body or an earlier member, and from a later member
        na, nb = after.a[v], after.b[v]
        slot = np.where(after.kind[v] == 0, t.slots[np.where(after.kind[v] == 0, na, 0)], 0)
        goal = here.mask[v]
        back = np.where(chain_v, t.backward(t.between, after.mask[v], t.pair(np.where(after.kind[v] == 0, na, 0), slot, nb)), 0)
        place = np.where(chain_v, here.idx[v], here.b[v])
        # u: its kind, with a table row of masks for each
        cycle = np.where(chain_u, here.a[u], 0)
        phase = np.where(chain_u, (here.b[u] - 1 + here.idx[u]) % t.lengths[cycle], 0)
        next_ = [np.where(chain_u & (after.kind[u] == 0), x[u], 0) for x in (after.a, after.b, after.mask)]
        first, kind = _classes(chain_u.astype(np.int64), here.a[u], here.b[u], here.mask[u], phase, *next_)
        in_chain = blocks[chain_u[blocks[:, 0]]]
        i, j = here.idx[u], here.idx[v]
        most = int(max(0, *[(j[in_chain[:, 3] - 1] - i[in_chain[:, 0]]).max(initial=0), (i[in_chain[:, 1] - 1] - j[in_chain[:, 2]]).max(initial=0)]))
        body_width, chain_width = int(t.width.max()) + 1, 2 * most + 1
        chains = np.flatnonzero(chain_u[first])
        parts = max(1, -(-len(chains) * chain_width // CELLS))
        for k in range(parts):
            some = chains[k::parts]
            number = _filled(len(first), -1, some, np.arange(len(some)))
            bodies = np.flatnonzero(~chain_u[first]) if k == 0 else np.zeros(0, np.int64)
            number[bodies] = np.arange(len(bodies))
            mine = number[kind] >= 0
            x = first[bodies]
            columns = np.arange(body_width)[None, :]
            at = t.pair(here.a[u[x]][:, None], here.b[u[x]][:, None], columns)
            onward = [np.where(columns == here.b[u[x]][:, None], 0, t.forward(t.between, here.mask[u[x]][:, None], at)).ravel()]
            later = [np.zeros_like(onward[0])]
            if len(some):
                x = first[some]
                mask = t.forward(t.between, next_[2][x], t.pair(next_[0][x], next_[1][x], t.slots[next_[0][x]]))
                ahead, behind = np.zeros((len(x), chain_width), np.int64), np.zeros((len(x), chain_width), np.int64)
                if most:
                    ahead[:, most + 1 :] = t.powers("enter", cycle[x], phase[x], mask, most - 1)
                    behind[:, :most] = t.powers("leave", cycle[x], (phase[x] - 2) % t.lengths[cycle[x]], here.mask[u[x]], most - 1)[:, ::-1]
                onward.append(ahead.ravel())
                later.append(behind.ravel())
            off = np.where(chain_u, len(onward[0]) + number[kind] * chain_width + most - here.idx[u], number[kind] * body_width)
            onward, later = np.concatenate(onward), np.concatenate(later)
            kinds = [c for c, bits in ((np.uint8, 8), (np.uint16, 16), (np.uint32, 32), (np.int64, 63)) if 2 * n <= bits]
            halves = [((onward | later << n).astype(kinds[0]), (goal | back << n).astype(kinds[0]))] if kinds else [(onward, goal), (later, back)]
            own = np.flatnonzero(mine)
            cut = blocks if len(own) == len(u) else _blocks(group[u[own]], group[v])
            cut = cut[(cut[:, 1] - cut[:, 0]) * (cut[:, 3] - cut[:, 2]) > 0]
            large = (~chain_u[own[cut[:, 0]]]) & ((cut[:, 1] - cut[:, 0]) * (cut[:, 3] - cut[:, 2]) >= LARGE)
            cut = np.concatenate([cut[~large], _pieces(cut[large], here.b[u[own]], here.b[v])])
            for a, b in _hits(cut, off[own], place, halves):
                yield u[own[a]], v[b]
    if t.empty:
        group = np.cumsum(apart)
        u, v = (np.flatnonzero(side == k) for k in (0, 1))
        if len(same := _blocks(group[u], group[v])):
            for a, b in _pairs(same):
                yield u[a], v[b]


def pairs_of(rows: pa.Table, t: Tables) -> Iterator[pa.RecordBatch]:
    """run_id, src, dst of the pairs that match."""
    run, name = (pa.concat_arrays(rows[c].chunks) for c in ("run_id", "node_id"))

    def batch(us: list[np.ndarray], vs: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        u, v = np.concatenate(us), np.concatenate(vs)
        for i in range(0, len(u), OUT):
            a, b = pa.array(u[i : i + OUT]), pa.array(v[i : i + OUT])
            yield pa.RecordBatch.from_arrays([run.take(a), name.take(a), name.take(b)], names=["run_id", "src", "dst"])

    us, vs, held = [], [], 0
    for u, v in matched(rows, t):
        us.append(u)
        vs.append(v)
        held += len(u)
        if held >= OUT:
            yield from batch(us, vs)
            us, vs, held = [], [], 0
    if held:
        yield from batch(us, vs)
