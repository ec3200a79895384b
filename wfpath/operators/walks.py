"""Walks of some whole runs over product graphs, and ways of a relation without branches on one side, in numpy within a task."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Pairs in a batch that leaves a task.
OUT = 50_000


def walked(rows: pa.Table, states: int, finals: list[int], every: bool, places: int) -> Iterator[pa.RecordBatch]:
    """Pairs (run_id, src, dst) of whole runs.

    ``rows`` (run_id, kind, at, q, dst, q2) are edges (kind 0), starts (1) and goals (2, unless ``every`` node is one).
    A start has a place for each node and state of its run, and starts are taken while they have at most ``places`` together.
    """
    runs = rows["run_id"].combine_chunks().dictionary_encode()
    run, kind = runs.indices.to_numpy(), rows["kind"].to_numpy()
    is_edge = kind == 0
    edges = rows.filter(pa.array(is_edge))
    names = pa.concat_arrays([*rows["at"].chunks, *edges["dst"].chunks]).dictionary_encode()
    width = max(1, len(names.dictionary))
    # nodes are numbered run by run, so that those of a run are neighbours
    key, number = np.unique(np.concatenate([run, run[is_edge]]).astype(np.int64) * width + names.indices.to_numpy(), return_inverse=True)
    at, dst, n = number[: len(run)], number[len(run) :], len(key)
    base = np.searchsorted(key, np.arange(len(runs.dictionary) + 1, dtype=np.int64) * width)
    u, v = at[is_edge] * states + edges["q"].to_numpy(), dst * states + edges["q2"].to_numpy()
    v = v[np.argsort(u, kind="stable")]
    first = np.concatenate([[0], np.cumsum(np.bincount(u, minlength=n * states))])
    goal = np.full(n, every)
    goal[at[kind == 2]] = True
    final = np.zeros(states, bool)
    final[finals] = True
    starts = np.unique(at[kind == 1])
    of = key[starts] // width
    size = np.cumsum((base[of + 1] - base[of]) * states)
    done = 0
    while done < len(starts):
        upto = max(done + 1, int(np.searchsorted(size, (size[done - 1] if done else 0) + places, "right")))
        some, own = starts[done:upto], of[done:upto]
        ends = size[done:upto] - (size[done - 1] if done else 0)
        # a start's place of a node and state is that node and state's number and this
        shift = np.concatenate([[0], ends[:-1]]) - base[own] * states
        seen = np.zeros(ends[-1], bool)
        who, p = np.arange(len(some)), some * states
        seen[shift[who] + p] = True
        while len(p):
            degree = first[p + 1] - first[p]
            who = np.repeat(who, degree)
            p = v[np.repeat(first[p] - np.cumsum(degree) + degree, degree) + np.arange(len(who))]
            place = shift[who] + p
            new = np.flatnonzero(~seen[place])
            place, once = np.unique(place[new], return_index=True)
            seen[place] = True
            who, p = who[new[once]], p[new[once]]
        place = np.flatnonzero(seen)
        who = np.searchsorted(ends, place, "right")
        p = place - shift[who]
        keep = final[p % states] & goal[p // states]
        who, node = who[keep], p[keep] // states
        # a node's final states stand together
        once = np.flatnonzero((np.diff(who, prepend=-1) != 0) | (np.diff(node, prepend=-1) != 0))
        who, node = who[once], node[once]
        for i in range(0, len(who), OUT):
            w, x = who[i : i + OUT], node[i : i + OUT]
            yield pa.RecordBatch.from_arrays([runs.dictionary.take(pa.array(own[w])), names.dictionary.take(pa.array(key[some[w]] % width)), names.dictionary.take(pa.array(key[x] % width))], names=["run_id", "src", "dst"])
        done = upto


def _steps(rows: pa.Table):
    """The pairs (run_id, src, dst) of whole runs as one step of their nodes: to the one before, or else to the one behind; no node stands for none.

    Gives the step, whether it leads back, the hops of 1, 2, 4, ... steps, which nodes are sources, and the nodes' runs and names; None
    if a node has two neighbours on both sides, or a path has no end.
    """
    runs = rows["run_id"].combine_chunks().dictionary_encode()
    names = pa.concat_arrays([*rows["src"].chunks, *rows["dst"].chunks]).dictionary_encode()
    run, width = runs.indices.to_numpy(), max(1, len(names.dictionary))
    key, number = np.unique(np.concatenate([run, run]).astype(np.int64) * width + names.indices.to_numpy(), return_inverse=True)
    u, v, n = number[: len(run)], number[len(run) :], len(key)
    back = int(np.bincount(v).max()) == 1
    if not back and int(np.bincount(u).max()) > 1:
        return None
    step = np.full(n + 1, n, np.int32)
    step[v if back else u] = u if back else v
    hops = [step]
    while (longer := hops[-1][hops[-1]]).min() < n:
        if 2 ** len(hops) >= n:
            return None
        hops.append(longer)
    source = np.zeros(n + 1, bool)
    source[u] = True
    return back, hops, source, runs.dictionary.take(pa.array(key // width)), names.dictionary.take(pa.array(key % width))


def longest(rows: pa.Table) -> Iterator[pa.RecordBatch]:
    """The largest power of two of steps that a path of these runs has; 0 if a pair may have two paths or a path no end."""
    found = _steps(rows)
    yield pa.RecordBatch.from_arrays([pa.array([0 if found is None else 1 << (len(found[1]) - 1)], pa.int64())], names=["longest"])


#: Steps of a block as a power of two, ends of a tile's ways, and nodes that are taken at once, for blocks and for tiles.
BLOCK, ENDS, AT, TILES = 9, 2048, 1 << 15, 1 << 12


def _grown(hops: list[np.ndarray], at: np.ndarray, mode: str, none: int) -> Iterator[tuple[int, np.ndarray]]:
    """Where 1 .. 2^k steps from some nodes lead, k being the number of hops.

    A round doubles the steps: ``linear`` joins all found so far with the longest hop, ``semi`` what the last round found with the two
    longest, and ``double`` what was found with the longest of itself.
    """
    if not hops or not len(at):
        return
    found = front = [(1, hops[0][at])]
    longest = hops[0]
    yield from found
    for i, hop in enumerate(hops):
        by = {"linear": [(2**i, hop)], "semi": [(2 ** (i - 1), hops[i - 1]), (2**i, hop)] if i else [(1, hop)], "double": [(2**i, longest)]}[mode]
        front = [(m + more, h[x]) for more, h in by for m, x in (front if mode == "semi" else found)]
        front = [(m, x) for m, x in front if x.min() < none]
        yield from front
        if not front:
            return
        found = [*found, *front] if mode != "semi" else front
        if mode == "double":
            longest = longest[longest]


def _blocked(rows: pa.Table):
    """What ``_steps`` gives, the steps of a block as a power of two, and how many steps each node is from its path's end and from the block's."""
    back, hops, _, run, name = _steps(rows)
    n, k = len(run), min(BLOCK, max(1, len(hops) // 2))
    at, depth = np.arange(n), np.zeros(n, np.int64)
    for i, hop in reversed([*enumerate(hops)]):
        to = hop[at]
        depth += np.where(to < n, 1 << i, 0)
        at = np.where(to < n, to, at)
    return back, hops, run, name, n, k, depth, np.where(depth > 0, (depth - 1) % (1 << k) + 1, 0)


def near(rows: pa.Table, mode: str) -> Iterator[pa.RecordBatch]:
    """The ways (run_id, src, dst) of whole runs within a block: paths are cut into blocks of m steps, m being near the root of the longest."""
    back, hops, run, name, n, k, _, left = _blocked(rows)
    for i in range(0, n, AT):
        at = np.arange(i, min(i + AT, n))
        for m, to in _grown(hops[:k], at, mode, n):
            y = np.flatnonzero(m < left[at])
            src, dst = (to[y], at[y]) if back else (at[y], to[y])
            for j in range(0, len(src), OUT):
                u, v = pa.array(src[j : j + OUT]), pa.array(dst[j : j + OUT])
                yield pa.RecordBatch.from_arrays([run.take(u), name.take(u), name.take(v)], names=["run_id", "src", "dst"])


def far(rows: pa.Table, mode: str) -> Iterator[pa.RecordBatch]:
    """Tiles (run_id, srcs, dsts, tile) of whole runs: each source has a way to each target, by the ends of one or more blocks.

    From a block's end all blocks on are found by hops of whole blocks.  The nodes of one of these are a tile's one side, and the nodes
    whose block has that end are its other, so that a tile of some thousand nodes holds up to a million pairs.
    """
    back, hops, run, name, n, k, depth, left = _blocked(rows)
    end = np.full(n, n)
    for i in range(0, n, AT):
        at = np.arange(i, min(i + AT, n))
        for m, to in _grown(hops[:k], at, mode, n):
            y = np.flatnonzero(m == left[at])
            end[at[y]] = to[y]
    of = np.argsort(end, kind="stable")
    ends, first, size = np.unique(end[of], return_index=True, return_counts=True)
    ends, first, size = (x[ends < n] for x in (ends, first, size))
    for i in range(0, len(ends), TILES):
        at = ends[i : i + TILES]
        pairs = [(at, np.arange(len(at)))]
        for _, to in _grown(hops[k:], at, mode, n):
            some = np.flatnonzero(to < n)
            pairs.append((to[some], some))
        begin, which = (np.concatenate(x) for x in zip(*pairs, strict=True))
        blocks, number = np.unique(begin, return_inverse=True)
        # a block's nodes: its end and what follows up to the next
        long = np.minimum(depth[blocks] + 1, 1 << k)
        start = np.cumsum(long) - long
        nodes = np.zeros(int(long.sum()), np.int64)
        nodes[start] = blocks
        for m, to in _grown(hops[:k], blocks, mode, n):
            some = np.flatnonzero(m < long)
            nodes[start[some] + m] = to[some]
        parts = -(-size[i + which] // ENDS)
        tile = np.repeat(np.arange(len(which)), parts)
        part = np.arange(len(tile)) - np.repeat(np.cumsum(parts) - parts, parts)
        a0, a_size = start[number[tile]], long[number[tile]]
        b0, b_size = first[i + which[tile]] + part * ENDS, np.minimum(ENDS, size[i + which[tile]] - part * ENDS)
        group = np.cumsum(a_size + b_size) // (4 * OUT)
        for some in np.split(np.arange(len(tile)), np.flatnonzero(np.diff(group)) + 1):
            lists = [_lists(name, x, begin[some], length[some]) for x, begin, length in ((nodes, a0, a_size), (of, b0, b_size))]
            srcs, dsts = lists if back else lists[::-1]
            yield pa.RecordBatch.from_arrays([run.take(pa.array(at[which[tile[some]]])), srcs, dsts, pa.array(some + i)], names=["run_id", "srcs", "dsts", "tile"])


def _lists(name: pa.Array, x: np.ndarray, begin: np.ndarray, size: np.ndarray) -> pa.ListArray:
    """A list of names for each stretch of nodes."""
    bounds = np.concatenate([[0], np.cumsum(size)])
    flat = x[np.repeat(begin - bounds[:-1], size) + np.arange(bounds[-1])]
    return pa.ListArray.from_arrays(pa.array(bounds, pa.int32()), name.take(pa.array(flat)))
