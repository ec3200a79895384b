"""An adaptive context-mixing range coder for token ids.

The ids are cut into blocks; each block starts from an empty model, so it can be decoded alone,
and carries its length and the CRC-32 of its ids.  All blocks of a call are coded in lockstep,
one id of each at a time, with vectors over blocks in place of loops over ids.

For each id the model makes three predictions: the id that last followed the two ids before it
(order 2), the one that last followed the id before it (order 1), and the recent ids by slot
(order 0).  What is coded first is which of them is right (or none).  The probability of that
event is a mix of three adaptive estimates, in the contexts of the order-2 prediction's standing,
of the order-1 prediction's, and of none; the mix's weights follow how well each estimate has
done.  Then comes the slot of a recent id, or a new id itself.  Only elementwise IEEE additions,
products and quotients enter, so every machine decodes alike.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np

U64, U32 = np.uint64, np.uint32
BLOCK = 1024
MAGIC = b"CM2\0"
TOTAL = 1 << 16
FIRST_BITS, SECOND_BITS, SLOT_BITS = 9, 10, 9
NONE = 0xFFFFFFFF
LOW_MASK, RENEW = U64((1 << 48) - 1), U64(1 << 32)


class Model:
    """Predictions and event estimates of n blocks, side by side in flat tables; four bytes a cell unless ids are ``wide``."""

    def __init__(self, n: int, wide: bool) -> None:
        self.n, self.kind = n, np.int64 if wide else np.int32
        none = NONE << 2 if wide else TOTAL << 2
        # a predicted id and, in the low two bits, how well it has done
        self.first, self.second = np.full(n << FIRST_BITS, none, self.kind), np.full(n << SECOND_BITS, none, self.kind)
        self.recent = np.full(n << SLOT_BITS, none >> 2, self.kind)
        lanes = np.arange(n, dtype=np.int64)
        self.base1, self.base2, self.base0, self.lanes = lanes << FIRST_BITS, lanes << SECOND_BITS, lanes << SLOT_BITS, lanes
        # how often each event was seen, by context: a row of four for every context and block
        self.counts = [np.full((c * n, 4), 0.5, np.float32) for c in (1, 4, 4)]
        self.sums = [np.full(c * n, 2.0, np.float32) for c in (1, 4, 4)]
        self.weights = [np.full(n, 1.0 / 3, np.float32) for _ in range(3)]
        self.edges = np.zeros((5, n), np.int64)
        self.edges[4] = TOTAL
        self.cells = lanes * 4
        self.a = self.b = np.zeros(n, U32)

    def slots(self, ids: np.ndarray) -> np.ndarray:
        return ((ids * 40503) >> 3) & ((1 << SLOT_BITS) - 1)

    def predict(self) -> np.ndarray:
        """Cumulative frequencies of the four events, of TOTAL; also finds the predictions."""
        n, fetch = self.n, {"mode": "clip"}  # places are in range: clipping saves the check
        spread = self.b * U32(2654435761)
        self.at1 = self.base1 + (spread >> U32(32 - FIRST_BITS))
        self.at2 = self.base2 + ((self.a * U32(2246822519) + (spread ^ (spread >> U32(15)))) * U32(3266489917) >> U32(32 - SECOND_BITS))
        self.held1, self.held2 = self.first.take(self.at1, **fetch), self.second.take(self.at2, **fetch)
        self.p1, self.p2 = self.held1 >> 2, self.held2 >> 2
        self.trust1, self.trust2 = self.held1 & 3, self.held2 & 3
        self.rows = [self.lanes, self.trust1 * np.int64(n) + self.lanes, self.trust2 * np.int64(n) + self.lanes]
        self.seen = [self.counts[0], *(c.take(r, 0, **fetch) for c, r in zip(self.counts[1:], self.rows[1:], strict=True))]
        self.total = [self.sums[0], *(s.take(r, **fetch) for s, r in zip(self.sums[1:], self.rows[1:], strict=True))]
        scale = np.float32(TOTAL - 8) / (self.weights[0] + self.weights[1] + self.weights[2])
        mixed = (self.weights[0] * scale / self.total[0])[:, None] * self.seen[0]
        for k in (1, 2):
            mixed += (self.weights[k] * scale / self.total[k])[:, None] * self.seen[k]
        mixed = mixed.astype(np.int32)
        edges = self.edges
        np.add(mixed[:, 0], 1, out=edges[1])
        np.add(edges[1] + 1, mixed[:, 1], out=edges[2])
        np.add(edges[2] + 1, mixed[:, 2], out=edges[3])
        return edges

    def event(self, ids: np.ndarray, slots: np.ndarray) -> np.ndarray:
        """0: order 2 is right, 1: order 1, 2: the id is recent, 3: none of them."""
        known = self.recent.take(self.base0 + slots, mode="clip") == ids
        return np.where(self.p2 == ids, 0, np.where(self.p1 == ids, 1, 3 - known))

    def learn(self, event: np.ndarray, ids: np.ndarray, slots: np.ndarray) -> None:
        w, shares, one = self.weights, [], np.float32(1)
        cell = self.cells + event
        for k in range(3):
            row, total = self.rows[k], self.total[k]
            count = self.seen[k].ravel().take(cell, mode="clip")
            shares.append(w[k] * (count / total))
            self.counts[k].ravel()[row * 4 + event] = count + one
            if k:
                self.sums[k][row] = total + one
            else:
                self.sums[0] = total + one
        scale = np.float32(0.94) / (shares[0] + shares[1] + shares[2])
        self.weights = [np.float32(0.02) + x * scale for x in shares]
        fresh = (ids << 2) | 1
        for table, at, held, predicted, trust in ((self.first, self.at1, self.held1, self.p1, self.trust1), (self.second, self.at2, self.held2, self.p2, self.trust2)):
            # right: trusted more; wrong: trusted less, and replaced once it isn't trusted
            table[at] = np.where(predicted == ids, held + (trust < 3), np.where(trust > 1, held - 1, fresh))
        self.recent[self.base0 + slots] = ids
        self.a, self.b = self.b, ids.astype(U32)


class Writer:
    """A range coder for each block: 48-bit low end, 16-bit digits, carries settled at the end."""

    def __init__(self, n: int, steps: int) -> None:
        self.low, self.range, self.lanes = np.zeros(n, U64), np.full(n, LOW_MASK), np.arange(n)
        self.digits = np.zeros((n, 3 * steps + 4), U32)
        self.used = np.zeros(n, np.int64)

    def put(self, start: np.ndarray, size: np.ndarray, rows: np.ndarray | slice) -> None:
        low, span = self.low[rows], self.range[rows]
        unit = span >> U64(16)
        low = low + unit * start.view(U64)
        span = unit * size.view(U64)
        lanes = self.lanes[rows]
        over = np.flatnonzero(low > LOW_MASK)
        if len(over):
            self.digits[lanes[over], self.used[lanes[over]] - 1] += U32(1)
            low &= LOW_MASK
        small = np.flatnonzero(span < RENEW)
        if len(small):
            at = lanes[small]
            x = low[small]
            self.digits[at, self.used[at]] = (x >> U64(32)).astype(U32)
            self.used[at] += 1
            low[small] = (x & U64(0xFFFFFFFF)) << U64(16)
            span[small] <<= U64(16)
        self.low[rows], self.range[rows] = low, span

    def end(self) -> tuple[np.ndarray, np.ndarray]:
        lanes = np.arange(len(self.low))
        for shift in (32, 16, 0):
            self.digits[lanes, self.used] = ((self.low >> U64(shift)) & U64(0xFFFF)).astype(U32)
            self.used += 1
        for j in range(self.digits.shape[1] - 1, 0, -1):
            carry = self.digits[:, j] >> U32(16)
            if carry.any():
                self.digits[:, j] &= U32(0xFFFF)
                self.digits[:, j - 1] += carry
        return self.digits.astype("<u2"), self.used


class Reader:
    def __init__(self, digits: np.ndarray) -> None:
        n = len(digits)
        self.digits, self.at, self.lanes = digits, np.full(n, 3, np.int64), np.arange(n)
        d = digits[:, :3].astype(U64)
        self.value, self.range = (d[:, 0] << U64(32)) | (d[:, 1] << U64(16)) | d[:, 2], np.full(n, LOW_MASK)

    def peek(self, rows) -> np.ndarray:
        return np.minimum(self.value[rows] // (self.range[rows] >> U64(16)), U64(TOTAL - 1)).astype(np.int64)

    def take(self, start: np.ndarray, size: np.ndarray, rows) -> None:
        value, span = self.value[rows], self.range[rows]
        unit = span >> U64(16)
        value = value - unit * start.view(U64)
        span = unit * size.view(U64)
        small = np.flatnonzero(span < RENEW)
        if len(small):
            lanes = self.lanes[rows][small]
            value[small] = (value[small] << U64(16)) | self.digits[lanes, self.at[lanes]].astype(U64)
            self.at[lanes] += 1
            span[small] <<= U64(16)
        self.value[rows], self.range[rows] = value, span


def encode(ids: np.ndarray, block: int = BLOCK) -> list[bytes]:
    """The blocks of a sequence of ids (unsigned, under 2**32 - 1)."""
    ids = np.asarray(ids, np.int64)
    if len(ids) == 0:
        return []
    block = min(block, len(ids))
    n = -(-len(ids) // block)
    padded = np.zeros(n * block, np.int64)
    padded[: len(ids)] = ids
    wide = bool(ids.max() >= TOTAL)
    columns = np.ascontiguousarray(padded.reshape(n, block).T.astype(np.int64 if wide else np.int32))
    model, out, whole, lanes = Model(n, wide), Writer(n, block * (2 if wide else 1)), slice(None), np.arange(n)
    for x in columns:
        edge = model.predict()
        slots = model.slots(x)
        e = model.event(x, slots)
        at = e * n + lanes
        start = edge.ravel().take(at, mode="clip")
        out.put(start, edge.ravel().take(at + n, mode="clip") - start, whole)
        more = np.flatnonzero(e >= 2)
        if len(more):
            y, known = x[more], e[more] == 2
            if wide:
                fresh = more[~known]
                out.put(x[fresh] >> 16, np.ones(len(fresh), np.int64), fresh)
            shift = 16 - SLOT_BITS
            out.put(np.where(known, slots[more] << shift, y & 0xFFFF).astype(np.int64), np.where(known, 1 << shift, 1), more)
        model.learn(e, x, slots)
    digits, used = out.end()
    found = []
    for i in range(n):
        own = padded[i * block : min(len(ids), (i + 1) * block)].astype("<u4")
        head = MAGIC + struct.pack("<IIII", len(own), int(wide), int(used[i]), zlib.crc32(own.tobytes()))
        found.append(head + digits[i, : used[i]].tobytes())
    return found


def decode(blocks: list[bytes]) -> np.ndarray:
    """The ids of these blocks, one block after another; a block that fails its checksum raises."""
    if not blocks:
        return np.zeros(0, U32)
    heads = []
    for b in blocks:
        if b[:4] != MAGIC:
            raise ValueError("not a block of token ids")
        heads.append(struct.unpack_from("<IIII", b, 4))
    counts = np.array([h[0] for h in heads])
    wides = {h[1] for h in heads}
    if len(wides) > 1:
        return np.concatenate([decode([b]) for b in blocks])
    wide, n, steps = bool(wides.pop()), len(blocks), int(counts.max())
    digits = np.zeros((n, max(h[2] for h in heads) + 4 + (2 + wide) * 2), np.uint16)
    for i, (b, h) in enumerate(zip(blocks, heads, strict=True)):
        digits[i, : h[2]] = np.frombuffer(b, "<u2", h[2], 20)
    # blocks shorter than the longest were padded by the encoder or run on zeros here; what they yield then is dropped
    digits = np.pad(digits, ((0, 0), (0, (3 * steps if counts.min() < steps else 0))))
    out = np.zeros((steps, n), U32)
    model, source, whole, lanes = Model(n, wide), Reader(digits), slice(None), np.arange(n)
    for step in range(steps):
        edge = model.predict()
        f = source.peek(whole)
        e = (f >= edge[1]).astype(np.int64) + (f >= edge[2]) + (f >= edge[3])
        at = e * n + lanes
        start = edge.ravel().take(at, mode="clip")
        source.take(start, edge.ravel().take(at + n, mode="clip") - start, whole)
        x = np.where(e == 0, model.p2, model.p1)
        more = np.flatnonzero(e >= 2)
        if len(more):
            known = e[more] == 2
            high = np.zeros(len(more), np.int64)
            if wide:
                fresh = more[~known]
                high[~known] = source.peek(fresh)
                source.take(high[~known], np.ones(len(fresh), np.int64), fresh)
            shift = 16 - SLOT_BITS
            f2 = source.peek(more)
            slot = f2 >> shift
            source.take(np.where(known, slot << shift, f2), np.where(known, 1 << shift, 1), more)
            x[more] = np.where(known, model.recent[model.base0[more] + slot], (high << 16) | f2)
        out[step] = x
        model.learn(e, x, model.slots(x))
    parts = []
    for i, (count, head) in enumerate(zip(counts, heads, strict=True)):
        own = out[:count, i].astype("<u4")
        if zlib.crc32(own.tobytes()) != head[3]:
            raise ValueError(f"block {i} fails its checksum")
        parts.append(own)
    return np.concatenate(parts)
