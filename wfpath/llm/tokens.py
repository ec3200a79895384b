"""Token ids of whole texts by a public tokenizer, as arrays over a slice of texts.

The tokenizer lower-cases, drops white space, cuts texts into runs of letters, single digits and
runs of other characters, and codes each such piece by itself.  So a text's ids are those of its
pieces in order, and each different piece needs to be coded once: a process keeps the ids of
pieces that it has coded, KEPT at most.  Pieces are found here in ASCII and the Latin-1 letters; a
word with any other byte, with an apostrophe (which may begin a piece of its own) or with the start
of a special token goes to the tokenizer as a whole.
"""

from __future__ import annotations

import os

import numpy as np
import pyarrow as pa

from wfpath.llm import textbytes as tb

VOCABULARY = "word_bpe_49k.json"
SLICE, GROUP = 6 << 20, 2000
KEPT = 400_000
_LETTER, _DIGIT, _OTHER, _GAP = 0, 1, 2, 3
_KIND = np.full(256, _OTHER, np.uint8)
_KIND[65:91] = _KIND[97:123] = _LETTER
_KIND[0xC3] = _LETTER
_KIND[0x80:0xC0] = _LETTER  # the second byte of a two-byte letter; others are told apart below
_KIND[48:58] = _DIGIT
_KIND[tb._SPACE] = _GAP
_EASY = np.zeros(256, bool)
_EASY[0x21:0x7F] = _EASY[0x80:0xC0] = _EASY[0xC3] = True
_EASY[ord("'")] = False
_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[65:91] += 32


def spread(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Indices of the ranges [start, start + size), one after another."""
    ends = np.cumsum(sizes)
    total = int(ends[-1]) if len(ends) else 0
    return np.arange(total) + np.repeat(starts - (ends - sizes), sizes)


class Encoder:
    """A tokenizer, and which of its ids end a piece."""

    def __init__(self, name: str) -> None:
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        import public_tokenizers
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(public_tokenizers.path(name) if "/" not in name else name)
        vocabulary = self.tokenizer.get_vocab(with_added_tokens=False)
        self.ends = np.zeros(max(vocabulary.values()) + 1, bool)
        self.ends[[i for w, i in vocabulary.items() if w.endswith("</w>")]] = True
        self.special = [t.content.encode() for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.forget()

    def forget(self) -> None:
        # the pieces coded so far by number; the ids of all, one after another, and where each piece's begin
        self.known: dict[str, int] = {}
        self.flat, self.bounds = np.zeros(0, np.int64), np.zeros(1, np.int64)

    def whole(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of words that may hold several pieces, and the number of ids of each."""
        lists = [e.ids for e in self.tokenizer.encode_batch_fast(words, add_special_tokens=False)]
        sizes = np.fromiter(map(len, lists), np.int64, len(lists))
        return np.fromiter((x for ids in lists for x in ids), np.int64, int(sizes.sum())), sizes

    def pieces(self, pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of different single pieces; those that were coded before are looked up."""
        fresh = [p for p in pieces if p not in self.known]
        if len(self.known) + len(fresh) > KEPT:
            self.forget()
            if len(pieces) > KEPT:
                return self.coded(pieces)
            fresh = pieces
        if fresh:
            flat, sizes = self.coded(fresh)
            self.known.update(zip(fresh, range(len(self.known), len(self.known) + len(fresh)), strict=True))
            self.flat, self.bounds = np.concatenate([self.flat, flat]), np.concatenate([self.bounds, self.bounds[-1] + np.cumsum(sizes)])
        at = np.fromiter(map(self.known.__getitem__, pieces), np.int64, len(pieces))
        sizes = np.diff(self.bounds)[at]
        return self.flat[spread(self.bounds[at], sizes)], sizes

    def coded(self, pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of single pieces: coded many at once, and told apart by the ids that end a piece."""
        texts = [" ".join(pieces[i : i + GROUP]) for i in range(0, len(pieces), GROUP)]
        flat = np.concatenate([np.zeros(0, np.int64), *[np.array(e.ids, np.int64) for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]])
        stops = np.flatnonzero(self.ends[flat])
        if len(stops) != len(pieces):
            return self.whole(pieces)
        return flat, np.diff(np.r_[-1, stops])


_encoders: dict[str, Encoder] = {}


def _strings(data: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> pa.Array:
    offsets = np.zeros(len(starts) + 1, np.int64)
    np.cumsum(sizes, out=offsets[1:])
    return pa.LargeStringArray.from_buffers(len(starts), pa.py_buffer(offsets), pa.py_buffer(np.ascontiguousarray(data[spread(starts, sizes)])))


def encode(texts: pa.Array, end_id: int, name: str = VOCABULARY) -> tuple[np.ndarray, np.ndarray]:
    """Ids of all texts with ``end_id`` after each (null: empty), and the offsets of the texts."""
    coder = _encoders.get(name) or _encoders.setdefault(name, Encoder(name))
    data, offsets = tb.texts_of(texts)
    starts, ends, first = tb.word_bounds(data, offsets)
    # bytes that this module can't place; 0xC3 stands for itself only before 0x80-0xBF but the signs at 0x97 and 0xB7
    odd = ~_EASY[data]
    odd[tb._SPACE[data]] = False
    tail = (data >= 0x80) & (data < 0xC0)
    before = np.r_[np.uint8(0), data[:-1]] if len(data) else data
    odd |= tail & ((before != 0xC3) | (data == 0x97) | (data == 0xB7))
    for mark in coder.special:
        head = np.flatnonzero(data == mark[0])
        if len(mark) > 1:
            head = head[head + 1 < len(data)]
            head = head[data[head + 1] == mark[1]]
        odd[head] = True
    sums = np.zeros(len(data) + 1, np.int32)
    np.cumsum(odd, out=sums[1:])
    hard = sums[ends] > sums[starts]
    # pieces of the easy words: cut where the kind changes, at digits and at words' ends
    kind = _KIND[data]
    cut = np.zeros(len(data) + 1, bool)
    cut[1:-1] = (kind[1:] != kind[:-1]) | (kind[1:] == _DIGIT)
    cut[starts] = True
    cut[ends] = True
    inside = np.zeros(len(data) + 1, np.int8)
    inside[starts[~hard]] += 1
    inside[ends[~hard]] -= 1  # words end in different places
    at = np.flatnonzero(cut)
    easy = np.cumsum(inside)[at[:-1]] > 0 if len(at) else np.zeros(0, bool)
    piece_start, piece_size = at[:-1][easy], np.diff(at)[easy]
    folded = _FOLD[data]
    upper = tail & (before == 0xC3) & (data < 0x9F)
    folded[upper] += 0x20
    # all units in text order: pieces and hard words
    unit_start = np.concatenate([piece_start, starts[hard]])
    order = np.argsort(unit_start, kind="stable")
    soft = _strings(folded, piece_start, piece_size).dictionary_encode()
    whole = _strings(data, starts[hard], ends[hard] - starts[hard]).dictionary_encode()
    flat1, sizes1 = coder.pieces(soft.dictionary.to_pylist())
    flat2, sizes2 = coder.whole(whole.dictionary.to_pylist())
    code = np.concatenate([soft.indices.to_numpy(zero_copy_only=False), whole.indices.to_numpy(zero_copy_only=False).astype(np.int64) + len(sizes1)])[order].astype(np.int64)
    sizes, flat = np.concatenate([sizes1, sizes2]), np.concatenate([flat1, flat2])
    each = sizes[code]
    totals = np.zeros(len(code) + 1, np.int64)
    np.cumsum(each, out=totals[1:])
    bounds = np.searchsorted(unit_start[order], offsets)
    out_at = totals[bounds] + np.arange(len(offsets))
    ids = np.empty(int(totals[-1]) + len(texts), np.uint32)
    plain = np.ones(len(ids), bool)
    plain[out_at[1:] - 1] = False
    begin = np.cumsum(sizes) - sizes
    ids[plain] = flat[spread(begin[code], each)]
    ids[out_at[1:] - 1] = end_id
    return ids, out_at
