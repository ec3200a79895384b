"""Statistics of whole texts, vectorised over a slice of texts."""

from __future__ import annotations

import numpy as np

from wfpath.llm import textbytes as tb

#: The characters that count as symbols.
SYMBOLS = b"#*$%&|<>"
_IS_SYMBOL = np.isin(np.arange(256), list(SYMBOLS))
_UPPER = np.zeros(256, bool)
_UPPER[65:91] = True
_ALPHA = np.zeros(256, bool)
_ALPHA[65:91] = _ALPHA[97:123] = True
_DIGIT = np.zeros(256, bool)
_DIGIT[48:58] = True
_PUNCT = np.isin(np.arange(256), list(b".,;:!?\"'()[]{}-_/\\=+@~^`"))
BASE = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
MORE = ["n_bytes", "n_lines", "n_distinct_words", "n_upper", "n_alpha", "n_digits", "n_punct", "n_bang", "n_multibyte", "n_short_words", "n_end_words", "longest_word", "n_capital_words", "n_distinct_pairs", "n_bar"]


def _per_text(flags: np.ndarray, cuts: np.ndarray) -> np.ndarray:
    sums = np.zeros(len(flags) + 1, np.int64)
    np.cumsum(flags, out=sums[1:])
    return sums[cuts[1:]] - sums[cuts[:-1]]


def _distinct(hashes: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
    """How many different hashes each text has."""
    keys = tb.mix(hashes + owner.astype(tb.U64) * tb.U64(0x9E3779B97F4A7C15))
    _, at = np.unique(keys, return_index=True)
    return np.bincount(owner[at], minlength=n)


def statistics(data: np.ndarray, offsets: np.ndarray, more: bool = True) -> dict[str, np.ndarray]:
    """Counts for each text: those of ``BASE``, and those of ``MORE`` if asked for."""
    n = len(offsets) - 1
    starts, ends, first = tb.word_bounds(data, offsets)
    counts = np.diff(first)
    owner = np.repeat(np.arange(n), counts)
    hashes = tb.word_hashes(data, starts, ends)
    out = {"n_words": counts}
    space = tb._SPACE[data]
    out["word_chars"] = _per_text(~space & ((data & 0xC0) != 0x80), offsets)
    out["n_symbols"] = _per_text(_IS_SYMBOL[data], offsets)
    # lines: cut at every newline and at the ends of texts
    breaks = np.flatnonzero(data == 10)
    line_start = np.sort(np.concatenate([offsets[:-1], breaks + 1]))
    line_end = np.sort(np.concatenate([offsets[1:], breaks]))
    line_owner = np.searchsorted(breaks, offsets[:-1])  # newlines before each text
    per = np.searchsorted(breaks, offsets[1:]) - line_owner + 1
    line_owner = np.repeat(np.arange(n), per)
    words_before = np.zeros(len(data) + 1, np.int64)
    np.cumsum(~space, out=words_before[1:])
    has_word = words_before[line_end] > words_before[line_start]
    s, e, o = line_start[has_word], line_end[has_word], line_owner[has_word]
    lines = np.bincount(o, minlength=n)
    out["n_dup_lines"] = lines - _distinct(tb.word_hashes(data, s, e), o, n) if len(s) else np.zeros(n, np.int64)
    grams, at = tb.windows(hashes, first, 5)
    covered = np.zeros(len(hashes) + 1, np.int64)
    if len(at):
        keys = tb.mix(grams + owner[at].astype(tb.U64) * tb.U64(0xC2B2AE3D27D4EB4F))
        order = np.argsort(keys)
        k = keys[order]
        same = np.zeros(len(k), bool)
        same[1:] = k[1:] == k[:-1]
        same[:-1] |= same[1:]
        again = at[order[same]]
        np.add.at(covered, again, 1)
        np.subtract.at(covered, np.minimum(again + 5, len(hashes)), 1)
    out["n_repeat_words"] = np.bincount(owner[np.cumsum(covered[:-1]) > 0], minlength=n)
    if more:
        lengths = ends - starts
        out["n_bytes"], out["n_lines"] = np.diff(offsets), lines
        out["n_distinct_words"] = _distinct(hashes, owner, n)
        for name, table in (("n_upper", _UPPER), ("n_alpha", _ALPHA), ("n_digits", _DIGIT), ("n_punct", _PUNCT)):
            out[name] = _per_text(table[data], offsets)
        out["n_bang"], out["n_bar"] = _per_text(data == 33, offsets), _per_text(data == 124, offsets)
        out["n_multibyte"] = _per_text(data >= 0xC0, offsets)
        out["n_short_words"] = np.bincount(owner[lengths <= 3], minlength=n)
        last, head = data[ends - 1], data[starts]
        out["n_end_words"] = np.bincount(owner[np.isin(last, list(b".!?"))], minlength=n)
        out["n_capital_words"] = np.bincount(owner[_UPPER[head] | (head == 0xC3)], minlength=n)
        longest = np.zeros(n, np.int64)
        np.maximum.at(longest, owner, lengths)
        out["longest_word"] = longest
        pairs, at2 = tb.windows(hashes, first, 2)
        out["n_distinct_pairs"] = _distinct(pairs, owner[at2], n) if len(at2) else np.zeros(n, np.int64)
    return out


def by_batch(batches, keep: list[str], names: list[str], text: str = "text"):
    """Arrow batches with the columns ``keep`` and the statistics ``names`` of every text."""
    import pyarrow as pa

    more = any(x in MORE for x in names)
    for batch in batches:
        data, offsets = tb.texts_of(batch.column(batch.schema.get_field_index(text)))
        parts = []
        for a, b in tb.slices(offsets):
            piece = data[offsets[a] : offsets[b]]
            parts.append(statistics(piece, offsets[a : b + 1] - offsets[a], more))
        cols = [batch.column(batch.schema.get_field_index(k)) for k in keep]
        cols += [pa.array(np.concatenate([p[x] for p in parts]) if parts else np.zeros(0, np.int64), pa.int64()) for x in names]
        yield pa.RecordBatch.from_arrays(cols, [*keep, *names])
