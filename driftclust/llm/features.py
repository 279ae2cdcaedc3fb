"""Hashed word features of whole texts, for the two linear text models."""

from __future__ import annotations

import string

import numpy as np

from . import kernels

#: Words end at white space and at ASCII punctuation.
WORD_BREAKS = kernels.separators(string.punctuation.encode())


def ngram_hashes(data: np.ndarray, offsets: np.ndarray, skips: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """(hash, row): words, word pairs and, with skips, pairs with one word between."""
    starts, ends = kernels.words(data, offsets, WORD_BREAKS)
    h = kernels.span_hashes(data, starts, ends)
    row = np.searchsorted(offsets, starts, side="right") - 1
    parts, rows = [h], [row]
    for gap, salt in ((1, 0xC2B2AE3D27D4EB4F), (2, 0x165667B19E3779F9))[: 2 if skips else 1]:
        if len(h) > gap:
            same = row[gap:] == row[:-gap]
            parts.append(kernels.mix(h[:-gap] * np.uint64(salt) + h[gap:])[same])
            rows.append(row[gap:][same])
    return np.concatenate(parts), np.concatenate(rows)


def slots(hashes: np.ndarray, bits: int) -> np.ndarray:
    return (hashes >> np.uint64(64 - bits)).astype(np.int64)


def presence(column, bits: int, skips: bool = True):
    """(row, sorted distinct slots) of each row of a text column."""
    data, offsets = kernels.utf8(column)
    for lo, hi in kernels.blocks(offsets):
        part, off = data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]
        h, row = ngram_hashes(part, off, skips)
        pairs = np.unique((row.astype(np.int64) << bits) | slots(h, bits))
        cut = np.searchsorted(pairs, np.arange(hi - lo + 1, dtype=np.int64) << bits)
        for r in range(hi - lo):
            yield lo + r, pairs[cut[r] : cut[r + 1]] & ((1 << bits) - 1)


def linear_scores(column, weights: np.ndarray, bits: int, skips: bool = True) -> np.ndarray:
    """Sum of the weights of each row's distinct slots; most weights are 0."""
    data, offsets = kernels.utf8(column)
    out = np.zeros(len(offsets) - 1)
    for lo, hi in kernels.blocks(offsets):
        part, off = data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]
        h, row = ngram_hashes(part, off, skips)
        at = slots(h, bits)
        used = np.flatnonzero(weights[at])
        pairs = np.unique((row[used].astype(np.int64) << bits) | at[used])
        out[lo:hi] = np.bincount(pairs >> bits, weights=weights[pairs & ((1 << bits) - 1)], minlength=hi - lo)
    return out


STYLE = (
    "bias", "log_bytes", "log_words", "word_len", "upper", "digit", "bang", "mark", "pipe", "comma_stop", "other_punct", "non_ascii", "space",
    "newline", "distinct_words", "repeat_next", "distinct_pairs", "long_words", "no_lower_words", "odd_end_words", "distinct_lines",
)


def style(column) -> np.ndarray:
    """(rows, len(STYLE)) shares and logs that describe how a text is written."""
    data, offsets = kernels.utf8(column)
    out = np.zeros((len(offsets) - 1, len(STYLE)))
    kind = np.zeros(256, np.int64)
    for code, chars in enumerate((string.ascii_uppercase, string.digits, "!", "*#$%&@^~<>=+_\\{}[]", "|", ",.;:'\"-?()", "/`"), 1):
        kind[list(chars.encode())] = code
    kind[128:] = 8
    kind[[32, 9]] = 9
    kind[10] = 10
    for lo, hi in kernels.blocks(offsets):
        part, off = data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]
        n, size = hi - lo, np.diff(off).astype(float)
        row_of_byte = np.repeat(np.arange(n), np.diff(off))
        shares = np.bincount(row_of_byte * 11 + kind[part], minlength=n * 11).reshape(n, 11) / np.maximum(size, 1)[:, None]
        starts, ends = kernels.words(part, off)
        row = np.searchsorted(off, starts, side="right") - 1
        count = np.bincount(row, minlength=n).astype(float)
        some = np.maximum(count, 1)
        h = kernels.span_hashes(part, starts, ends)

        def per_row(mask, row=row, n=n, some=some):
            return np.bincount(row[: len(mask)][mask], minlength=n) / some

        def distinct(values, rows, n=n):
            order = np.lexsort((values, rows))
            v, r = values[order], rows[order]
            new = np.ones(len(v), bool)
            new[1:] = (v[1:] != v[:-1]) | (r[1:] != r[:-1])
            return np.bincount(r[new], minlength=n) / np.maximum(np.bincount(r, minlength=n), 1)

        same = np.zeros(len(h), bool)
        pair = np.zeros(0, np.uint64)
        pair_row = np.zeros(0, np.int64)
        if len(h) > 1:
            joined = row[1:] == row[:-1]
            same[:-1] = joined & (h[1:] == h[:-1])
            pair, pair_row = kernels.mix(h[:-1] * np.uint64(3) + h[1:])[joined], row[1:][joined]
        lower = np.concatenate([[0], np.cumsum((part >= 97) & (part <= 122))])
        last = part[ends - 1] if len(ends) else np.zeros(0, np.uint8)
        newline = np.ones(256, bool)
        newline[:] = False
        newline[10] = True
        ls, le = kernels.words(part, off, newline)
        lh, lrow = kernels.span_hashes(part, ls, le), np.searchsorted(off, ls, side="right") - 1
        k = kind[last] if len(last) else np.zeros(0, np.int64)
        out[lo:hi] = np.stack(
            [
                np.ones(n), np.log1p(size) / 10, np.log1p(count) / 10, np.bincount(row, weights=ends - starts, minlength=n) / some / 10,
                shares[:, 1], shares[:, 2], shares[:, 3], shares[:, 4], shares[:, 5], shares[:, 6], shares[:, 7], shares[:, 8], shares[:, 9], shares[:, 10],
                distinct(h, row), per_row(same), distinct(pair, pair_row), per_row(ends - starts > 20), per_row(lower[ends] == lower[starts]),
                per_row((k >= 3) & (k <= 5)), distinct(lh, lrow),
            ],
            axis=1,
        )
    return out
