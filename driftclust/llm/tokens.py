"""Byte-level BPE encoding of whole columns with the tokenizers library.

The library's merges never cross the pieces that its pre-tokenizer cuts, so a
text's ids are those of its pieces in order. Pieces are found for a block of
texts at once by character class, each distinct piece is encoded by the library
the first time a worker meets it, and all later places take the ids from a table
of bounded size. Texts with characters that Unicode versions class differently,
and those that contain a token added to the vocabulary, are handed to the library
whole.
"""

from __future__ import annotations

import os
import unicodedata
from functools import cache

import numpy as np

from . import kernels

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

_OTHER, _LETTER, _NUMBER, _SPACE, _UNSURE = range(5)
#: Distinct pieces that a worker remembers; beyond it starts anew.
MAX_PIECES = 2_000_000


def default_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


@cache
def char_classes() -> np.ndarray:
    """Class of each code point; unsure where an old Unicode version differs."""
    old = unicodedata.ucd_3_2_0
    out = np.zeros(0x110000, np.uint8)
    for cp in range(0x110000):
        c = chr(cp)
        kind = unicodedata.category(c)
        if kind != old.category(c) or kind in ("Cn", "Cs"):
            out[cp] = _UNSURE
        elif kind[0] == "L":
            out[cp] = _LETTER
        elif kind[0] == "N":
            out[cp] = _NUMBER
    for lo, hi in ((9, 13), (32, 32), (0xA0, 0xA0), (0x1680, 0x1680), (0x2000, 0x200A), (0x2028, 0x2029), (0x202F, 0x202F), (0x205F, 0x205F), (0x3000, 0x3000)):
        out[lo : hi + 1] = _SPACE
    for cp in (*range(0x1C, 0x20), 0x85, 0x180E, 0x200B):
        out[cp] = _UNSURE
    return out


def byte_names() -> dict[int, str]:
    """The character that stands for each byte in a byte-level vocabulary.

    Printable bytes stand for themselves, the others, in order, for the
    characters from 256 on.
    """
    shown = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = iter(range(256, 512))
    return {b: chr(b if b in shown else next(rest)) for b in range(256)}


def piece_starts(chars: np.ndarray, kind: np.ndarray, row_start: np.ndarray) -> np.ndarray:
    """Indices where pieces begin; chars are code points of concatenated rows."""
    n = len(chars)
    start = row_start.copy()
    start[1:] |= kind[1:] != kind[:-1]
    runs = np.flatnonzero(start)
    # White space before something else gives its last character away: a blank
    # joins what follows, another character stands alone.
    follows = np.zeros(n, bool)
    at = runs[1:]
    at = at[(kind[at - 1] == _SPACE) & ~row_start[at]]
    start[at - 1] = True
    joined = at[chars[at - 1] == 32]
    start[joined] = False
    follows[joined] = True
    # 's, 't, 'm, 'd, 're, 've, 'll where the apostrophe begins a piece.
    q = np.flatnonzero((chars == 39) & start & ~follows)
    q = q[q + 1 < n]
    q = q[~row_start[q + 1]]
    one, two = chars[q + 1], np.where(q + 2 < n, chars[np.minimum(q + 2, n - 1)], 0)
    two[(q + 2 < n) & row_start[np.minimum(q + 2, n - 1)]] = 0
    single = np.isin(one, [ord(c) for c in "stmd"])
    double = ((one == ord("r")) & (two == ord("e"))) | ((one == ord("v")) & (two == ord("e"))) | ((one == ord("l")) & (two == ord("l")))
    for picked, width in ((q[single], 2), (q[double], 3)):
        start[picked + 1] = False
        end = picked + width
        end = end[end < n]
        start[end[(kind[end] == _LETTER) & ~row_start[end]]] = True
    return np.flatnonzero(start)


class _Table:
    """Ids of known pieces: sorted hashes beside places in one flat array."""

    def __init__(self, hashes, first, count, flat):
        order = np.argsort(hashes)
        self.hashes, self.first, self.count, self.flat = hashes[order], first[order], count[order], flat

    def find(self, u):
        if not len(self.hashes):
            return np.zeros(len(u), np.int64), np.zeros(len(u), bool)
        at = np.minimum(np.searchsorted(self.hashes, u), len(self.hashes) - 1)
        return at, self.hashes[at] == u


class Encoder:
    """Encodes text columns; one for each worker and vocabulary file."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.added = [t.content.encode() for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.names = byte_names()
        self.forget()

    def forget(self) -> None:
        empty = np.zeros(0, np.int64)
        self.table = _Table(np.zeros(0, np.uint64), empty, empty, np.zeros(0, np.int32))
        self.recent = self.table

    def _learn(self, hashes: np.ndarray, pieces: list[bytes]) -> None:
        merge, names = self.tokenizer.model.tokenize, self.names
        ids = [[t.id for t in merge(p.decode("latin-1").translate(names))] for p in pieces]
        count = np.array([len(i) for i in ids], np.int64)
        flat = np.array([x for i in ids for x in i], np.int32)
        if len(self.table.hashes) + len(self.recent.hashes) + len(hashes) > MAX_PIECES:
            self.forget()
        self.recent = self._joined(self.recent, _Table(hashes, np.cumsum(count) - count, count, flat))
        if len(self.recent.hashes) > 100_000 + len(self.table.hashes) // 4:
            self.table = self._joined(self.table, self.recent)
            self.recent = _Table(np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int32))

    @staticmethod
    def _joined(a: _Table, b: _Table) -> _Table:
        return _Table(np.concatenate([a.hashes, b.hashes]), np.concatenate([a.first, b.first + len(a.flat)]), np.concatenate([a.count, b.count]), np.concatenate([a.flat, b.flat]))

    def _pieces(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids of all pieces, and how many each has."""
        h = kernels.span_hashes(data, starts, ends, fold=False)
        u, index, inverse = np.unique(h, return_index=True, return_inverse=True)
        known = self.table.find(u)[1] | self.recent.find(u)[1]
        if not known.all():
            new = np.flatnonzero(~known)
            raw = data.tobytes()
            if len(self.table.hashes) + len(self.recent.hashes) + len(new) > MAX_PIECES:
                self.forget()
                new = np.arange(len(u))
            self._learn(u[new], [raw[starts[i] : ends[i]] for i in index[new].tolist()])
        (a, in_a), (b, in_b) = self.table.find(u), self.recent.find(u)
        shift = len(self.table.flat)
        first, count = np.zeros(len(u), np.int64), np.zeros(len(u), np.int64)
        first[in_a], count[in_a] = self.table.first[a[in_a]], self.table.count[a[in_a]]
        first[in_b], count[in_b] = self.recent.first[b[in_b]] + shift, self.recent.count[b[in_b]]
        flat = np.concatenate([self.table.flat, self.recent.flat]) if len(self.recent.flat) else self.table.flat
        n = count[inverse]
        return flat[kernels.segments(first[inverse], n)], n

    def _block(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids of the rows, and how many each row has."""
        if not len(data):
            return np.zeros(0, np.int32), np.zeros(len(offsets) - 1, np.int64)
        raw = data.tobytes()
        chars = np.frombuffer(raw.decode().encode("utf-32-le"), np.uint32)
        at = np.flatnonzero((data & 0xC0) != 0x80)
        rows = np.searchsorted(at, offsets)
        kind = char_classes()[chars]
        row_start = np.zeros(len(chars), bool)
        row_start[rows[:-1][rows[:-1] < len(chars)]] = True
        odd = np.flatnonzero(kind == _UNSURE)
        starts = at[piece_starts(chars, kind, row_start)]
        ids, n = self._pieces(data, starts, np.append(starts[1:], len(data)))
        total = np.concatenate([[0], np.cumsum(n)])
        edge = total[np.searchsorted(starts, offsets)]
        special = rows_with(raw, offsets, self.added)
        if not len(odd) and not len(special):
            return ids, np.diff(edge)
        whole = set((np.searchsorted(rows, odd, side="right") - 1).tolist()) | set(special.tolist())
        parts = [np.array(self.tokenizer.encode(raw[offsets[r] : offsets[r + 1]].decode(), add_special_tokens=False).ids, np.int32) if r in whole else ids[edge[r] : edge[r + 1]] for r in range(len(offsets) - 1)]
        return np.concatenate(parts), np.array([len(p) for p in parts])

    def encode(self, column) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids of a text column, and row offsets into them; null is empty."""
        data, offsets = kernels.utf8(column)
        cut, owner = safe_cuts(data, offsets, added=self.added)
        flat, count = [np.zeros(0, np.int32)], np.zeros(len(offsets) - 1, np.int64)
        for lo, hi in kernels.blocks(cut, kernels.BLOCK // 2):
            ids, n = self._block(data[cut[lo] : cut[hi]], cut[lo : hi + 1] - cut[lo])
            flat.append(ids)
            np.add.at(count, owner[lo:hi], n)
        return np.concatenate(flat), np.concatenate([[0], np.cumsum(count)])


def rows_with(raw: bytes, offsets: np.ndarray, words: list[bytes]) -> np.ndarray:
    """Rows that contain one of the words."""
    hit = set()
    for w in words:
        at = raw.find(w)
        while at >= 0:
            r = int(np.searchsorted(offsets, at, side="right")) - 1
            if at + len(w) <= offsets[r + 1]:
                hit.add(r)
                at = raw.find(w, int(offsets[r + 1]))
            else:
                at = raw.find(w, at + 1)
    return np.array(sorted(hit), np.int64)


def safe_cuts(data: np.ndarray, offsets: np.ndarray, limit: int = 8 * kernels.BLOCK, added: list[bytes] | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Row offsets with long rows split, and the row of each part.

    A split is put before a blank that follows an ASCII letter: a piece always
    begins there, whatever stands on either side. Rows with unsure characters
    or an added token stay whole.
    """
    sizes = np.diff(offsets)
    if not len(sizes) or sizes.max() <= limit:
        return offsets, np.arange(len(sizes))
    cut, owner = [0], []
    for r in range(len(sizes)):
        lo, hi = int(offsets[r]), int(offsets[r + 1])
        if hi - lo > limit:
            part = data[lo:hi]
            sure = not (char_classes()[np.frombuffer(part.tobytes().decode().encode("utf-32-le"), np.uint32)] == _UNSURE).any() and not any(w in part.tobytes() for w in added or ())
            letter = ((part[:-1] | 32) >= 97) & ((part[:-1] | 32) <= 122)
            places = np.flatnonzero(letter & (part[1:] == 32)) + 1 + lo if sure else np.zeros(0, np.int64)
            while hi - cut[-1] > limit and len(places):
                k = int(np.searchsorted(places, cut[-1] + limit)) - 1
                if k < 0 or places[k] <= cut[-1]:
                    break
                cut.append(int(places[k]))
                owner.append(r)
        cut.append(hi)
        owner.append(r)
    return np.array(cut, np.int64), np.array(owner, np.int64)


@cache
def encoder(path: str) -> Encoder:
    """The worker's encoder; its table is kept between tasks."""
    return Encoder(path)


def with_end(ids: np.ndarray, offsets: np.ndarray, end_id: int) -> tuple[np.ndarray, np.ndarray]:
    """The same with one more id at the end of each row."""
    n = len(offsets) - 1
    out = np.full(len(ids) + n, end_id, np.int64)
    row = np.repeat(np.arange(n), np.diff(offsets))
    out[np.arange(len(ids)) + row] = ids
    return out, offsets + np.arange(n + 1)
