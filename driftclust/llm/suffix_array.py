"""Suffix arrays by two-stage sorting, in NumPy.

Stage one sorts only the suffixes that are smaller than their successors,
directly. Stage two scans the buckets of first bytes upwards: where a sorted
suffix is preceded by a larger byte, the suffix that begins there is larger than
its successor, so its place in its own bucket follows. Sorting looks at
``depth`` bytes only: suffixes that agree so far stay side by side in any order.
"""

from __future__ import annotations

import numpy as np

from . import kernels


def _words(text: np.ndarray) -> np.ndarray:
    """The 8 bytes from each place on, as a number that sorts like them."""
    n = len(text)
    padded = np.concatenate([text, np.zeros(8, np.uint8)])
    word = np.zeros(n, np.uint64)
    for k in range(8):
        word <<= np.uint64(8)
        word |= padded[k : n + k]
    return word


def window_hashes(text: np.ndarray, depth: int, ends: np.ndarray | None = None) -> np.ndarray:
    """Hash of the next ``depth`` bytes at each place, fewer at the end, or at
    the end of the place's part of the text where ``ends`` gives it: what stands
    behind that decides nothing.

    A polynomial hash modulo 2^64 with random byte values: unlike windows of
    under 1,024 bytes agree by chance alone, once in 2^64.
    """
    at = np.arange(len(text))
    return kernels.span_hashes(text, at, np.minimum(at + depth, len(text) if ends is None else ends), fold=False)


def _direct(text: np.ndarray, which: np.ndarray, depth: int, hashes: np.ndarray) -> np.ndarray:
    """``which`` sorted by the ``depth`` bytes that begin there, 8 at a time.

    Of suffixes whose next ``depth`` bytes are alike one is sorted; each round
    looks only at those still tied with a neighbour.
    """
    if not len(which):
        return which
    by_hash = np.argsort(hashes[which])
    alike = which[by_hash]
    h = hashes[alike]
    new = np.ones(len(alike), bool)
    new[1:] = h[1:] != h[:-1]
    lead = np.flatnonzero(new)
    size = np.diff(np.append(lead, len(alike)))
    one = alike[lead]
    n, word = len(text), _words(text)
    order = np.argsort(word[one])
    key = word[one[order]]
    group = np.zeros(len(order), np.int64)
    group[1:] = np.cumsum(key[1:] != key[:-1])
    slot = np.arange(len(order))
    done = 8
    while done < depth:
        same = np.zeros(len(slot) + 1, bool)
        same[1:-1] = group[1:] == group[:-1]
        tied = same[1:] | same[:-1]
        if not tied.any():
            break
        slot, group = slot[tied], group[tied]
        at = one[order[slot]] + done
        key = np.where(at < n, word[np.minimum(at, n - 1)], np.uint64(0))
        by_key = np.argsort(key)
        by_both = by_key[np.argsort(group[by_key], kind="stable")]
        order[slot] = order[slot[by_both]]
        key, group = key[by_both], group[by_both]
        new = np.ones(len(group), bool)
        new[1:] = (key[1:] != key[:-1]) | (group[1:] != group[:-1])
        group = np.cumsum(new)
        done += 8
    return alike[kernels.segments(lead[order], size[order])]


def suffix_array(text: np.ndarray, depth: int, hashes: np.ndarray | None = None, wanted: np.ndarray | None = None) -> np.ndarray:
    """Starts of all suffixes in order of their first ``depth`` bytes or more.

    With ``wanted``, only of these and of those that placing them takes: a
    larger suffix is placed by its successor, so a run of wanted places is
    followed up to the next suffix that is sorted directly.

    The text should end in a byte that is smaller than all before it.
    """
    n = len(text)
    if not n:
        return np.zeros(0, np.int64)
    # Smaller than its successor: a smaller byte, or an equal one before such.
    nxt = np.append(text[1:].astype(np.int16), -1)
    rise = np.where(text < nxt, 1, np.where(text > nxt, 0, 2)).astype(np.int8)
    last = np.where(rise != 2, np.arange(n), n)
    last = np.minimum.accumulate(last[::-1])[::-1]
    small = rise[last] == 1
    used = np.ones(n, bool)
    if wanted is not None:
        used = wanted.copy()
        stop = np.minimum.accumulate(np.where(small, np.arange(n), n - 1)[::-1])[::-1]
        runs = np.flatnonzero(wanted[:-1] & ~wanted[1:]) + 1
        used[kernels.segments(runs, stop[runs] - runs + 1)] = True
        used[n - 1] = True
    direct = _direct(text, np.flatnonzero(small & used), depth, window_hashes(text, depth) if hashes is None else hashes)
    first = text[direct]
    edge = np.searchsorted(first, np.arange(257))
    induced: list[list[np.ndarray]] = [[] for _ in range(256)]
    # The last suffix has no successor; it is larger than the empty one.
    induced[text[n - 1]].append(np.array([n - 1]))
    out: list[np.ndarray] = []

    def hand_down(found: np.ndarray, byte: int) -> np.ndarray:
        """Give the larger predecessors to their buckets; those in this one."""
        before = found[found > 0] - 1
        before = before[~small[before] & used[before]]
        c = text[before]
        here = before[c == byte]
        up = c > byte
        c, before = c[up], before[up]
        if len(c):
            by = np.argsort(c, kind="stable")
            c, before = c[by], before[by]
            cut = np.flatnonzero(np.concatenate([[True], c[1:] != c[:-1]]))
            for lo, hi in zip(cut.tolist(), [*cut[1:].tolist(), len(c)], strict=True):
                induced[c[lo]].append(before[lo:hi])
        return here

    for byte in range(256):
        level = np.concatenate(induced[byte]) if induced[byte] else np.zeros(0, np.int64)
        induced[byte] = []
        while len(level):
            out.append(level)
            level = hand_down(level, byte)
        rest = direct[edge[byte] : edge[byte + 1]]
        if len(rest):
            out.append(rest)
            hand_down(rest, byte)
    return np.concatenate(out)


def reaches(text: np.ndarray, sa: np.ndarray, depth: int, hashes: np.ndarray) -> np.ndarray:
    """Whether each suffix shares ``depth`` bytes or more with the one before it.

    The common prefix of neighbours is measured against depth by window hash,
    and by the bytes at both ends.
    """
    ok = np.zeros(len(sa), bool)
    live = np.arange(1, len(sa))
    a, b = sa[1:], sa[:-1]
    live = live[(hashes[a] == hashes[b]) & (np.maximum(a, b) + depth <= len(text))]
    a, b = sa[live], sa[live - 1]
    ok[live[(text[a] == text[b]) & (text[a + depth - 1] == text[b + depth - 1])]] = True
    return ok
