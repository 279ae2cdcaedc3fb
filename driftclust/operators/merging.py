"""Hierarchical merging of cells by density gaps along the map's edges."""

from __future__ import annotations

import heapq
import itertools
import math
from dataclasses import dataclass

import numpy as np

from ..params import Params

#: The places at which the mixture is looked at: -0.5 to 0.5 by 0.01.
GRID = np.arange(-50, 51) / 100.0


@dataclass
class Cells:
    """Counts, sums and sums of outer products: they add up under merging."""

    n: np.ndarray
    s1: np.ndarray
    s2: np.ndarray

    def mean(self, i) -> np.ndarray:
        return self.s1[i] / self.n[i]

    def copy(self) -> Cells:
        return Cells(self.n.copy(), self.s1.copy(), self.s2.copy())

    def add(self, i: int, j: int) -> None:
        self.n[i] += self.n[j]
        self.s1[i] += self.s1[j]
        self.s2[i] += self.s2[j]


def cell_stats(x: np.ndarray, cell: np.ndarray, q: int) -> Cells:
    d = x.shape[1]
    n = np.bincount(cell, minlength=q).astype(float)
    s1 = np.zeros((q, d))
    np.add.at(s1, cell, x)
    s2 = np.zeros((q, d, d))
    order = np.argsort(cell, kind="stable")
    ends = np.cumsum(np.bincount(cell, minlength=q))
    for c in np.flatnonzero(n).tolist():
        part = x[order[ends[c] - int(n[c]) : ends[c]]]
        s2[c] = part.T @ part
    return Cells(n, s1, s2)


def axis_variance(c: Cells, i: int, w: np.ndarray) -> float:
    """Variance of a cluster's objects on the axis w, in units of its length squared."""
    m = c.s1[i] / c.n[i]
    cov = c.s2[i] / c.n[i] - np.outer(m, m)
    return float(max(w @ cov @ w, 0.0)) / float((w @ w) ** 2)


def log_mixture(n_i: float, v_i: float, n_j: float, v_j: float) -> np.ndarray:
    """Log density of the two-part mixture on the grid, centres at 0.5 and -0.5."""
    def part(n, centre, v):
        return np.log(n / (n_i + n_j)) - 0.5 * np.log(2 * np.pi * v) - 0.5 * (GRID - centre) ** 2 / v

    return np.logaddexp(part(n_i, 0.5, v_i), part(n_j, -0.5, v_j))


def log_gap(c: Cells, i: int, j: int, floor: float = 1e-6) -> float:
    """Log of the density gap; minus infinity where the centres coincide."""
    w = c.mean(i) - c.mean(j)
    if not float(w @ w) > 0.0:
        return float("-inf")
    v_i, v_j = max(axis_variance(c, i, w), floor), max(axis_variance(c, j, w), floor)
    return -float(log_mixture(c.n[i], v_i, c.n[j], v_j).min())


class Gaps:
    """Gaps of one cluster against many; follows the statistics of ``c`` by ``refresh``."""

    def __init__(self, c: Cells, floor: float):
        self.c, self.floor = c, floor
        q, d = c.s1.shape
        self.mean, self.cov, self.log_n = np.zeros((d, q)), np.zeros((d, d, q)), np.zeros(q)  # by axis
        for i in np.flatnonzero(c.n > 0).tolist():
            self.refresh(i)

    def refresh(self, i: int) -> None:
        mean = self.c.s1[i] / self.c.n[i]
        self.mean[:, i], self.log_n[i] = mean, np.log(self.c.n[i])
        self.cov[:, :, i] = self.c.s2[i] / self.c.n[i] - np.outer(mean, mean)

    def _lines(self, a: int, js: np.ndarray):
        """(log density but for the square term and variance, of a and of each of
        js on the line through both), and where the centres coincide."""
        w = self.mean[:, a : a + 1] - self.mean[:, js]
        d = len(w)
        l2, va, vj = np.zeros(len(js)), np.zeros(len(js)), np.zeros(len(js))
        for p in range(d):
            for q in range(p, d):
                pq = w[p] * w[q]
                if p == q:
                    l2 += pq
                else:
                    pq *= 2
                va += self.cov[p, q, a] * pq
                vj += self.cov[p, q][js] * pq
        none = ~(l2 > 0.0)
        l4 = np.where(none, 1.0, l2) ** 2
        va, vj = np.maximum(va / l4, self.floor), np.maximum(vj / l4, self.floor)
        total = np.log(self.c.n[a] + self.c.n[js])
        ta = self.log_n[a] - total - 0.5 * np.log(2 * np.pi * va)
        return ta, va, self.log_n[js] - total - 0.5 * np.log(2 * np.pi * vj), vj, none

    def exact(self, a: int, js: np.ndarray) -> np.ndarray:
        out = np.zeros(len(js))
        for lo in range(0, len(js), 20_000):
            ta, va, tj, vj, none = self._lines(a, js[lo : lo + 20_000])
            part = lambda t, centre, v: t[:, None] - 0.5 * (GRID - centre) ** 2 / v[:, None]
            gap = -np.logaddexp(part(ta, 0.5, va), part(tj, -0.5, vj)).min(axis=1)
            out[lo : lo + 20_000] = np.where(none, -np.inf, gap)
        return out

    def bounds(self, a: int, js: np.ndarray) -> np.ndarray:
        """Not above ``exact``: twice the larger part of the mixture at one place of
        the grid, where both are about equal."""
        ta, va, tj, vj, none = self._lines(a, js)
        p, q = 0.5 / va, 0.5 / vj
        # ta - p (u - 1/2)^2 = tj - q (u + 1/2)^2, solved for u.
        two, one, zero = q - p, p + q, ta - tj + 0.25 * (q - p)
        root = np.sqrt(np.maximum(one * one - 4 * two * zero, 0.0))
        u = GRID[np.rint(np.clip(-2 * zero / (one + root), -0.5, 0.5) * 100).astype(np.int64) + 50]
        value = -np.maximum(ta - 0.5 * (u - 0.5) ** 2 / va, tj - 0.5 * (u + 0.5) ** 2 / vj) - math.log(2.0)
        return np.where(none, -np.inf, value - 1e-9 * (1 + np.abs(value)))  # less than rounding could take off

    def least(self, a: int, js: np.ndarray) -> tuple[float, int]:
        """(gap, partner) of the least exact gap, ties to the lower number (js ascend)."""
        if not len(js):
            return float("inf"), -1
        low = self.bounds(a, js)
        few = np.argpartition(low, 7)[:8] if len(js) > 8 else np.arange(len(js))
        left = np.flatnonzero(low <= self.exact(a, js[few]).min())
        gap = self.exact(a, js[left])
        at = int(gap.argmin())
        return float(gap[at]), int(js[left[at]])


def project(x: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Places of x on the line through two centres: a is at 0.5, b at -0.5."""
    w = a - b
    return (x - (a + b) / 2) @ w / (w @ w)


def neighbours(x: np.ndarray, s: int, block: int = 64, rows: np.ndarray | None = None) -> np.ndarray:
    """(n, s) nearest others of each row, or of the given rows, exact at every size,
    in the order of their indices; ties to the lower index.

    Of equal rows one is looked up, and the s + 1 lowest can be found; a row then
    leaves itself out, or else the last.
    """
    n = len(x)
    s = min(s, n - 1)
    asked = np.arange(n) if rows is None else rows
    if s < 1:
        return np.zeros((len(asked), max(s, 0)), np.int64)
    order = np.lexsort(x.T)
    new = np.ones(n, bool)
    new[1:] = (x[order[1:]] != x[order[:-1]]).any(axis=1)
    first = np.flatnonzero(new)
    group = np.cumsum(new) - 1
    nth = np.arange(n) - first[group]
    cls = np.zeros(n, np.int64)
    cls[order] = group
    few = nth <= s
    ids, (need, nth_need) = order[few], np.unique(cls[asked], return_inverse=True)
    got, d = nearest_in(x[order[first[need]]], x[ids], ids, s + 1, block)
    last = s - d[:, ::-1].argmax(axis=1)
    out = np.zeros((len(asked), s), np.int64)
    for lo in range(0, len(asked), 100_000):
        mine, of = asked[lo : lo + 100_000], nth_need[lo : lo + 100_000]
        found = got[of]
        leave = found == mine[:, None]
        other = ~leave.any(axis=1)
        leave[other, last[of[other]]] = True
        out[lo : lo + 100_000] = found[~leave].reshape(len(mine), s)
    return out


def share_of_rows(x: np.ndarray, share: int, shares: int) -> np.ndarray:
    """Rows of one of some shares that are close together and make up all rows."""
    return np.concatenate([np.zeros(0, np.int64), *_boxes(x, max(1, -(-len(x) // shares)))[share::shares]])


def fewer(x: np.ndarray, near: np.ndarray, s: int) -> np.ndarray:
    """The s nearest out of more ``neighbours``."""
    if s >= near.shape[1]:
        return near
    out = np.zeros((len(near), s), near.dtype)
    for lo in range(0, len(near), 100_000):
        part = near[lo : lo + 100_000]
        r = np.repeat(np.arange(lo, lo + len(part)), part.shape[1])
        out[lo : lo + 100_000] = part[least(_by_differences(x, x, r, part.reshape(-1)).reshape(part.shape), s)].reshape(-1, s)
    return out


def nearest_in(x: np.ndarray, y: np.ndarray, ids: np.ndarray, s: int, block: int = 64) -> tuple[np.ndarray, np.ndarray]:
    """(ids, squared distances) of the s nearest rows of y to each row of x, by
    ascending id; ties to the lower id.

    Both are cut at medians into boxes of at most ``block`` rows. The rows of a box
    look into some boxes beside it, then into all that are no further than the
    furthest neighbour found.
    """
    if x.shape[1] > 3 and len(y) > 4096:
        return _nearest_by_products(x, y, ids, s, block)
    got, dist = np.zeros((len(x), s), np.int64), np.zeros((len(x), s))
    around = Boxes(y, block)
    boxes = around.rows
    # Boxes of s rows together at least, however few rows each has.
    enough = np.cumsum(np.sort([len(b) for b in boxes]))
    beside = max(min(len(boxes), 1 << min(x.shape[1], 4)), int(np.searchsorted(enough, s)) + 1)
    for mine, some, apart, edge in around.seen_from(x, block, beside):
        near = some[np.argpartition(apart, beside - 1)[:beside]]
        far = np.partition(_sq(x[mine], y[np.concatenate([boxes[b] for b in near])]), s - 1, axis=1)[:, s - 1].max()
        # Rounding of the sums must not hide a tie at the edge.
        far *= 1 + 1e-9
        if far >= edge:
            some, apart = np.arange(len(boxes)), around.apart(x[mine].min(axis=0), x[mine].max(axis=0))
        seen = np.concatenate([boxes[b] for b in some[apart <= far]])
        seen = seen[np.argsort(ids[seen])]
        step = max(1, 4_000_000 // len(seen))
        for at in range(0, len(mine), step):
            part = mine[at : at + step]
            d = _sq(x[part], y[seen])
            r, c = least(d, s)
            got[part], dist[part] = ids[seen[c]].reshape(-1, s), d[r, c].reshape(-1, s)
    return got, dist


def _nearest_by_products(x: np.ndarray, y: np.ndarray, ids: np.ndarray, s: int, block: int) -> tuple[np.ndarray, np.ndarray]:
    """``nearest_in`` on more axes, where boxes tell little: products in single
    precision leave the rows of y that can be among the s nearest with all that
    rounding could do, differences decide. The rows of a box are taken in parts of
    about equal reach, so that few of far reach don't widen the search of the rest.
    """
    got, dist = np.zeros((len(x), s), np.int64), np.zeros((len(x), s))
    around = Boxes(y, block)
    at = np.concatenate(around.rows)
    edges = np.concatenate([[0], np.cumsum([len(b) for b in around.rows])])
    d, mid = x.shape[1], (y.min(axis=0) + y.max(axis=0)) / 2
    z, zx = y[at] - mid, x - mid
    zz, xx = np.einsum("ij,ij->i", z, z), np.einsum("ij,ij->i", zx, zx)
    right = np.column_stack([-2 * z, zz]).T.astype(np.float32)
    left = np.column_stack([zx, np.ones(len(x))]).astype(np.float32)
    slack = 4 * (d + 4) * float(np.finfo(np.float32).eps) * (float(zz.max()) + float(xx.max()))
    enough = np.cumsum(np.sort([len(b) for b in around.rows]))
    beside = min(len(around.rows), max(64, int(np.searchsorted(enough, s)) + 1))
    starts, ends = edges[:-1], edges[1:]

    def places(boxes: np.ndarray) -> np.ndarray:
        n = ends[boxes] - starts[boxes]
        return np.repeat(starts[boxes] - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(int(n.sum()))

    for mine, some, apart, edge in around.seen_from(x, block, beside, 4096):
        seen = places(some[np.argpartition(apart, beside - 1)[:beside]])
        # Square distances but for the row's own square, as single products.
        reach = np.partition(left[mine] @ right[:, seen], s - 1, axis=1)[:, s - 1].astype(float) + 2 * slack
        far = np.maximum(reach + xx[mine], 0.0) * (1 + 1e-9) + slack
        order = np.argsort(far, kind="stable")
        for part in np.array_split(order, min(4, len(order))):
            rows = mine[part]
            low, high, most = x[rows].min(axis=0), x[rows].max(axis=0), far[part].max()
            within = np.arange(len(starts)) if most >= edge else some[apart <= most]
            seen = places(within[around.apart(low, high, within) <= most])
            step = max(1, 4_000_000 // len(seen))
            for lo in range(0, len(rows), step):
                few = rows[lo : lo + step]
                r, c = np.nonzero(left[few] @ right[:, seen] <= reach[part[lo : lo + step], None])
                c = at[seen[c]]
                d2 = _by_differences(x[few], y, r, c)
                pick = first_of_each(r, d2, ids[c], s)
                again = pick[np.lexsort((ids[c[pick]], r[pick]))]
                got[few], dist[few] = ids[c[again]].reshape(-1, s), d2[again].reshape(-1, s)
    return got, dist


class Boxes:
    """Rows in boxes, and which boxes are near others."""

    def __init__(self, y: np.ndarray, block: int):
        self.rows = _boxes(y, block)
        self.low, self.high = (np.array([f(y[b], axis=0) for b in self.rows]).T.copy() for f in (np.min, np.max))

    def apart(self, lo: np.ndarray, hi: np.ndarray, some=slice(None)) -> np.ndarray:
        """Squared distance of each box to the one from lo to hi."""
        out = 0.0
        for low, high, a, b in zip(self.low, self.high, lo, hi, strict=True):
            out += np.maximum(np.maximum(low[some] - b, a - high[some]), 0.0) ** 2
        return out

    def seen_from(self, x: np.ndarray, block: int, least: int, most: int = 512):
        """(rows of x in a box, numbers of the boxes near it, their squared
        distances, what all other boxes exceed or equal); boxes near a larger box
        are looked for once for all in it."""
        most = max(most, least)
        for large in _boxes(x, 64 * block):
            far = self.apart(x[large].min(axis=0), x[large].max(axis=0))
            some, edge = np.arange(len(far)), np.inf
            if len(far) > most:
                cut = np.argpartition(far, most)
                some, edge = np.sort(cut[:most]), far[cut[most]]
            for inner in _boxes(x[large], block):
                mine = large[inner]
                yield mine, some, self.apart(x[mine].min(axis=0), x[mine].max(axis=0), some), edge


def _boxes(x: np.ndarray, most: int) -> list[np.ndarray]:
    """Indices of the rows in boxes cut at the median of their widest axis."""
    out, stack = [], [np.arange(len(x))]
    while stack:
        rows = stack.pop()
        if len(rows) <= most:
            out.append(rows)
            continue
        part = x[rows]
        half = len(rows) // 2
        cut = np.argpartition(part[:, int(np.ptp(part, axis=0).argmax())], half)
        stack += [rows[cut[half:]], rows[cut[:half]]]
    return out


def _sq(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    d = np.zeros((len(a), len(b)))
    for c in range(a.shape[1]):
        d += (a[:, c][:, None] - b[:, c][None, :]) ** 2
    return d


def least(d: np.ndarray, s: int) -> tuple[np.ndarray, np.ndarray]:
    """Row and column of the s least of each row, ties to the lower column."""
    last = np.partition(d, s - 1, axis=1)[:, s - 1 : s]
    pick = d <= last
    for r in np.flatnonzero(pick.sum(axis=1) > s).tolist():
        ties = np.flatnonzero(d[r] == last[r])
        pick[r, ties[s - int((d[r] < last[r]).sum()) :]] = False
    return np.nonzero(pick)


def _by_products(x: np.ndarray, y: np.ndarray):
    """Blocks of rows of x as (place, squared distances to y by products, bound of
    their rounding)."""
    xx, yy = np.einsum("ij,ij->i", x, x), np.einsum("ij,ij->i", y, y)
    step = max(1, 4_000_000 // len(y))
    for lo in range(0, len(x), step):
        part = xx[lo : lo + step, None]
        yield lo, part + yy - 2 * (x[lo : lo + step] @ y.T), 8 * (x.shape[1] + 8) * np.finfo(float).eps * (part + yy.max())


def _by_differences(x: np.ndarray, y: np.ndarray, r: np.ndarray, c: np.ndarray) -> np.ndarray:
    d2 = np.zeros(len(r))
    for j in range(x.shape[1]):
        d2 += (x[r, j] - y[c, j]) ** 2
    return d2


def close_pairs(x: np.ndarray, y: np.ndarray, s: int, allowed=None):
    """(place, (row, column, d2)) for blocks of rows of x: at least the s nearest
    rows of y, by products with all that rounding could have put behind them,
    distances by differences. ``allowed(lo, hi)`` masks pairs."""
    for lo, d2, slack in _by_products(x, y):
        if allowed is not None:
            d2[~allowed(lo, lo + len(d2))] = np.inf
        last = np.partition(d2, s - 1, axis=1)[:, s - 1 : s]
        r, c = np.nonzero(~(d2 > last + slack) & (d2 != np.inf))
        yield lo, (r, c, _by_differences(x[lo : lo + len(d2)], y, r, c))


def first_of_each(r: np.ndarray, d2: np.ndarray, c: np.ndarray, s: int) -> np.ndarray:
    """Places of the s least (d2, c) of each r."""
    order = np.lexsort((c, d2, r))
    start = np.searchsorted(r[order], r[order])
    return order[np.arange(len(order)) - start < s]


def pairs_below(x: np.ndarray, y: np.ndarray, limit: float):
    """(place, mask) for blocks of rows of x: whose squared distance is below the
    limit; by products, by differences where rounding could decide."""
    for lo, d2, slack in _by_products(x, y):
        inside = d2 < limit
        r, c = np.nonzero(~(np.abs(d2 - limit) > slack))
        inside[r, c] = _by_differences(x[lo : lo + len(d2)], y, r, c) < limit
        yield lo, inside


def cross_counts(near: np.ndarray, cell: np.ndarray, q: int) -> np.ndarray:
    """(q, q): how often an object of one cell has a neighbour in another."""
    out = np.zeros((q, q))
    if near.shape[1]:
        np.add.at(out, (np.repeat(cell, near.shape[1]), cell[near].reshape(-1)), 1)
    return out


def cross_pairs(near: np.ndarray, cell: np.ndarray, q: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``cross_counts`` as (cell, neighbour's cell, count), without the zeros."""
    found = [np.unique((cell[lo : lo + 200_000, None] * q + cell[near[lo : lo + 200_000]]).reshape(-1), return_counts=True) for lo in range(0, len(near), 200_000)]
    at, of = np.unique(np.concatenate([a for a, _ in found]) if found else np.zeros(0, np.int64), return_inverse=True)
    n = np.bincount(of, weights=np.concatenate([c for _, c in found]) if found else None, minlength=len(at))
    return at // q, at % q, n.astype(float)


def _pairs_of(cross) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    return cross if isinstance(cross, tuple) else (*np.nonzero(cross), cross[np.nonzero(cross)])


def separability(cross, group: np.ndarray, s: int) -> float:
    """Worst cluster's number of foreign neighbours, over s; group by cell. cross
    as from ``cross_counts`` or ``cross_pairs``."""
    a, b, n = _pairs_of(cross)
    names, group = np.unique(group, return_inverse=True)
    apart = group[a] != group[b]
    return float(np.bincount(group[a[apart]], weights=n[apart], minlength=len(names)).max(initial=0.0)) / max(s, 1)


@dataclass
class Trace:
    """One row for each k from the first state down: the pair merged next."""

    k: list[int]
    a: list[int]
    b: list[int]
    log_theta: list[float]
    omega: list[float]
    start: np.ndarray
    gaps: int = 0

    def groups(self, k: int) -> np.ndarray:
        """Cluster of each cell when k clusters are left, -1 for empty cells."""
        g = self.start.copy()
        for kk, a, b in zip(self.k, self.a, self.b, strict=True):
            if kk <= k or a < 0:
                break
            g[g == b] = a
        return g


def bridged(edges: list[tuple[int, int]], n: np.ndarray) -> set[tuple[int, int]]:
    """Edges between cells with objects; neighbours of an empty cell meet."""
    near: dict[int, set[int]] = {i: set() for i in range(len(n))}
    for a, b in edges:
        near[a].add(b)
        near[b].add(a)
    out = {(min(a, b), max(a, b)) for a, b in edges if a != b and n[a] and n[b]}
    seen = n > 0
    for dead in np.flatnonzero(n == 0).tolist():
        around, stack = set(), [dead]
        while stack:  # over empty cells that are linked
            at = stack.pop()
            if not seen[at]:
                seen[at] = True
                around |= {o for o in near[at] if n[o]}
                stack += [o for o in near[at] if not seen[o]]
        out.update(itertools.combinations(sorted(around), 2))
    return out


def closest_across(c: Cells, subnet: np.ndarray, alive: list[int]) -> set[tuple[int, int]]:
    """For each pair of subnets their two closest cells, and for each cell the
    nearest one of another subnet."""
    ids = np.array(alive)
    if len(ids) < 2:
        return set()
    m, of = c.s1[ids] / c.n[ids, None], subnet[ids]
    names = np.unique(of)
    if len(names) < 2:
        return set()
    parts = [np.flatnonzero(of == name) for name in names]
    boxes = [Boxes(m[mine], 32) for mine in parts]
    out = set()
    for i, mine in enumerate(parts):
        others = np.flatnonzero(of != names[i])
        near = nearest_in(m[mine], m[others], others, 1)[0][:, 0]
        out |= set(zip(ids[np.minimum(mine, near)].tolist(), ids[np.maximum(mine, near)].tolist(), strict=True))
        for j in range(i + 1, len(names)):
            a, b = closest_pair(m, mine, boxes[i], parts[j], boxes[j])
            out.add((int(min(ids[a], ids[b])), int(max(ids[a], ids[b]))))
    return out


def closest_pair(m: np.ndarray, some: np.ndarray, some_boxes: Boxes, others: np.ndarray, other_boxes: Boxes) -> tuple[int, int]:
    """Of two sets of rows of m the closest pair, ties to the lower rows; pairs of
    boxes are looked at from the closest on."""
    best = (np.inf, -1, -1)
    top = other_boxes.apart(some_boxes.low.min(axis=1), some_boxes.high.max(axis=1))
    first = np.argsort(top, kind="stable")
    for at in first.tolist():
        if top[at] > best[0] * (1 + 1e-9):
            break
        cols = np.sort(others[other_boxes.rows[at]])
        apart = some_boxes.apart(m[cols].min(axis=0), m[cols].max(axis=0))
        for o in np.argsort(apart, kind="stable").tolist():
            if apart[o] > best[0] * (1 + 1e-9):
                break
            rows = np.sort(some[some_boxes.rows[o]])
            d = _sq(m[rows], m[cols])
            r, q = np.unravel_index(int(d.argmin()), d.shape)
            best = min(best, (float(d[r, q]), int(rows[r]), int(cols[q])))
    return best[1], best[2]


def run(cells: Cells, subnet: np.ndarray, edges: list[tuple[int, int]], cross, s: int, p: Params) -> Trace:
    """Merge down to one cluster, the pair with the least gap first.

    guided looks at the edges inside subnets and, for each pair of subnets, at
    their closest cells; two_stage at adjacent pairs inside subnets until none
    is left, then at all pairs of what remains; adjacent at all edges, then at
    all pairs; all_pairs at all pairs from the start. The two stages in turn
    force a subnet that spans two clusters into one before any other merge,
    guided lets the gap decide; on one complete subnet all of them agree.

    cross is as from ``cross_counts`` or ``cross_pairs``. While all pairs are open
    each cluster keeps its least gap to a later one; the pair of a cluster that
    lost it is looked for when that gap, then a lower bound, is the least of all.
    """
    c = cells.copy()
    alive = np.flatnonzero(c.n > 0).tolist()
    start = np.where(c.n > 0, np.arange(len(c.n)), -1)
    foreign, between = np.full(len(c.n), -np.inf), {i: {} for i in alive}
    foreign[alive] = 0.0
    for i, j, n in zip(*(v.tolist() for v in _pairs_of(cross)), strict=True):
        if i != j:
            foreign[i] += n
            if j in between and i in between:
                between[i][j] = between[i].get(j, 0.0) + n
                between[j][i] = between[i][j]
    t, k, gap = Trace([], [], [], [], [], start), len(alive), Gaps(c, p.var_floor)

    def note(a: int, b: int, theta: float) -> None:
        t.k.append(k), t.a.append(a), t.b.append(b), t.log_theta.append(theta), t.omega.append(float(foreign.max()) / max(s, 1))

    def unite(a: int, b: int) -> None:
        foreign[a] += foreign[b] - between[a].pop(b, 0.0)
        foreign[b] = -np.inf
        for o, n in between.pop(b).items():
            if o != a:
                between[a][o] = between[a].get(o, 0.0) + n
                between[o][a] = between[a][o]
                del between[o][b]
        c.add(a, b)
        gap.refresh(a)

    near: dict[int, set[int]] = {i: set() for i in alive}
    for a, b in bridged(edges, c.n) if p.schedule != "all_pairs" else ():
        if p.schedule != "two_stage" or subnet[a] == subnet[b]:
            near[a].add(b)
            near[b].add(a)
    if p.schedule == "guided":
        for a, b in closest_across(c, subnet, alive):
            near[a].add(b)
            near[b].add(a)
    version = np.zeros(len(c.n), np.int64)
    heap: list[tuple[float, int, int, int, int]] = []

    def push(a: int, others: list[int]) -> None:
        if others:
            t.gaps += len(others)
            for b, theta in zip(others, gap.exact(a, np.array(others)).tolist(), strict=True):
                i, j = min(a, b), max(a, b)
                heapq.heappush(heap, (theta, i, j, int(version[i]), int(version[j])))

    for a in alive:
        push(a, [b for b in near[a] if a < b])
    most = 2 * len(heap) + 100_000
    while k > 1 and heap:
        theta, a, b, at_a, at_b = heapq.heappop(heap)
        if at_a != version[a] or at_b != version[b]:
            continue
        note(a, b, theta)
        unite(a, b)
        version[a] += 1
        version[b] += 1
        for o in near[b]:
            near[o].discard(b)
            if o != a:
                near[o].add(a)
        near[a] = (near[a] | near.pop(b)) - {a, b}
        push(a, list(near[a]))
        k -= 1
        if len(heap) > most:  # gaps of pairs that changed since go
            heap = [h for h in heap if h[3] == version[h[1]] and h[4] == version[h[2]]]
            heapq.heapify(heap)
            most = max(most, 2 * len(heap))

    ids = np.array(sorted(near), np.int64)
    t.gaps += k * (k - 1) // 2
    low, mate, known = np.full(len(c.n), np.inf), np.full(len(c.n), -1), np.zeros(len(c.n), bool)
    known[ids] = True
    for at in range(k - 1):
        low[ids[at]], mate[ids[at]] = gap.least(int(ids[at]), ids[at + 1 :])
    while k > 1:
        a = int(ids[low[ids].argmin()])
        if not known[a]:
            low[a], mate[a] = gap.least(a, ids[ids > a])
            known[a] = True
            continue
        b = int(mate[a])
        note(a, b, float(low[a]))
        unite(a, b)
        k -= 1
        t.gaps += k - 1
        ids = np.delete(ids, np.searchsorted(ids, b))
        low[b] = np.inf
        known[ids[(mate[ids] == a) | (mate[ids] == b)]] = False
        before, after = ids[ids < a], ids[ids > a]
        if len(before):
            new = gap.bounds(a, before)
            lost = ~known[before]
            low[before[lost]] = np.minimum(low[before[lost]], new[lost])
            some = before[~lost & (new <= low[before])]
            if len(some):
                new = gap.exact(a, some)
                won = (new < low[some]) | ((new == low[some]) & (a < mate[some]))
                low[some[won]], mate[some[won]] = new[won], a
        (low[a], mate[a]), known[a] = gap.least(a, after), True
    if k == 1:
        note(-1, -1, float("nan"))
    return t


def scores(k: np.ndarray, log_theta: np.ndarray, omega: np.ndarray, min_k: int = 2, theta: str = "formed") -> tuple[np.ndarray, np.ndarray]:
    """(k, score) by falling k: normalised gap plus normalised separability.

    next: the gap of the merge that k clusters would make. formed: the largest
    gap of the merges that made them, which never falls as k does; without it a
    trace whose widest gap lies between its true clusters prefers the few
    clusters after that merge, as all later gaps are small beside it.
    """
    order = np.argsort(-k, kind="stable")
    k, gap, omega = k[order], log_theta[order], omega[order]
    top = float(np.nanmax(gap)) if len(gap) and not np.isnan(gap).all() else 0.0
    if theta == "formed":
        gap = np.concatenate([[-np.inf], np.maximum.accumulate(np.where(np.isnan(gap), -np.inf, gap))[:-1]])
    else:
        gap = np.where(np.isnan(gap), top, gap)
    value = np.exp(gap - top) if np.isfinite(top) else np.zeros(len(k))
    ok = k >= min_k
    worst = omega[ok].max() if ok.any() else 0.0
    return k[ok], value[ok] + (omega[ok] / worst if worst > 0 else 0.0)


def best_k(k: np.ndarray, log_theta: np.ndarray, omega: np.ndarray, rule: str = "argmin", min_k: int = 2, theta: str = "formed", max_k: int = 0) -> int:
    """The k of the least score, or the score curve's knee; ties to smaller k."""
    kk, score = scores(np.asarray(k), np.asarray(log_theta, float), np.asarray(omega, float), min_k, theta)
    if not len(kk):
        return 1
    if max_k and (kk <= max_k).any():
        kk, score = kk[kk <= max_k], score[kk <= max_k]
    kk, score = kk[::-1], score[::-1]
    if rule == "argmin" or len(kk) < 3:
        return int(kk[int(score.argmin())])
    line = score[0] + (score[-1] - score[0]) * (kk - kk[0]) / (kk[-1] - kk[0])
    return int(kk[int((line - score).argmax())])


def neuron_cross(w: np.ndarray, s: int) -> np.ndarray:
    """Neurons as objects: (q, q) 0/1 neighbour counts."""
    return cross_counts(neighbours(w, s), np.arange(len(w)), len(w))
