"""The growing map: several small neuron graphs trained one object at a time.

Plain NumPy; the same code runs in an executor's task, on the driver and in
tests. A map is trained in one task because every step depends on the one
before; parallelism comes from chunks, streams or shards.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np

from ..params import Params
from . import merging
from .places import MOST_AXES, Places, square_gaps

#: Neurons from which a block of objects is taken together on few axes.
LARGE = 6000
#: Nearest neurons that are looked up for each object then.
CLOSE = 4


def sq_distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Squared distances of all rows of a to all rows of b, by differences."""
    return ((a[:, None, :] - b[None, :, :]) ** 2).sum(axis=2)


@dataclass
class GrowingMap:
    """Neurons, their strain, subnet and wins, and an undirected edge set."""

    w: np.ndarray
    strain: np.ndarray
    subnet: np.ndarray
    hits: np.ndarray
    nbrs: list[set[int]]
    idle: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    splits: int = 0
    joins: int = 0
    steps: int = 0
    distances: int = 0
    #: Room behind the arrays, and for a large map its places and neighbours as arrays.
    room: dict[str, np.ndarray] = field(default_factory=dict, repr=False, compare=False)
    places: Places | None = field(default=None, repr=False, compare=False)
    around: np.ndarray | None = field(default=None, repr=False, compare=False)
    changed: set[int] = field(default_factory=set, repr=False, compare=False)
    #: Neurons from which places are worth another try, where many are in one place.
    crowded: int = 0

    @classmethod
    def empty(cls, d: int) -> GrowingMap:
        return cls(np.zeros((0, d)), np.zeros(0), np.zeros(0, np.int64), np.zeros(0, np.int64), [])

    @classmethod
    def from_rows(cls, neurons: list[dict], edges: list[dict], d: int) -> GrowingMap:
        rows = sorted(neurons, key=lambda r: r["neuron"])
        m = cls(np.array([r["w"] for r in rows], float).reshape(len(rows), d), np.array([r["strain"] for r in rows], float), np.array([r["subnet"] for r in rows], np.int64), np.array([r["hits"] for r in rows], np.int64), [set() for _ in rows])
        for e in edges:
            m.link(e["a"], e["b"])
        return m

    @property
    def q(self) -> int:
        return len(self.w)

    def edges(self) -> list[tuple[int, int]]:
        return sorted((a, b) for a in range(self.q) for b in self.nbrs[a] if a < b)

    def link(self, a: int, b: int) -> None:
        self.nbrs[a].add(b)
        self.nbrs[b].add(a)
        self.changed |= {a, b}

    def unlink(self, a: int, b: int) -> None:
        self.nbrs[a].discard(b)
        self.nbrs[b].discard(a)
        self.changed |= {a, b}

    def add(self, w: np.ndarray, subnet: int, strain: float = 0.0) -> int:
        n = self.q
        for name, value in (("w", w), ("strain", strain), ("subnet", subnet), ("hits", 0)):
            held, room = getattr(self, name), self.room.get(name)
            if room is None or held.base is not room or len(room) == n:
                room = np.empty((max(64, 2 * n), *held.shape[1:]), held.dtype)
                room[:n] = held
                self.room[name] = room
            room[n] = value
            setattr(self, name, room[: n + 1])
        self.nbrs.append(set())
        self.changed.add(n)
        return n

    def winner(self, x: np.ndarray) -> tuple[int, float]:
        """Nearest neuron, ties to the lowest number, and its distance."""
        gap = self.w - x
        d2 = np.einsum("ij,ij->i", gap, gap)
        p = int(d2.argmin())
        return p, float(np.sqrt(d2[p]))

    def visit(self, x: np.ndarray, p: Params) -> int:
        """One training object: pull the winner and its neighbours, account strain."""
        return self.visits(x[None, :], p)

    def visits(self, rows: np.ndarray, p: Params) -> int:
        """``visit`` for each row in turn, between which the graph stays as it is;
        the last winner."""
        if self.q >= max(LARGE, self.crowded) and rows.shape[1] <= MOST_AXES and p.strain_at == "before" and np.isfinite(rows).all():
            self._index()
            if 16 * len(self.places.over) <= self.q:
                return self._visits_together(rows, p)
            self.crowded = 2 * self.q
        self.places = None
        w, strain = np.ascontiguousarray(self.w.T), self.strain  # by axis: long runs in memory
        gap, d2 = np.empty_like(w), np.empty(self.q)
        near: dict[int, np.ndarray] = {}
        kept_share: dict[int, np.ndarray] = {}
        win = -1
        for x in rows[:, :, None]:
            np.subtract(w, x, out=gap)
            np.multiply(gap, gap, out=gap)
            np.add.reduce(gap, axis=0, out=d2)
            win = int(d2.argmin())
            far = math.sqrt(d2[win])
            self.distances += self.q
            w[:, win] += p.lr_win * (x[:, 0] - w[:, win])
            if win not in near:
                near[win] = np.array(list(self.nbrs[win]), np.int64)
                subnet = int(self.subnet[win])
                if subnet not in kept_share:
                    kept_share[subnet] = np.where(self.subnet == subnet, 1.0 - p.decay, 1.0)
            around = near[win]
            if len(around):
                at = w[:, around]
                w[:, around] = at + p.lr_nbr * (x - at)
            if p.strain_at == "after":
                far = float(np.linalg.norm(x[:, 0] - w[:, win]))
            kept = strain[win] + far
            strain *= kept_share[int(self.subnet[win])]
            strain[win] = kept
            self.hits[win] += 1
        self.w = np.ascontiguousarray(w.T)
        return win

    def _index(self) -> None:
        """Places and neighbour arrays as the map is now."""
        if self.places is None or self.places.worn(self.q):
            if self.places is None:
                self.around, self.changed = np.full((self.q, 8), -1), set(range(self.q))
            self.places = Places(self.w)
        else:
            new = np.array([v for v in self.changed if self.places.cell[v] < 0], np.int64)
            self.places.move(new, self.w[new])
        most = max((len(self.nbrs[v]) for v in self.changed), default=0)
        if self.q > len(self.around) or most > self.around.shape[1]:
            larger = np.full((2 * self.q, max(most, self.around.shape[1])), -1)
            larger[: len(self.around), : self.around.shape[1]] = self.around
            self.around = larger
        for v in self.changed:
            near = self.nbrs[v]
            self.around[v, : len(near)], self.around[v, len(near) :] = list(near), -1
        self.changed = set()

    def _visits_together(self, rows: np.ndarray, p: Params) -> int:
        """``visits`` of a large map. Winners are guessed from where neurons are before
        all rows; then all pulls are worked out, each row's winner is looked for among
        the neurons where they are by then, and the pulls again, until no winner
        changes. That ends, as rows up to the first that changed are right."""
        n, w, t = len(rows), self.w, np.arange(len(rows))
        near, near2, limit = self.places.few(rows, w, CLOSE)
        for i in np.flatnonzero(near[:, 0] < 0).tolist():
            d2 = square_gaps(w, rows[i])
            cut = np.argpartition(d2, CLOSE)[: CLOSE + 1]
            limit[i] = d2[cut].max()
            cut = np.sort(cut[d2[cut] < limit[i]]) if (d2[cut] < limit[i]).any() else np.array([d2.argmin()])
            cut = cut[np.argsort(d2[cut], kind="stable")]
            near[i, : len(cut)], near2[i, : len(cut)] = cut, d2[cut]
        win, moved_at = near[:, 0].copy(), np.full(self.q, n)
        while True:
            both = np.column_stack([win, self.around[win]])
            r, c = np.nonzero(both >= 0)
            who = both[r, c]
            order = np.argsort(who, kind="stable")
            who, when, pulled = who[order], r[order], c[order] == 0
            x, rate = rows[when], np.where(pulled, p.lr_win, p.lr_nbr)[:, None]
            again = np.zeros(len(who), bool)
            again[1:] = who[1:] == who[:-1]
            first = np.flatnonzero(~again)
            before = w[who]
            after = before + rate * (x - before)
            if again.any():
                nth = np.arange(len(who)) - np.repeat(first, np.diff(np.append(first, len(who))))
                turns = np.split(np.argsort(nth, kind="stable"), np.cumsum(np.bincount(nth)))
                for at in turns[1:]:
                    if len(at) > 8:
                        before[at] = now = after[at - 1]
                        after[at] = now + rate[at] * (x[at] - now)
                        continue
                    for i in at.tolist():  # the few that many rows pull
                        by = float(rate[i, 0])
                        before[i] = now = after[i - 1].tolist()
                        after[i] = [v + by * (to - v) for v, to in zip(now, x[i].tolist(), strict=True)]
            until = np.full(len(who), n)
            until[:-1][again[1:]] = when[1:][again[1:]]
            moved_at[who[first]] = when[first]
            still = np.where(moved_at[near] < t[:, None], np.inf, near2)
            i = still.argmin(axis=1)
            unmoved, to_unmoved = near[t, i], still[t, i]
            # Of the moved ones those no further on the first axis.
            along, reach = np.argsort(after[:, 0]), np.sqrt(to_unmoved) * (1 + 1e-9)
            lo, hi = (np.searchsorted(after[along, 0], rows[:, 0] + v, side=e) for v, e in ((-reach, "left"), (reach, "right")))
            row = np.repeat(t, hi - lo)
            some = along[np.arange(len(row)) + np.repeat(lo - np.cumsum(hi - lo) + (hi - lo), hi - lo)]
            there = (row > when[some]) & (row <= until[some])
            row, some = row[there], some[there]
            gap = square_gaps(after[some], rows[row])
            least = np.lexsort((who[some], gap, row))
            least = least[np.flatnonzero(np.diff(row[least], prepend=-1))]
            to_moved, moved = np.full(n, np.inf), np.zeros(n, np.int64)
            to_moved[row[least]], moved[row[least]] = gap[least], who[some[least]]
            for a in np.flatnonzero(np.isinf(to_unmoved) & ~(to_moved < limit)).tolist():
                d2 = square_gaps(w, rows[a])
                d2[moved_at < a] = np.inf
                unmoved[a] = d2.argmin()
                to_unmoved[a] = d2[unmoved[a]]
            moved_at[who[first]] = n
            new = np.where((to_moved < to_unmoved) | ((to_moved == to_unmoved) & (moved < unmoved)), moved, unmoved)
            if (new == win).all():
                break
            win = new
        last = np.append(first[1:], len(who)) - 1
        w[who[last]] = after[last]
        self.places.move(who[last], after[last])
        far = np.sqrt(square_gaps(before[pulled], x[pulled]))
        self._account(who[pulled], when[pulled], far, win, p)
        self.distances += self.q * n
        return int(win[-1])

    def _account(self, who: np.ndarray, when: np.ndarray, far: np.ndarray, win: np.ndarray, p: Params) -> None:
        """Strain and hits after several rows: ``far`` of neuron who at its times, by
        neuron and time. Strain falls at each win of another neuron of the subnet."""
        names, of = np.unique(self.subnet[win], return_inverse=True)
        wins, turn = np.bincount(of), np.zeros(len(win), np.int64)
        for s in range(len(names)):
            turn[of == s] = np.arange(1, wins[s] + 1)
        kept = (1.0 - p.decay) ** np.arange(len(win) + 1)
        first = np.flatnonzero(np.diff(who, prepend=-1))
        own = np.diff(np.append(first, len(who)))
        later = np.repeat(first + own, own) - 1 - np.arange(len(who))
        grown = np.add.reduceat(far * kept[wins[of[when]] - turn[when] - later], first)
        mine = who[first]
        grown += self.strain[mine] * kept[wins[of[when[first]]] - own]
        fall = np.ones(int(self.subnet.max()) + 1)
        fall[names] = kept[wins]
        self.strain *= fall[self.subnet]
        self.strain[mine] = grown
        self.hits[mine] += own

    def strained_pair(self) -> tuple[int, int | None]:
        """The most strained neuron, and the most strained of another subnet."""
        v = int(self.strain.argmax())
        g = int(np.where(self.subnet != self.subnet[v], self.strain, -np.inf).argmax())
        return v, g if self.subnet[g] != self.subnet[v] else None

    def furthest_neighbour(self, v: int) -> int | None:
        near = sorted(self.nbrs[v])
        if not near:
            return None
        return near[int(((self.w[near] - self.w[v]) ** 2).sum(axis=1).argmax())]

    def spread(self, v: int) -> float:
        """Mean length of a neuron's edges."""
        near = list(self.nbrs[v])
        return float(np.sqrt(((self.w[near] - self.w[v]) ** 2).sum(axis=1)).mean()) if near else 0.0

    def split(self, v: int, q: int, keep_edge: bool = False) -> int:
        """A newborn half-way between v and q, linked to both and to the
        neighbours they share; it takes over the strain that they lose."""
        shared = self.nbrs[v] & self.nbrs[q]
        around = sorted(shared | {v, q})
        before = {c: self.spread(c) for c in around}
        h = self.add((self.w[v] + self.w[q]) / 2, int(self.subnet[v]))
        if not keep_edge:
            self.unlink(v, q)
        for c in around:
            self.link(h, c)
        for c in around:
            loss = (before[c] - self.spread(c)) / before[c] * self.strain[c] if before[c] > 0 else 0.0
            self.strain[c] -= loss
            self.strain[h] += loss
        self.splits += 1
        return h

    def merge_subnets(self, v: int, q: int | None, g: int) -> None:
        """Link v and its furthest neighbour to a neuron of another subnet."""
        self.link(v, g)
        if q is not None:
            self.link(q, g)
        a, b = int(self.subnet[v]), int(self.subnet[g])
        self.subnet[self.subnet == max(a, b)] = min(a, b)
        self.joins += 1

    def step(self, p: Params) -> str:
        """Split the strained edge, or join the two strained subnets."""
        self.steps += 1
        v, g = self.strained_pair()
        q = self.furthest_neighbour(v)
        apart = g is not None and (q is None or np.linalg.norm(self.w[v] - self.w[g]) <= np.linalg.norm(self.w[v] - self.w[q]))
        if apart:
            if p.join:
                self.merge_subnets(v, q, g)
                return "join"
            return "none"
        if p.grow and q is not None:
            if p.max_neurons and self.q >= p.max_neurons:
                raise ValueError(f"the map needs more than max_neurons = {p.max_neurons} neurons: raise it, or cluster in shards")
            self.split(v, q, p.keep_split_edge)
            return "split"
        return "none"

    def drop(self, gone: np.ndarray) -> None:
        """Remove neurons; the rest are numbered anew in their order."""
        keep = np.flatnonzero(~gone)
        number = {int(old): new for new, old in enumerate(keep)}
        self.nbrs = [{number[b] for b in self.nbrs[a] if b in number} for a in keep]
        self.w, self.strain, self.subnet, self.hits = self.w[keep], self.strain[keep], self.subnet[keep], self.hits[keep]
        self.places = None


def seeds(x: np.ndarray, t: int, how: str = "poisson") -> np.ndarray:
    """Indices of t points in given (seeded) order.

    poisson: no two closer than the largest radius, by bisection, at which dart
    throwing over the points still accepts t of them.
    """
    n = len(x)
    t = min(t, n)
    if how == "random" or t == n:
        return np.arange(t)
    if how == "farthest":
        picked, d = [0], ((x - x[0]) ** 2).sum(axis=1)
        while len(picked) < t:
            picked.append(int(d.argmax()))
            d = np.minimum(d, ((x - x[picked[-1]]) ** 2).sum(axis=1))
        return np.array(picked)

    def thrown(r2: float) -> list[int]:
        got: list[int] = []
        free = np.ones(n, bool)
        while len(got) < t and free.any():
            i = int(free.argmax())
            got.append(i)
            free &= merging._sq(x, x[i : i + 1])[:, 0] >= r2
            free[i] = False
        return got

    lo, hi = 0.0, float(((x.max(axis=0) - x.min(axis=0)) ** 2).sum())
    best = list(range(t))
    for _ in range(24):
        mid = (lo + hi) / 2
        got = thrown(mid)
        if len(got) >= t:
            best, lo = got, mid
        else:
            hi = mid
    return np.array(best)


def triangles(x: np.ndarray, picked: np.ndarray) -> GrowingMap:
    """A three-neuron subnet at each seed: the seed and its two nearest points,
    or points set off a little where there are none."""
    m = GrowingMap.empty(x.shape[1])
    scale = float(np.ptp(x, axis=0).max()) or 1.0
    for number, i in enumerate(picked.tolist()):
        d = ((x - x[i]) ** 2).sum(axis=1)
        d[i] = np.inf
        near = [j for j in np.argsort(d, kind="stable")[:8].tolist() if np.isfinite(d[j]) and d[j] > 0][:2]
        corners = [x[i], *(x[j] for j in near)]
        for k in range(len(corners), 3):
            offset = np.zeros(x.shape[1])
            offset[k % x.shape[1]] = scale * 1e-3 * k
            corners.append(x[i] + offset)
        ids = [m.add(np.array(c, float), number) for c in corners]
        for a, b in ((0, 1), (1, 2), (0, 2)):
            m.link(ids[a], ids[b])
    return m


def fit(x: np.ndarray, p: Params, state: GrowingMap | None = None, given: np.ndarray | None = None) -> GrowingMap:
    """One pass over the rows of x in seeded order."""
    order = np.random.default_rng(p.seed).permutation(len(x))
    if not len(x):
        return state or GrowingMap.empty(x.shape[1])
    m = state
    if m is None or not m.q:
        pool = x[order]
        m = triangles(pool, np.arange(min(p.subnets, len(pool))) if given is not None else seeds(pool, p.subnets, p.seeding))
    m.hits[:] = 0
    for lo in range(0, len(order), p.rho):
        rows = order[lo : lo + p.rho]
        m.visits(x[rows], p)
        if len(rows) == p.rho:
            m.step(p)
    if p.prune == "idle":
        wins = {s: int(m.hits[m.subnet == s].sum()) for s in set(m.subnet.tolist())}
        gone = np.array([wins[int(s)] < p.min_hits for s in m.subnet])
        if gone.any() and not gone.all():
            m.drop(gone)
    return m


def boxes_for(x: np.ndarray, q: int) -> list[np.ndarray] | None:
    """Boxes of rows for ``nearest`` against q neurons, where they save work."""
    return merging._boxes(x, 1024) if x.shape[1] <= 3 and q >= 64 and len(x) * q >= 1 << 22 else None


def nearest(x: np.ndarray, w: np.ndarray, block: int = 4096, boxes: list[np.ndarray] | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(winner, distance) of every row; no full distance matrix is kept.

    Against many neurons on few axes the rows are cut into boxes (``boxes_for``,
    which a caller with the same rows again can hand over): those of a box meet
    only neurons that can be nearest to some place in it.
    """
    win, dist = np.zeros(len(x), np.int64), np.zeros(len(x))
    boxes = boxes_for(x, len(w)) if boxes is None else boxes
    if boxes is not None:
        for rows in boxes:
            part = x[rows]
            lo, hi = part.min(axis=0), part.max(axis=0)
            least, most = np.zeros(len(w)), np.zeros(len(w))
            for j in range(x.shape[1]):
                below, above = lo[j] - w[:, j], w[:, j] - hi[j]
                least += np.maximum(np.maximum(below, above), 0.0) ** 2
                most += np.maximum(hi[j] - w[:, j], w[:, j] - lo[j]) ** 2
            near = np.flatnonzero(least <= most.min() * (1 + 1e-9))
            step = max(1, 4_000_000 // len(near))
            for at in range(0, len(rows), step):
                win[rows[at : at + step]] = near[merging._sq(part[at : at + step], w[near]).argmin(axis=1)]
        for lo in range(0, len(x), 100_000):
            dist[lo : lo + 100_000] = np.sqrt(((x[lo : lo + 100_000] - w[win[lo : lo + 100_000]]) ** 2).sum(axis=1))
        return win, dist
    if len(x) * len(w) >= 1 << 22:
        # Single products leave the neurons that can be nearest, differences decide.
        mid = (w.min(axis=0) + w.max(axis=0)) / 2
        z, v = x - mid, w - mid
        vv = np.einsum("ij,ij->i", v, v)
        right = np.column_stack([-2 * v, vv]).T.astype(np.float32)
        slack = 8 * (x.shape[1] + 4) * np.finfo(np.float32).eps * (vv.max() + np.einsum("ij,ij->i", z, z).max())
        step = max(1, 4_000_000 // len(w))
        for lo in range(0, len(x), step):
            part = x[lo : lo + step]
            d2 = np.column_stack([z[lo : lo + step], np.ones(len(part))]).astype(np.float32) @ right
            r, c = np.nonzero(d2 <= d2.min(axis=1, keepdims=True) + np.float32(slack))
            win[lo : lo + step] = c[merging.first_of_each(r, merging._by_differences(part, w, r, c), c, 1)]
            dist[lo : lo + step] = np.sqrt(((part - w[win[lo : lo + step]]) ** 2).sum(axis=1))
        return win, dist
    ww = (w * w).sum(axis=1)
    for lo in range(0, len(x), block):
        part = x[lo : lo + block]
        d2 = ww - 2 * part @ w.T
        # The product form loses digits: settle near ties by differences.
        close = d2.argmin(axis=1)[:, None]
        if len(w) > 1:
            d2[np.arange(len(part)), close[:, 0]] = np.inf
            close = np.column_stack([close, d2.argmin(axis=1)])
        exact = np.sqrt(((part[:, None, :] - w[close]) ** 2).sum(axis=2))
        swap = (exact[:, 1:] < exact[:, :1])[:, 0] | ((exact[:, -1] == exact[:, 0]) & (close[:, -1] < close[:, 0])) if close.shape[1] > 1 else np.zeros(len(part), bool)
        pick = swap.astype(int)
        rows = np.arange(len(part))
        win[lo : lo + block], dist[lo : lo + block] = close[rows, pick], exact[rows, pick]
    return win, dist


def batch_fit(sums_of, w: np.ndarray, rounds: int = 10, grow: int = 0) -> np.ndarray:
    """Order-free training: ``sums_of(w)`` gives (n, sum of x, sum of distance)
    by neuron over all data; neurons move to means, ``grow`` split each round."""
    for _ in range(rounds):
        n, total, strain = sums_of(w)
        hit = n > 0
        w = w.copy()
        w[hit] = total[hit] / n[hit, None]
        worst = [i for i in np.argsort(-strain, kind="stable")[:grow] if n[i] > 1]
        if worst:
            step = np.maximum(np.abs(w[worst]) * 1e-3, 1e-4)
            w = np.vstack([w, w[worst] + step])
    return w
