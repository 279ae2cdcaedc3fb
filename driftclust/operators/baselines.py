"""Comparison algorithms, each on one chunk: (x, k, seed, options) -> labels.

Plain NumPy. Where a publication leaves a detail open the choice made here is
named in the docstring. Those that need the number of clusters take k; the
others ignore it.
"""

from __future__ import annotations

import numpy as np

from ..params import Params
from . import growing_map, merging
from .growing_map import sq_distances


def _compact(labels: np.ndarray) -> np.ndarray:
    return np.unique(labels, return_inverse=True)[1]


def kpp_seeds(x: np.ndarray, k: int, rng: np.random.Generator, weight: np.ndarray | None = None) -> np.ndarray:
    """k-means++ seeding: each next seed with chance in proportion to its squared distance."""
    w = np.ones(len(x)) if weight is None else weight
    first = int(rng.choice(len(x), p=w / w.sum()))
    away = lambda i: merging._sq(x, x[i : i + 1])[:, 0]
    picked, d = [first], away(first)
    while len(picked) < min(k, len(x)):
        mass = d * w
        i = int(rng.choice(len(x), p=mass / mass.sum())) if mass.sum() > 0 else int(rng.integers(len(x)))
        picked.append(i)
        d = np.minimum(d, away(i))
    return x[picked].copy()


def lloyd(x: np.ndarray, centres: np.ndarray, rounds: int = 25, weight: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(labels, centres) after at most ``rounds`` rounds; empty clusters stay put."""
    w = np.ones(len(x)) if weight is None else weight
    c, label = centres.astype(float).copy(), None
    boxes = growing_map.boxes_for(x, len(c))
    for _ in range(rounds):
        new, _ = growing_map.nearest(x, c, boxes=boxes)
        if label is not None and (new == label).all():
            break
        label = new
        mass = np.bincount(label, weights=w, minlength=len(c))
        for j in range(x.shape[1]):
            total = np.bincount(label, weights=w * x[:, j], minlength=len(c))
            c[:, j] = np.where(mass > 0, total / np.maximum(mass, 1e-300), c[:, j])
    return growing_map.nearest(x, c, boxes=boxes)[0], c


def kmeans(x, k, seed=1, rounds=25, init="kpp"):
    rng = np.random.default_rng(seed)
    start = kpp_seeds(x, k, rng) if init == "kpp" else x[rng.permutation(len(x))[:k]].copy()
    return lloyd(x, start, rounds)[0]


def agglomerate(centres: np.ndarray, k: int) -> np.ndarray:
    """Join the closest centres (single link) until k groups are left."""
    n = len(centres)
    group = np.arange(n)
    d = sq_distances(centres, centres)
    for i, j in zip(*np.unravel_index(np.argsort(d, axis=None, kind="stable"), d.shape), strict=True):
        if len(np.unique(group)) <= k:
            break
        if group[i] != group[j]:
            group[group == max(group[i], group[j])] = min(group[i], group[j])
    return _compact(group)


def multi_center(x, k, seed=1, m=0):
    """Many k-means centres, the closest joined until k are left."""
    m = min(len(x), m or max(4 * k, 12))
    label, c = lloyd(x, kpp_seeds(x, m, np.random.default_rng(seed)))
    return agglomerate(c, k)[label]


def cf_leaves(x: np.ndarray, threshold: float, most: int = 200) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(n, sum, square sum) of cluster features: a point joins the nearest leaf
    whose radius stays within the threshold; with more than ``most`` leaves the
    threshold grows by half and leaves are inserted again."""
    n, s, q = np.zeros(0), np.zeros((0, x.shape[1])), np.zeros(0)
    items = [(1.0, r, float(r @ r)) for r in x]
    while True:
        n, s, q = np.zeros(most + 1), np.zeros((most + 1, x.shape[1])), np.zeros(most + 1)
        used, full = 0, False
        for i, (ni, si, qi) in enumerate(items):
            if used:
                c = s[:used] / n[:used, None]
                j = int(((c - si / ni) ** 2).sum(axis=1).argmin())
                nn, ss, qq = n[j] + ni, s[j] + si, q[j] + qi
                if max(qq / nn - float((ss / nn) @ (ss / nn)), 0.0) <= threshold**2:
                    n[j], s[j], q[j] = nn, ss, qq
                    continue
            if used == most:
                items = [(float(n[j]), s[j].copy(), float(q[j])) for j in range(used)] + items[i:]
                threshold, full = threshold * 1.5, True
                break
            n[used], s[used], q[used] = ni, si, qi
            used += 1
        if not full:
            return n[:used], s[:used], q[:used]


def birch(x, k, seed=1, threshold=0.05):
    """Cluster features of all points, their centres clustered with weights."""
    n, s, _ = cf_leaves(x, threshold)
    c = s / n[:, None]
    leaf, _ = growing_map.nearest(x, c)
    return lloyd(c, kpp_seeds(c, k, np.random.default_rng(seed), n), weight=n)[0][leaf]


def coreset(x: np.ndarray, w: np.ndarray, m: int, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
    """At most m weighted points: k-means++ seeds with the weight of their cells."""
    if len(x) <= m:
        return x, w
    c = kpp_seeds(x, m, rng, w)
    return c, np.bincount(growing_map.nearest(x, c)[0], weights=w, minlength=len(c))


def coreset_kmeans(x, k, seed=1, m=0, bucket=0):
    """Merge and reduce: buckets become coresets, pairs of equal rank are reduced again."""
    rng = np.random.default_rng(seed)
    m = m or max(20 * k, 100)
    bucket = bucket or m * 2
    held: dict[int, tuple[np.ndarray, np.ndarray]] = {}
    for lo in range(0, len(x), bucket):
        part, rank = coreset(x[lo : lo + bucket], np.ones(len(x[lo : lo + bucket])), m, rng), 0
        while rank in held:
            old = held.pop(rank)
            part, rank = coreset(np.vstack([old[0], part[0]]), np.append(old[1], part[1]), m, rng), rank + 1
        held[rank] = part
    px, pw = np.vstack([p for p, _ in held.values()]), np.concatenate([w for _, w in held.values()])
    keep = pw > 0
    _, c = lloyd(px[keep], kpp_seeds(px[keep], k, rng, pw[keep]), weight=pw[keep])
    return growing_map.nearest(x, c)[0]


def coop_penal_learning(x, k=0, seed=1, k0=0, rate=0.05, passes=3):
    """Cooperative and penalised competition: the winner by frequency-weighted
    distance moves; seeds within its reach cooperate, the rest of those near the
    winner are pushed off; coinciding seeds are one cluster."""
    rng = np.random.default_rng(seed)
    k0 = min(len(x), k0 or max(2 * k, 10))
    c, wins = x[rng.permutation(len(x))[:k0]].copy(), np.ones(k0)
    for _ in range(passes):
        for i in rng.permutation(len(x)):
            d = ((c - x[i]) ** 2).sum(axis=1)
            v = int((wins / wins.sum() * d).argmin())
            wins[v] += 1
            reach = ((c - c[v]) ** 2).sum(axis=1)
            inside = reach <= d[v]
            coop = inside & (d <= d[v] * 4)
            penal = inside & ~coop
            c[coop] += rate * (x[i] - c[coop])
            if penal.any():
                c[penal] -= rate * 0.05 * (x[i] - c[penal])
    span = float(np.ptp(x, axis=0).max()) or 1.0
    group, left = np.full(k0, -1), 0
    for a in range(k0):
        if group[a] < 0:
            same = (group < 0) & (((c - c[a]) ** 2).sum(axis=1) <= (0.02 * span) ** 2)
            group[same], left = left, left + 1
    return _compact(group[growing_map.nearest(x, c)[0]])


def _merged_prototypes(x, w, p: Params):
    """Merge prototypes' cells over all pairs; k by gap and separability."""
    cell, _ = growing_map.nearest(x, w)
    cells = merging.cell_stats(x, cell, len(w))
    cross = merging.cross_pairs(merging.neighbours(x, p.s), cell, len(w))
    t = merging.run(cells, np.zeros(len(w), np.int64), [], cross, p.s, Params(schedule="all_pairs", s=p.s))
    return t.groups(merging.best_k(np.array(t.k), np.array(t.log_theta), np.array(t.omega)))[cell]


def self_adaptive_prototypes(x, k=0, seed=1, rate=0.05, m=0):
    """Competitive learning that adds prototypes where the winner's load is
    highest until the distribution is covered, then merges over all pairs."""
    rng = np.random.default_rng(seed)
    m = min(m or 30, max(2, len(x) // 4))
    c = x[rng.permutation(len(x))[:2]].copy()
    for _ in range(m - 2):
        part = x[rng.integers(0, len(x), min(len(x), 400))]
        for v in part:
            j = int(((c - v) ** 2).sum(axis=1).argmin())
            c[j] += rate * (v - c[j])
        cell, dist = growing_map.nearest(x, c)
        load = np.bincount(cell, weights=dist, minlength=len(c))
        mine = np.flatnonzero(cell == int(load.argmax()))
        c = np.vstack([c, x[mine[int(dist[mine].argmax())]]])
    return _compact(_merged_prototypes(x, c, Params()))


def _to_near(x, near):
    d = np.zeros(near.shape)
    for lo in range(0, len(x), 100_000):
        d[lo : lo + 100_000] = ((x[lo : lo + 100_000, None, :] - x[near[lo : lo + 100_000]]) ** 2).sum(axis=2)
    return d


def knn_density(x, s, near=None):
    """(density, neighbours): sum of exp(-distance) over the s nearest; near: those,
    where they are known."""
    near = merging.neighbours(x, s) if near is None else near
    d = np.sqrt(_to_near(x, near))
    return np.exp(-d / (d.mean() or 1.0)).sum(axis=1), near


def _denser(x, rho, block=64):
    """(nearest denser point, its distance, points by falling density); the
    densest points at itself. Ties in distance to the denser.

    Rows are cut into boxes at medians. Those of a box look into some boxes beside
    it; one that has a denser point no further than all other boxes is done, the
    rest look into more boxes, the nearest first, that hold a denser point.
    """
    order = np.lexsort((np.arange(len(x)), -rho))
    rank = np.zeros(len(x), np.int64)
    rank[order] = np.arange(len(x))
    parent, d2 = np.arange(len(x)), np.full(len(x), np.inf)
    around = merging.Boxes(x, block)
    boxes = around.rows
    top = np.array([rank[b].min() for b in boxes])
    beside = min(len(boxes), 16)

    def look(rows, seen):
        at = np.concatenate([boxes[b] for b in seen])
        at = at[np.argsort(rank[at])]
        d = merging._sq(x[rows], x[at])
        d[rank[at][None, :] >= rank[rows][:, None]] = np.inf
        j = d.argmin(axis=1)
        got = d[np.arange(len(rows)), j]
        better = (got < d2[rows]) | ((got == d2[rows]) & np.isfinite(got) & (rank[at[j]] < rank[parent[rows]]))
        d2[rows[better]], parent[rows[better]] = got[better], at[j[better]]

    for mine, some, far, edge in around.seen_from(x, block, beside):
        cut = np.argpartition(far, beside - 1)
        look(mine, some[cut[:beside]])
        edge = min(edge, far[cut[beside:]].min(initial=np.inf))
        for i in mine[~(d2[mine] * (1 + 1e-9) < edge)].tolist():
            own = around.apart(x[i], x[i])
            left = np.flatnonzero(top < rank[i])
            left = left[np.argsort(own[left], kind="stable")]
            at, step = 0, 4
            while at < len(left) and own[left[at]] <= d2[i] * (1 + 1e-9):
                look(np.array([i]), left[at : at + step])
                at, step = at + step, step * 2
    delta = np.sqrt(d2)
    delta[order[0]] = np.sqrt(((x - x[order[0]]) ** 2).sum(axis=1)).max()
    return parent, delta, order


def _row_blocks(x, values: int = 4_000_000):
    """(place, squared distances to all rows) for blocks of rows."""
    step = max(1, values // len(x))
    for lo in range(0, len(x), step):
        yield lo, sq_distances(x[lo : lo + step], x)


def _ranges(around: merging.Boxes, a: int) -> tuple[np.ndarray, np.ndarray]:
    """Bounds of the squared distances between rows of box a and of each box."""
    low, high = around.low[:, a], around.high[:, a]
    most = sum(np.maximum(top - lo, hi - bottom) ** 2 for bottom, top, lo, hi in zip(around.low, around.high, low, high, strict=True))
    return around.apart(low, high) * (1 - 1e-9), most * (1 + 1e-9)


def _parts_of(boxes: list[np.ndarray], some: np.ndarray, n: int, values: int = 2_000_000):
    """The rows of some boxes in parts that give so many distances with n rows."""
    seen = np.concatenate([boxes[b] for b in some]) if len(some) else np.zeros(0, np.int64)
    step = max(1, values // n)
    for lo in range(0, len(seen), step):
        yield seen[lo : lo + step]


def pair_quantile(x: np.ndarray, q: float, bins: int = 1 << 16, block: int = 64) -> float:
    """``np.quantile`` of the squared distances of all pairs, exact, without
    holding them: bounds between large boxes tell where it lies, pairs of small
    boxes that can be there are counted in bins, then the values of the bins at
    the rank are held."""
    total = len(x) * (len(x) - 1) // 2
    rank = q * (total - 1)
    k = int(rank)
    ends = [k, min(k + 1, total - 1)]
    around = merging.Boxes(x, max(block, len(x) // 1024))
    size = np.array([len(b) for b in around.rows])
    bounds = [(least[a:], most[a:], np.append(size[a] * (size[a] - 1) // 2, size[a] * size[a + 1 :])) for a in range(len(size)) for least, most in [_ranges(around, a)]]
    least, most, pairs = (np.concatenate(v) for v in zip(*bounds, strict=True))
    lo, hi = (float(v[o][np.searchsorted(np.cumsum(pairs[o]), e, side="right")]) for v, e in ((least, ends[0]), (most, ends[1])) for o in [np.argsort(v, kind="stable")])
    around = merging.Boxes(x, block)
    size = np.array([len(b) for b in around.rows])

    def between():
        """(number of pairs below lo, distances from lo to hi, their bins)."""
        for a, rows in enumerate(around.rows):
            least, most = _ranges(around, a)
            later = np.arange(len(size)) > a
            below = len(rows) * int(size[later & (most < lo)].sum())
            found = [merging._sq(x[rows], x[rows])[np.triu_indices(len(rows), 1)]]
            found += [merging._sq(x[rows], x[seen]).reshape(-1) for seen in _parts_of(around.rows, np.flatnonzero(later & (most >= lo) & (least <= hi)), len(rows))]
            for d in found:
                v = d[(d >= lo) & (d <= hi)]
                yield below + int((d < lo).sum()), v, np.minimum(((v - lo) * (bins / ((hi - lo) or 1.0))).astype(np.int64), bins - 1)
                below = 0

    less, count = 0, np.zeros(bins, np.int64)
    for n, _, b in between():
        less += n
        count += np.bincount(b, minlength=bins)
    below = less + np.cumsum(count)
    first, last = (int(np.searchsorted(below, e, side="right")) for e in ends)
    held: dict[float, int] = {}
    for _, v, b in between():
        for value, n in zip(*np.unique(v[(b == first) | (b == last)], return_counts=True), strict=True):
            held[value] = held.get(value, 0) + int(n)
    values = np.array(sorted(held))
    seen = np.cumsum([held[v] for v in values]) + (int(below[first - 1]) if first else less)
    a, b = (values[int(np.searchsorted(seen, e, side="right"))] for e in ends)
    return float(np.quantile([a, b], rank - k))


def count_within(x: np.ndarray, d2: float, block: int = 64) -> np.ndarray:
    """How many rows, itself among them, are at less than the squared distance d2 of
    each row; boxes that are within it, or beyond it, as a whole aren't looked into."""
    around, out = merging.Boxes(x, block), np.zeros(len(x))
    size = np.array([len(b) for b in around.rows])
    for a, rows in enumerate(around.rows):
        least, most = _ranges(around, a)
        out[rows] = size[most < d2].sum()
        for seen in _parts_of(around.rows, np.flatnonzero((most >= d2) & (least < d2)), len(rows)):
            out[rows] += (merging._sq(x[rows], x[seen]) < d2).sum(axis=1)
    return out


def density_peaks(x, k, seed=1, density="cutoff", quantile=0.02, s=10):
    """Peaks by density times distance to a denser point; others follow that point.

    density: cutoff (points within the quantile of all distances), gauss, or
    fuzzy_knn (sum of exp(-distance) over s neighbours)."""
    if density == "fuzzy_knn":
        rho = knn_density(x, s)[0]
    else:
        dc2 = pair_quantile(x, quantile) if len(x) > 1 else 0.0
        rho = count_within(x, dc2) - 1.0 if density == "cutoff" else np.concatenate([np.exp(-d2 / (dc2 or 1.0)).sum(axis=1) for _, d2 in _row_blocks(x)])
    parent, delta, order = _denser(x, rho)
    label = np.full(len(x), -1)
    label[np.argsort(-rho * delta, kind="stable")[:k]] = np.arange(min(k, len(x)))
    if label[order[0]] < 0:
        label[order[0]] = 0
    for i in order.tolist():
        if label[i] < 0:
            label[i] = label[parent[i]]
    return label


def local_peaks(x, k=0, seed=1, s=10, near=None):
    """Local density peaks start subclusters, points follow the nearest denser
    neighbour, and subclusters are merged by gap and separability."""
    rho, near = knn_density(x, s, near)
    label = np.arange(len(x))
    order = np.lexsort((np.arange(len(x)), -rho))
    up = (rho[near] > rho[:, None]) | ((rho[near] == rho[:, None]) & (near < label[:, None]))
    some = up.any(axis=1)
    to = np.where(some, near[label, np.where(up, _to_near(x, near), np.inf).argmin(axis=1)], label).tolist() if near.shape[1] else label.tolist()
    for i in order.tolist():
        label[i] = label[to[i]]
    label = _compact(label)
    q = int(label.max()) + 1
    cells = merging.cell_stats(x, label, q)
    t = merging.run(cells, np.zeros(q, np.int64), [], merging.cross_pairs(near, label, q), s, Params(schedule="all_pairs"))
    return _compact(t.groups(merging.best_k(np.array(t.k), np.array(t.log_theta), np.array(t.omega)))[label])


def density_soinn(x, k=0, seed=1, age=50, period=200):
    """Two nearest nodes compete; a point beyond their reach becomes a node, else
    it pulls them and renews their edge; old edges and idle nodes go at times;
    linked nodes are a cluster."""
    rng = np.random.default_rng(seed)
    order = rng.permutation(len(x))
    space, hits, n = np.zeros((x.shape[1], 1024)), np.ones(1024), 2  # by axis
    space[:, :2] = x[order[:2]].T
    #: For each node its linked nodes, and the age of each link.
    links: list[dict[int, int]] = [{}, {}]

    def away(v):
        d = space[:, :n] - v[:, None]
        d *= d
        return np.add.reduce(d, axis=0)

    def reach(a):
        if links[a]:
            g = space[:, list(links[a])] - space[:, a : a + 1]
            g *= g
            return np.add.reduce(g, axis=0).max()
        g = away(space[:, a])
        g[a] = np.inf
        return g.min()

    for count, i in enumerate(order.tolist(), 1):
        d = away(x[i])
        a = int(d.argmin())
        to_a, d[a] = d[a], np.inf
        b = int(d.argmin())
        if to_a > reach(a) or d[b] > reach(b):
            if n == len(hits):
                space, hits = np.hstack([space, np.zeros_like(space)]), np.append(hits, np.ones(n))
            space[:, n], hits[n] = x[i], 1.0
            links.append({})
            n += 1
        else:
            hits[a] += 1
            space[:, a] += (x[i] - space[:, a]) / hits[a]
            for o, old in list(links[a].items()):
                if old + 1 > age:
                    del links[a][o], links[o][a]
                else:
                    links[a][o] = links[o][a] = old + 1
            links[a][b] = links[b][a] = 0
        if count % period == 0 and n > 4:
            keep = [v for v in range(n) if links[v] or hits[v] > 1]
            if len(keep) >= 2:
                number = {o: m for m, o in enumerate(keep)}
                links = [{number[o]: v for o, v in links[m].items()} for m in keep]
                n = len(keep)
                space[:, :n], hits[:n] = space[:, keep], hits[keep]
    group = np.full(n, -1)
    for v in range(n):
        stack = [v] if group[v] < 0 else []
        while stack:
            at = stack.pop()
            if group[at] < 0:
                group[at] = v
                stack += links[at]
    return _compact(group[growing_map.nearest(x, np.ascontiguousarray(space[:, :n].T))[0]])


def three_way(x, k=0, seed=1, s=10, core=0.5, near=None):
    """Core, border and outside: the denser share of points forms clear-edged
    cores through mutual neighbours, the rest follow the nearest core point."""
    rho, near = knn_density(x, s, near)
    is_core = rho >= np.quantile(rho, 1 - core)
    one, two = np.repeat(np.arange(len(x)), near.shape[1]), near.reshape(-1)
    both = np.isin(one * len(x) + two, two * len(x) + one) & is_core[one] & is_core[two]
    edge, mutual = np.searchsorted(one[both], np.arange(len(x) + 1)).tolist(), two[both].tolist()
    label = np.full(len(x), -1)
    c = 0
    for i in np.flatnonzero(is_core).tolist():
        if label[i] >= 0:
            continue
        stack = [i]
        label[i] = c
        while stack:
            at = stack.pop()
            for j in mutual[edge[at] : edge[at + 1]]:
                if label[j] < 0:
                    label[j] = c
                    stack.append(j)
        c += 1
    cores = np.flatnonzero(is_core)
    rest = np.flatnonzero(~is_core)
    if len(rest):
        label[rest] = label[merging.nearest_in(x[rest], x[cores], cores, 1)[0][:, 0]]
    return _compact(label)


def granule_tree(x, k=0, seed=1, granules=0):
    """Micro-granules by fast partitioning, linked into a minimum spanning tree
    whose links are cut at the largest relative jump in length."""
    m = min(len(x), granules or max(8, int(np.sqrt(len(x)))))
    label, c = lloyd(x, kpp_seeds(x, m, np.random.default_rng(seed)), rounds=5)
    d = sq_distances(c, c)
    inside, links = {0}, []
    best, via = d[0].copy(), np.zeros(m, np.int64)
    while len(inside) < m:
        best_out = np.where([i in inside for i in range(m)], np.inf, best)
        j = int(best_out.argmin())
        links.append((float(np.sqrt(best_out[j])), int(via[j]), j))
        inside.add(j)
        closer = d[j] < best
        best[closer], via[closer] = d[j][closer], j
    links.sort()
    size = np.array([v for v, _, _ in links])
    cut = len(links)
    if len(size) > 2:
        jump = size[1:] / np.maximum(size[:-1], 1e-12)
        half = len(jump) // 2
        cut = half + int(jump[half:].argmax()) + 1
    group = np.arange(m)
    for _, a, b in links[:cut]:
        group[group == max(group[a], group[b])] = min(group[a], group[b])
    return _compact(group[label])


def growing_cells(x, k=0, seed=1, rho=100, least=0.02):
    """One connected growing net; neurons that win few objects are removed, the
    parts that remain are clusters."""
    p = Params(subnets=1, join=False, rho=rho, seed=seed)
    m = growing_map.fit(x, p)
    cell, _ = growing_map.nearest(x, m.w)
    share = np.bincount(cell, minlength=m.q) / len(x)
    gone = share < least / max(1, np.sqrt(m.q))
    if gone.any() and not gone.all():
        m.drop(gone)
        cell, _ = growing_map.nearest(x, m.w)
    group = np.arange(m.q)
    for a, b in m.edges():
        group[group == max(group[a], group[b])] = min(group[a], group[b])
    return _compact(group[cell])


def grid_som(x, k=0, seed=1, rows=4, cols=4, rounds=12):
    """Fixed grid, batch rounds with shrinking neighbourhood; cells are clusters."""
    grid = np.array([(i, j) for i in range(rows) for j in range(cols)], float)
    w = x[np.random.default_rng(seed).integers(0, len(x), len(grid))].astype(float).copy()
    for r in range(rounds):
        radius = max(0.5, max(rows, cols) / 2 * (1 - r / rounds))
        h = np.exp(-sq_distances(grid, grid) / (2 * radius**2))
        cell, _ = growing_map.nearest(x, w)
        n = np.bincount(cell, minlength=len(grid))
        s = np.zeros_like(w)
        np.add.at(s, cell, x)
        w = (h @ s) / np.maximum(h @ n, 1e-12)[:, None]
    return _compact(growing_map.nearest(x, w)[0])


def two_phase(x, k=0, seed=1):
    """m microclusters, merged over all pairs."""
    m = min(len(x), max(8, int(np.sqrt(len(x)))))
    return _compact(_merged_prototypes(x, lloyd(x, kpp_seeds(x, m, np.random.default_rng(seed)))[1], Params()))


def grid_density_peaks(x, k=3, seed=1, width=0.1, adaptive=False):
    """Density peaks on grid-cell counts, as kept for streams; adaptive merges
    peaks whose cells adjoin."""
    key = np.floor(x / width).astype(np.int64)
    cells, cell, n = np.unique(key, axis=0, return_inverse=True, return_counts=True)
    cell = cell.reshape(-1)
    centre = (cells + 0.5) * width
    parent, delta, order = _denser(centre, n + np.arange(len(n)) * -1e-9)
    peaks = np.argsort(-(n * delta), kind="stable")[: (2 * k if adaptive else k)]
    label = np.full(len(cells), -1)
    label[peaks] = np.arange(len(peaks))
    if label[order[0]] < 0:
        label[order[0]] = 0
    for i in order.tolist():
        if label[i] < 0:
            label[i] = label[parent[i]]
    if adaptive:
        for a in range(len(cells)):
            close = np.flatnonzero(np.abs(cells - cells[a]).max(axis=1) <= 1)
            for b in close.tolist():
                if label[a] != label[b] and min(n[a], n[b]) >= 0.5 * min(n[label == label[a]].max(), n[label == label[b]].max()):
                    label[label == max(label[a], label[b])] = min(label[a], label[b])
    return _compact(label[cell])


#: Methods that start from the neighbours of all points -> how many.
FROM_NEIGHBOURS = {"local_peaks": 10, "three_way": 10}

#: Name -> (function, whether it needs k, whether the comparison tables name it).
METHODS = {
    "birch": (birch, True, True),
    "coreset_kmeans": (coreset_kmeans, True, True),
    "coop_penal_learning": (coop_penal_learning, False, True),
    "self_adaptive_prototypes": (self_adaptive_prototypes, False, True),
    "granule_tree": (granule_tree, False, True),
    "density_soinn": (density_soinn, False, True),
    "local_peaks": (local_peaks, False, True),
    "three_way": (three_way, False, True),
    "kmeans": (kmeans, True, False),
    "multi_center": (multi_center, True, False),
    "density_peaks": (density_peaks, True, False),
    "fuzzy_density_peaks": (lambda x, k, seed=1: density_peaks(x, k, seed, "fuzzy_knn"), True, False),
    "growing_cells": (growing_cells, False, False),
    "grid_som": (grid_som, False, False),
    "two_phase": (two_phase, False, False),
    "stream_density_peaks": (grid_density_peaks, True, False),
    "adaptive_density_peaks": (lambda x, k, seed=1: grid_density_peaks(x, k, seed, adaptive=True), True, False),
}
