"""Where the neurons of a large map are, so that few are compared with each object.

Space is cut into boxes at medians of the neurons' places. Neurons may move, and
more may be added. What is found is exact: the boxes that were not looked into tell
how far it is complete, and rows that need more are compared with all neurons.
"""

from __future__ import annotations

import numpy as np

#: Neurons that a box holds; those that find no place in theirs are always compared.
SLOTS = 12
#: Boxes known to each box as the nearest to it, and of these looked into for a row.
KNOWN, SEEN = 48, 12
#: Axes beyond which too many boxes meet.
MOST_AXES = 3


class Places:
    """Boxes of the rows of w (neurons)."""

    def __init__(self, w: np.ndarray):
        self.built = len(w)
        self._cut(w, max(0, int(np.log2(max(1.0, len(w) / 3)))))
        self._near()
        n = len(self.low)
        self.slots = np.full((n, SLOTS), -1)
        self.cell, self.slot = np.full(2 * len(w), -1), np.full(2 * len(w), -1)
        cells = self._cells(w)
        order = np.argsort(cells, kind="stable")
        place = np.arange(len(w)) - np.searchsorted(cells[order], cells[order])
        kept = place < SLOTS
        self.cell[: len(w)] = cells
        self.slot[order[kept]] = cells[order[kept]] * SLOTS + place[kept]
        self.slots.reshape(-1)[self.slot[order[kept]]] = order[kept]
        self.over: set[int] = set(order[~kept].tolist())
        self.most_over = 32 + len(w) // 500 + 2 * len(self.over)

    def worn(self, q: int) -> bool:
        """Whether it should be built anew for q neurons."""
        return q > 1.3 * self.built or len(self.over) > self.most_over

    def _cut(self, w: np.ndarray, depth: int) -> None:
        """Cuts and boxes (low, high) of a full tree; a box has its lower ends."""
        d = w.shape[1]
        held = np.resize(w, (-(-len(w) // 2**depth) * 2**depth, d))[None]
        low, high = np.full((1, d), -np.inf), np.full((1, d), np.inf)
        axes, cuts = [], []
        for _ in range(depth):
            axis = np.ptp(held, axis=1).argmax(axis=1)
            value = np.take_along_axis(held, axis[:, None, None], 2)[:, :, 0]
            order, half = np.argsort(value, axis=1, kind="stable"), held.shape[1] // 2
            held = np.take_along_axis(held, order[:, :, None], 1).reshape(2 * len(held), half, d)
            cut = np.take_along_axis(value, order[:, half - 1 : half + 1], 1).mean(axis=1)
            axes.append(axis)
            cuts.append(cut)
            low, high = np.repeat(low, 2, axis=0), np.repeat(high, 2, axis=0)
            each = np.arange(len(axis))
            high[2 * each, axis] = cut
            low[2 * each + 1, axis] = cut
        self.low, self.high, self.axes, self.cuts = low, high, axes, cuts

    def _near(self) -> None:
        """For each box the nearest others and itself, and what the rest exceed."""
        n, group = len(self.low), 64
        known = min(KNOWN, n)
        self.near, self.edge = np.zeros((n, known), np.int64), np.full(n, np.inf)
        for lo in range(0, n, group):
            mine = slice(lo, lo + group)
            some, beyond = np.arange(n), np.inf
            if n > 8 * group:
                far = _apart(self.low[mine].min(axis=0), self.high[mine].max(axis=0), self.low, self.high)
                cut = np.argpartition(far, 8 * group)
                some, beyond = cut[: 8 * group], far[cut[8 * group]]
            far = _apart(self.low[mine, None], self.high[mine, None], self.low[some], self.high[some])
            if len(some) > known:
                cut = np.argpartition(far, known, axis=1)
                self.near[mine] = some[cut[:, :known]]
                self.edge[mine] = np.minimum(beyond, np.take_along_axis(far, cut[:, known : known + 1], 1)[:, 0])
            else:
                self.near[mine] = some

    def _cells(self, x: np.ndarray) -> np.ndarray:
        at, rows = np.zeros(len(x), np.int64), np.arange(len(x))
        for axis, cut in zip(self.axes, self.cuts, strict=True):
            at = 2 * at + (x[rows, axis[at]] >= cut[at])
        return at

    def move(self, ids: np.ndarray, x: np.ndarray) -> None:
        """Neurons ids, each once, are at x now."""
        held = self.cell[ids]
        away = (held < 0) | ((x < self.low[held]) | (x >= self.high[held])).any(axis=1)
        if not away.any():
            return
        ids, x = ids[away], x[away]
        cells, old, slots = self._cells(x), self.slot[ids], self.slots.reshape(-1)
        slots[old[old >= 0]] = -1
        self.cell[ids], self.slot[ids] = cells, -1
        if self.over:
            self.over.difference_update(ids.tolist())
        while len(ids):
            at = cells * SLOTS + (self.slots[cells] < 0).argmax(axis=1)
            full = slots[at] >= 0
            slots[at[~full]] = ids[~full]
            got = ~full & (slots[at] == ids)  # the last of those for one slot
            self.slot[ids[got]] = at[got]
            if full.any():
                self.over.update(ids[full].tolist())
            left = ~(got | full)
            ids, cells = ids[left], cells[left]

    def few(self, x: np.ndarray, w: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(neurons, squared distances, limit): k near ones of each row by distance and
        number, -1 at inf where it isn't known that one is among the nearest; all
        others are at the limit or beyond."""
        own = self._cells(x)
        boxes, limit = self.near[own], self.edge[own]
        far = _apart(x[:, None], x[:, None], self.low[boxes], self.high[boxes])
        if boxes.shape[1] > SEEN:
            cut = np.argpartition(far, SEEN, axis=1)
            limit = np.minimum(limit, np.take_along_axis(far, cut[:, SEEN : SEEN + 1], 1)[:, 0])
            boxes = np.take_along_axis(boxes, cut[:, :SEEN], 1)
        near = self.slots[boxes].reshape(len(x), -1)
        if self.over:
            near = np.hstack([near, np.broadcast_to(np.array(sorted(self.over)), (len(x), len(self.over)))])
        d2 = square_gaps(w[near], x[:, None, :])
        d2[near < 0] = np.inf
        limit = limit * (1 - 1e-9)
        if d2.shape[1] > k:
            part = np.argpartition(d2, k, axis=1)[:, : k + 1]
            near, d2 = np.take_along_axis(near, part, 1), np.take_along_axis(d2, part, 1)
        order = np.lexsort((near, d2))
        near, d2 = np.take_along_axis(near, order, 1), np.take_along_axis(d2, order, 1)
        if d2.shape[1] > k:
            limit = np.minimum(limit, d2[:, k])
            near, d2 = near[:, :k], d2[:, :k]
        # An equal one of lower number may be among those left out.
        unknown = ~(d2 < limit[:, None])
        near[unknown], d2[unknown] = -1, np.inf
        return near, d2, limit


def _apart(a_low: np.ndarray, a_high: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Squared distances of boxes."""
    out = 0.0
    for j in range(low.shape[-1]):
        gap = np.maximum(np.maximum(low[..., j] - a_high[..., j], a_low[..., j] - high[..., j]), 0.0)
        out = out + gap * gap
    return out


def square_gaps(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Squared distances over the last axis, added up axis by axis."""
    out = 0.0
    for j in range(a.shape[-1]):
        gap = a[..., j] - b[..., j]
        out = out + gap * gap
    return out
