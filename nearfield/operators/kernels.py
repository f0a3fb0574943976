"""Numpy kernels of the searches: the k nearest of a block, and the spans of sorted lists.

Whatever shortens the work, the distances that come out are those of the metric's
own sum over the axes, and ties go to the smaller place.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from nearfield.functions.metrics import Metric

#: Pairs that one block computes at once: it stays in a core's cache.
CELLS = 1 << 17
#: Pairs that a span search gathers at once.
GATHERED = 1 << 19


def measured(metric: Metric, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The distances of rows that belong together."""
    return metric.cells(a, b) if len(a) else np.empty(0)


class Near:
    """The k nearest of fixed rows to each of others.

    For l2 a matrix product in single precision gives all squares up to rounding;
    every row that rounding could place among the k nearest is measured anew.
    For angles a product of unit vectors in double precision does the same.  Other
    metrics measure every pair.
    """

    def __init__(self, metric: Metric, values: np.ndarray):
        self.metric, self.values, self.boxes = metric, values, None
        self.product = metric.name == "l2" and len(values) > 0
        if self.product:
            self.centre = values.mean(axis=0)
            own = values - self.centre
            self.double = np.vstack((-2 * own.T, (own * own).sum(axis=1)[None, :]))
            self.single = self.double.astype(np.float32)
            self.largest = float(self.double[-1].max())
        self.turned = self._unit(values) if metric.name == "angular" and len(values) else None

    @staticmethod
    def _unit(a: np.ndarray) -> np.ndarray | None:
        """Rows of length one; None if a row has no direction."""
        norms = np.sqrt((a * a).sum(axis=1))
        return a / norms[:, None] if np.isfinite(norms).all() and (norms > np.sqrt(np.finfo(float).tiny)).all() else None

    def _rough(self, a: np.ndarray, single: bool) -> tuple[np.ndarray, np.ndarray]:
        """Squares less the row's own, and how far rounding may move any two of a row apart."""
        own = a - self.centre
        squares = (own * own).sum(axis=1)
        kind, table = (np.float32, self.single) if single else (np.float64, self.double)
        # The largest term of a product is at most the sum of both squares.
        slack = 4 * (a.shape[1] + 4) * np.finfo(kind).eps * (squares + self.largest)
        with np.errstate(over="ignore", invalid="ignore"):
            return np.hstack((own, np.ones((len(own), 1)))).astype(kind) @ table, slack

    def least(self, a: np.ndarray, k: int, apart: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Places and distances (rows by k at most); distances are infinite where there are fewer.

        ``apart`` marks pairs that don't count.
        """
        k = min(k, len(self.values))
        own = self._unit(a) if self.turned is not None and len(a) else None
        if own is not None:
            return self._least_angles(a, own, k, apart)
        if not self.product or not len(a):
            block = self.metric.block(a, self.values)
            if apart is not None:
                block[apart] = np.inf
            return _least_of(block, k)
        for single in (True, False):
            rough, slack = self._rough(a, single)
            if apart is not None:
                rough[apart] = np.inf
            kth = rough.min(axis=1) if k == 1 else np.partition(rough, k - 1, axis=1)[:, k - 1]
            flat = np.flatnonzero(rough <= (kth + slack).astype(rough.dtype)[:, None] if np.isfinite(kth).all() else ~(rough > (kth + slack)[:, None]))
            if len(flat) <= 8 * k * len(a) + 64:
                break
        row, col = np.divmod(flat, len(self.values))
        dist = measured(self.metric, a[row], self.values[col])
        if apart is not None:
            dist[apart[row, col]] = np.inf
        return first_of(row, col, dist, len(a), k)

    def nearest(self, a: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Place and distance of the nearest row to each of others, however many: by boxes where there are many on both sides."""
        if len(a) >= Boxes.GROUP and len(self.values) >= Boxes.ROWS and Boxes.fits(self.metric, a, self.values):
            if self.boxes is None:
                self.boxes = Boxes(self.metric, self.values)
            return self.boxes.nearest(a)
        step, place, dist = max(1, CELLS // max(1, len(self.values))), [np.empty(0, np.int64)], [np.empty(0)]
        for at in range(0, len(a), step):
            places, near = self.least(a[at : at + step], 1)
            place.append(places[:, 0])
            dist.append(near[:, 0])
        return np.concatenate(place), np.concatenate(dist)

    def _least_angles(self, a: np.ndarray, own: np.ndarray, k: int, apart: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
        """The angle falls with the cosine, and each cosine is off by a few roundings of terms of one at most."""
        rough = -own @ self.turned.T
        if apart is not None:
            rough[apart] = np.inf
        kth = rough.min(axis=1) if k == 1 else np.partition(rough, k - 1, axis=1)[:, k - 1]
        row, col = np.divmod(np.flatnonzero(rough <= (kth + 8 * (a.shape[1] + 4) * np.finfo(float).eps)[:, None]), len(self.values))
        dist = measured(self.metric, a[row], self.values[col])
        if apart is not None:
            dist[apart[row, col]] = np.inf
        return first_of(row, col, dist, len(a), k)

    def closer(self, a: np.ndarray, limits: np.ndarray) -> np.ndarray:
        """How many of the fixed rows are nearer than its limit to each of the others."""
        if not self.product or not len(a):
            return np.count_nonzero(self.metric.block(a, self.values) < limits[:, None], axis=1)
        rough, slack = self._rough(a, False)
        own = a - self.centre
        edge = np.where(limits > 0, limits, 0) ** 2 - (own * own).sum(axis=1)
        out = np.count_nonzero(rough < (edge - slack)[:, None], axis=1)
        # What rounding leaves open is measured.
        row, col = np.divmod(np.flatnonzero(np.abs(rough - edge[:, None]) <= slack[:, None]), len(self.values))
        near = measured(self.metric, a[row], self.values[col]) < limits[row]
        return out + np.bincount(row[near], minlength=len(a))


def _least_of(block: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    rows = np.arange(len(block))
    if k == 1 and block.shape[1]:
        at = block.argmin(axis=1)
        return at[:, None], block[rows, at][:, None]
    near = np.argsort(block, axis=1, kind="stable")[:, :k] if block.shape[1] else np.empty((len(block), 0), int)
    return near, np.take_along_axis(block, near, axis=1)


def first_of(row: np.ndarray, col: np.ndarray, dist: np.ndarray, rows: int, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Each row's k least (distance, place) of pairs listed in any order, as two tables."""
    order = np.lexsort((col, dist, row))
    row, col, dist = row[order], col[order], dist[order]
    starts = np.searchsorted(row, np.arange(rows))
    rank = np.arange(len(row)) - starts[row]
    fine = rank < k
    places, dists = np.zeros((rows, k), np.int64), np.full((rows, k), np.inf)
    places[row[fine], rank[fine]], dists[row[fine], rank[fine]] = col[fine], dist[fine]
    return places, dists


class Cells:
    """Fixed rows in cells as wide as a range: what is within the range of a row lies in its own cell or one beside it.

    Every metric whose distance is at least the difference on each axis may use it.
    """

    #: Axes that are cut, and most cells of an axis.
    AXES, MOST = 4, 1 << 20

    def __init__(self, metric: Metric, values: np.ndarray, eps: float):
        self.metric, self.eps = metric, eps
        self.own = np.flatnonzero(np.isfinite(values).all(axis=1))
        values = values[self.own]
        # A little wider than the range, so that rounding moves no neighbour two cells away.
        self.width, self.least = eps * (1 + 1e-6), values.min(axis=0)
        cells = np.floor((values.max(axis=0) - self.least) / self.width) + 1
        fit = np.flatnonzero(cells <= self.MOST)
        axes = fit[np.argsort(-cells[fit], kind="stable")][: self.AXES]
        # Two more on either side, where rows beyond the fixed ones are put; the widest axis stands last.
        self.axes, self.cells = axes[::-1], cells[axes[::-1]].astype(np.int64) + 4
        while len(self.axes) and float(np.prod(self.cells.astype(float))) >= 2.0**62:
            self.axes, self.cells = self.axes[1:], self.cells[1:]
        keys = self._keys(values)
        order = np.argsort(keys, kind="stable")
        self.keys, self.own, self.values = keys[order], self.own[order], values[order]
        sides = np.array(np.meshgrid(*[(-1, 0, 1)] * max(0, len(self.axes) - 1), indexing="ij")).reshape(max(0, len(self.axes) - 1), -1).T
        self.steps = (sides * self._strides()[:-1]).sum(axis=1) if len(self.axes) > 1 else np.zeros(1, np.int64)

    @staticmethod
    def fits(metric: Metric, values: np.ndarray, eps: float) -> bool:
        return metric.name in ("l1", "l2", "linf") and eps > 0 and bool(np.isfinite(values).all(axis=1).any())

    def _strides(self) -> np.ndarray:
        return np.r_[np.cumprod(self.cells[::-1])[::-1][1:], 1].astype(np.int64)

    def _keys(self, values: np.ndarray) -> np.ndarray:
        if not len(self.axes):
            return np.zeros(len(values), np.int64)
        at = np.floor((values[:, self.axes] - self.least[self.axes]) / self.width)
        return ((np.clip(at, -2, self.cells - 3).astype(np.int64) + 2) * self._strides()).sum(axis=1)

    def within(self, values: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """(place of a fixed row, row, distance) of all pairs within the range, cell by cell."""
        known = np.flatnonzero(np.isfinite(values).all(axis=1))
        keys = self._keys(values[known])
        order = np.argsort(keys, kind="stable")
        rows, keys = known[order], keys[order]
        names, start, times = np.unique(keys, return_index=True, return_counts=True)
        beside = names[:, None] + self.steps[None, :]
        edge = 1 if len(self.axes) else 0
        first, last = np.searchsorted(self.keys, beside - edge, "left"), np.searchsorted(self.keys, beside + edge, "right")
        # One span of fixed rows for each cell and row of cells beside it; each row of the cell meets all of them.
        cell, step = np.nonzero(last > first)
        first, size = first[cell, step], (last - first)[cell, step]
        row = np.repeat(start[cell] - (np.cumsum(times[cell]) - times[cell]), times[cell]) + np.arange(int(times[cell].sum()))
        first, size = np.repeat(first, times[cell]), np.repeat(size, times[cell])
        for part in _parts(size):
            n = size[part]
            fixed = np.repeat(first[part] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
            own = np.repeat(rows[row[part]], n)
            dist = measured(self.metric, self.values[fixed], values[own])
            near = np.flatnonzero(dist <= self.eps)
            yield self.own[fixed[near]], own[near], dist[near]


class Boxes:
    """Fixed rows in leaves of a balanced tree, asked by groups of rows that lie together: a group measures the leaves that its bounds leave.

    For l2 alone.  Wide rows are placed by their first principal axes, which never
    lengthen a distance; what comes out is always the metric's own sum.
    """

    #: Rows of a leaf and of a group, leaves that are tried first, axes that place a row, and bounds that are held at once.
    LEAF, GROUP, FIRST, AXES, BOUNDS = 32, 128, 48, 6, 1 << 21
    #: Fewer fixed rows than these are measured faster by a product.
    ROWS = 1 << 13

    def __init__(self, metric: Metric, values: np.ndarray):
        self.metric, self.values = metric, values
        self.centre, self.basis = values.mean(axis=0), None
        if values.shape[1] > 8:
            some = values[:: max(1, len(values) >> 14)] - self.centre
            self.basis = np.linalg.eigh(some.T @ some)[1][:, -self.AXES :]
        coords = self._coords(values)
        # Leaves are filled up with a repeated row, which stands at a place beyond all rows.
        self.places = _halved(coords, self.LEAF)
        source = np.where(self.places < len(values), self.places, 0)
        self.sorted, coords = values[source], coords[source]
        self.low, self.high = coords.min(axis=1), coords.max(axis=1)

    @staticmethod
    def fits(metric: Metric, *sides: np.ndarray) -> bool:
        return metric.name == "l2" and all(len(v) > 0 and bool(np.isfinite(v).all()) and float(np.abs(v).max()) < 1e100 for v in sides)

    def _coords(self, values: np.ndarray) -> np.ndarray:
        return values - self.centre if self.basis is None else (values - self.centre) @ self.basis

    def _groups(self, a: np.ndarray, reach: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, float]]:
        """For each group of rows: their places, lower bounds of their squared distances to all leaves, and the slack of a distance."""
        coords = self._coords(a)
        groups = _halved(coords, self.GROUP)
        held = coords[np.where(groups < len(a), groups, 0)]
        low, high = held.min(axis=1), held.max(axis=1)
        slack = 1e-9 * float(max(np.abs(low).max(), np.abs(high).max(), np.abs(self.low).max(), np.abs(self.high).max()))
        step = max(1, self.BOUNDS // len(self.low))
        for at in range(0, len(groups), step):
            gaps = np.zeros((len(groups[at : at + step]), len(self.low)))
            for j in range(coords.shape[1]):
                gap = np.maximum(low[at : at + step, j, None] - self.high[None, :, j], self.low[None, :, j] - high[at : at + step, j, None])
                gaps += np.square(np.maximum(gap, 0, out=gap), out=gap)
            for own, bounds in zip(groups[at : at + step], gaps, strict=True):
                own = own[own < len(a)]
                if len(own) and reach[own].max() >= 0:
                    yield own, bounds, slack

    def _measured(self, mine: np.ndarray, leaves: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        rows = self.sorted[leaves].reshape(-1, mine.shape[1])
        return self.places[leaves].ravel(), self.metric.cells(mine[:, None, :], rows[None, :, :])

    def within(self, a: np.ndarray, radius: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """(row of ``a``, place of a fixed row, distance) of all pairs within the radius of the row; a negative radius holds nothing."""
        found, pairs = [], 0
        for own, bounds, slack in self._groups(a, radius) if len(a) else ():
            leaves = np.flatnonzero(bounds <= _squared(radius[own].max(), slack))
            step = max(1, CELLS // (len(own) * self.places.shape[1]))
            for at in range(0, len(leaves), step):
                places, dist = self._measured(a[own], leaves[at : at + step])
                row, col = np.divmod(np.flatnonzero((dist <= radius[own, None]) & (places < len(self.values))[None, :]), len(places))
                found.append((own[row], places[col], dist[row, col]))
                pairs += len(row)
            if pairs >= 1 << 16:
                yield tuple(np.concatenate(x) for x in zip(*found, strict=True))
                found, pairs = [], 0
        if pairs:
            yield tuple(np.concatenate(x) for x in zip(*found, strict=True))

    def nearest(self, a: np.ndarray, limit: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Place and distance of the nearest fixed row of each row, ties to the smaller place; an infinite distance where none is within the limit."""
        place, dist = np.full(len(a), len(self.values), np.int64), np.full(len(a), np.inf)
        limit = np.full(len(a), np.inf) if limit is None else limit
        size = self.places.shape[1]
        for own, bounds, slack in self._groups(a, limit) if len(a) else ():
            mine, coords, best = a[own], self._coords(a[own]), limit[own]
            near, got = np.full(len(own), len(self.values), np.int64), np.full(len(own), np.inf)
            row, edge = np.arange(len(own)), _squared(best.max(), slack)
            # Each row's likeliest leaf first: what it holds bounds the rest.
            few = np.argpartition(bounds, self.FIRST)[: self.FIRST] if len(bounds) > self.FIRST else np.arange(len(bounds))
            few = few[bounds[few] <= edge]
            done = np.full(len(own), -1)
            if len(few):
                own_bounds = self._bounds(coords, few)
                done = few[own_bounds.argmin(axis=1)]
                self._answer(mine, row, done, best, near, got)
                best = np.minimum(best, got)
            leaves = np.flatnonzero(bounds <= _squared(best.max(), slack))
            if len(leaves):
                own_bounds = self._bounds(coords, leaves)
                edge = np.where(best < 0, -1.0, (best * (1 + 1e-9) + slack) ** 2)
                asks, at = np.divmod(np.flatnonzero((own_bounds <= edge[:, None]) & (leaves[None, :] != done[:, None])), len(leaves))
                step = max(1, 8 * CELLS // (size * mine.shape[1]))
                for start in range(0, len(asks), step):
                    self._answer(mine, asks[start : start + step], leaves[at[start : start + step]], best, near, got)
            place[own], dist[own] = near, got
        return place, dist

    def _bounds(self, coords: np.ndarray, leaves: np.ndarray) -> np.ndarray:
        """Lower bounds of the squared distances of rows to leaves."""
        out = np.zeros((len(coords), len(leaves)))
        for j in range(coords.shape[1]):
            own = coords[:, j, None]
            gap = np.maximum(own - self.high[None, leaves, j], self.low[None, leaves, j] - own)
            out += np.square(np.maximum(gap, 0, out=gap), out=gap)
        return out

    def _answer(self, mine: np.ndarray, row: np.ndarray, leaf: np.ndarray, best: np.ndarray, near: np.ndarray, got: np.ndarray) -> None:
        """Measure pairs of a row and a leaf (rows in order), and put what is nearest into ``near`` and ``got``."""
        dist = self.metric.cells(mine[row][:, None, :], self.sorted[leaf])
        least = np.full(len(mine), np.inf)
        np.minimum.at(least, row, dist.min(axis=1))
        least = np.minimum(least, best)
        pair, col = np.divmod(np.flatnonzero(dist <= np.minimum(least, got)[row][:, None]), dist.shape[1])
        places = self.places[leaf[pair], col]
        # A row that fills a leaf up is the first row.
        places = np.where(places < len(self.values), places, 0)
        new_place, new_dist = first_of(row[pair], places, dist[pair, col], len(mine), 1)
        new_place, new_dist = new_place[:, 0], new_dist[:, 0]
        better = (new_dist < got) | ((new_dist == got) & (new_place < near) & np.isfinite(new_dist))
        near[better], got[better] = new_place[better], new_dist[better]


def _squared(reach: float, slack: float) -> float:
    return -1.0 if reach < 0 else (reach * (1 + 1e-9) + slack) ** 2


def _halved(coords: np.ndarray, most: int) -> np.ndarray:
    """Places of rows in parts of one size that lie together: each part is halved at the median of its widest axis.

    Places from the number of rows on stand for repeats of the first row.
    """
    deep = max(0, int(np.ceil(np.log2(max(1, len(coords)) / most))))
    size = -(-len(coords) // (1 << deep))
    order = np.arange(size << deep)[None, :]
    coords = np.concatenate((coords, np.repeat(coords[:1], order.size - len(coords), axis=0)))
    for _ in range(deep):
        held = coords[order]
        axis = (held.max(axis=1) - held.min(axis=1)).argmax(axis=1)
        part = np.argpartition(np.take_along_axis(held, axis[:, None, None], axis=2)[:, :, 0], order.shape[1] // 2, axis=1)
        order = np.take_along_axis(order, part, axis=1).reshape(2 * len(order), -1)
    return order


class Lists:
    """Rows of owned lists, sorted by (list, owner distance): a span of a list is a run of rows."""

    def __init__(self, codes: np.ndarray, near: np.ndarray, ids: np.ndarray, values: np.ndarray):
        order = np.lexsort((near, codes))
        self.codes, self.near, self.ids, self.values = codes[order], near[order], ids[order], values[order]

    def spans(self, codes: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """First row and the row after the last of each (list, lo, hi), by a search of all at once."""
        start, stop = np.searchsorted(self.codes, codes, "left"), np.searchsorted(self.codes, codes, "right")
        return self._cut(start, stop, lo, False), self._cut(start, stop, hi, True)

    def _cut(self, low: np.ndarray, high: np.ndarray, bound: np.ndarray, after: bool) -> np.ndarray:
        low, high = low.copy(), high.copy()
        for _ in range(int((high - low).max(initial=0)).bit_length()):
            open_ = low < high
            mid = (low + high) >> 1
            at = self.near[np.minimum(mid, len(self.near) - 1)]
            right = open_ & ((at <= bound) if after else (at < bound))
            low = np.where(right, mid + 1, low)
            high = np.where(open_ & ~right, mid, high)
        return low

    def scan(self, metric: Metric, values: np.ndarray, asks: Asks, k: int | None):
        """What the asked spans hold within each ask's limit: (query, row, distance), and the rows each query measured.

        With ``k`` only each query's k least come out.  ``values`` are the queries'.
        """
        first, last = self.spans(asks.code, asks.lo, asks.hi)
        held = last > first
        query, first, size, limit = asks.query[held], first[held], (last - first)[held], asks.limit[held]
        order = np.argsort(query, kind="stable")
        query, first, size, limit = query[order], first[order], size[order], limit[order]
        work = np.bincount(query, size, minlength=len(values)).astype(np.int64)
        found = []
        for part in _parts(size):
            n = size[part]
            row = np.repeat(first[part] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
            own = np.repeat(query[part], n)
            dist = measured(metric, values[own], self.values[row])
            near = dist <= np.repeat(limit[part], n)
            own, row, dist = own[near], row[near], dist[near]
            if k == 1 and len(own):
                # A query's rows stand together: its least is one reduction, and only ties are sorted.
                cut = np.flatnonzero(np.r_[True, own[1:] != own[:-1]])
                least = dist <= np.repeat(np.minimum.reduceat(dist, cut), np.diff(np.r_[cut, len(own)]))
                own, row, dist = own[least], row[least], dist[least]
            found.append((own, row, dist) if k is None else self._least(own, row, dist, k))
        if not found:
            return (np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)), work
        merged = tuple(np.concatenate(x) for x in zip(*found, strict=True))
        return (merged if k is None else self._least(*merged, k)), work

    def answer(self, metric: Metric, start: int, stop: int, pivot: np.ndarray, values: np.ndarray, asks: np.ndarray, lo: np.ndarray, hi: np.ndarray, best: np.ndarray, k: int | None, cells: int) -> list[tuple]:
        """What many queries find in the spans of one list (rows ``start`` to ``stop``): (query, row, distance) for each block.

        ``asks`` are places in ``values``; ``best`` holds the most that each query's
        distance may be, and for k = 1 falls to what it has found.  For l2 a single-precision product
        around the pivot leaves the rows that rounding could place among the k least.
        """
        near, found = self.near[start:stop], []
        first, last = np.searchsorted(near, lo, "left"), np.searchsorted(near, hi, "right")
        some = np.flatnonzero(last > first)
        asks, first, last = asks[some], first[some], last[some]
        table, place = self.values[start:stop] - pivot, np.arange(stop - start)
        squares = (table * table).sum(axis=1)
        single = np.vstack((-2 * table.T, squares[None, :])).astype(np.float32)
        step = max(1, cells // max(1, stop - start))
        for at in range(0, len(asks), step):
            own = asks[at : at + step]
            outside = (place < first[at : at + step, None]) | (place >= last[at : at + step, None])
            if metric.name == "l2":
                a = values[own] - pivot
                mine = (a * a).sum(axis=1)
                with np.errstate(over="ignore", invalid="ignore"):
                    rough = np.hstack((a, np.ones((len(a), 1)))).astype(np.float32) @ single
                slack = 8 * (a.shape[1] + 4) * np.finfo(np.float32).eps * (mine + squares.max(initial=0.0))
                edge = best[own] ** 2 - mine + slack
                rough[outside] = np.inf
                if k is not None and k < rough.shape[1]:
                    edge = np.minimum(edge, (rough.min(axis=1) if k == 1 else np.partition(rough, k - 1, axis=1)[:, k - 1]) + slack)
                # What a product can't order (NaN) is measured.
                row, col = np.divmod(np.flatnonzero(~(rough > np.nextafter(edge.astype(np.float32), np.float32(np.inf))[:, None])), rough.shape[1])
                inside = ~outside[row, col]
                row, col = row[inside], col[inside]
            else:
                row, col = np.nonzero(~outside)
            dist = measured(metric, values[own[row]], self.values[start + col])
            fine = dist <= best[own[row]]
            query, col, dist = own[row[fine]], start + col[fine], dist[fine]
            if k is not None:
                query, col, dist = self._least(query, col, dist, k)
            if k == 1:
                best[query] = dist
            found.append((query, col, dist))
        return found

    def _least(self, query: np.ndarray, row: np.ndarray, dist: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        order = np.lexsort((self.ids[row], dist, query))
        query, row, dist = query[order], row[order], dist[order]
        if not len(query):
            return query, row, dist
        starts = np.flatnonzero(np.r_[True, query[1:] != query[:-1]])
        rank = np.arange(len(query)) - np.repeat(starts, np.diff(np.r_[starts, len(query)]))
        return query[rank < k], row[rank < k], dist[rank < k]


class Asks:
    """Spans that queries ask of lists: the place of the query, the list's code, lo, hi, and the most a distance may be."""

    def __init__(self, query: np.ndarray, code: np.ndarray, lo: np.ndarray, hi: np.ndarray, limit: np.ndarray):
        self.query, self.code, self.lo, self.hi, self.limit = query, code, lo, hi, limit

    def of(self, codes: np.ndarray) -> Asks:
        """Those of the given lists (sorted codes)."""
        at = np.minimum(np.searchsorted(codes, self.code), max(0, len(codes) - 1))
        some = codes[at] == self.code if len(codes) else np.zeros(len(self.code), bool)
        return Asks(self.query[some], self.code[some], self.lo[some], self.hi[some], self.limit[some])


def _parts(sizes: np.ndarray):
    """Slices of spans that hold about GATHERED rows together; a longer span stands alone."""
    ends, at = np.cumsum(sizes), 0
    while at < len(sizes):
        done = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, done + GATHERED, "right")))
        yield slice(at, to)
        at = to
