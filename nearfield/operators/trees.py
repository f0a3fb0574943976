"""Baselines: net tree, ball tree and kd-tree, built and searched within tasks.

Each is a sequential structure; in a task it works as usual, and a table is cut
into as many chunks as the caller asks for, whose answers are reduced by query.
``chunks=1`` is the single-core form.  All count their distance evaluations.
"""

from __future__ import annotations

import heapq
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nearfield.operators import bruteforce as bf
from nearfield.sources.points import PointSet


class NetTree:
    """Nested nets whose radii halve level by level.

    Nodes of a level are farther apart than its radius within their parent, and
    each knows how far its points reach.  Nodes of few points go down unsplit.  A
    search goes level by level and drops a node whose distance exceeds the k-th
    best by that reach.
    """

    def __init__(self, values: np.ndarray, block: Callable, leaf: int = 16):
        self.values, self.block = values, block
        n = len(values)
        self.evaluations = n
        reach = [float(block(values[:1], values).max())] if n else []
        centres, members = ([0], [np.arange(n)]) if n else ([], [])
        r = reach[0] if n and reach[0] > 0 else 1.0
        end = r * 1e-9
        #: For each level: centres, reaches and, for each node, the places of its children in the next level.
        self.levels: list[tuple[np.ndarray, np.ndarray, list[list[int]]]] = []
        while r > end and any(len(m) > leaf for m in members):
            r /= 2
            kids, below, parts, reaches = [], [], [], []
            for c, m, far in zip(centres, members, reach, strict=True):
                own = []
                if len(m) <= leaf:
                    own.append(len(below))
                    below.append(c)
                    parts.append(m)
                    reaches.append(far)
                else:
                    rest, lead = m, c
                    while len(rest):
                        d = block(values[lead : lead + 1], values[rest])[0]
                        self.evaluations += len(rest)
                        inside = d <= r
                        own.append(len(below))
                        below.append(int(lead))
                        parts.append(rest[inside])
                        reaches.append(float(d[inside].max()))
                        rest = rest[~inside]
                        lead = rest[0] if len(rest) else lead
                kids.append(own)
            self.levels.append((np.array(centres), np.array(reach), kids))
            centres, members, reach = below, parts, reaches
        self.levels.append((np.array(centres), np.array(reach), []))
        self.members = members

    def search(self, q: np.ndarray, k: int) -> tuple[list[tuple[float, int]], int]:
        if not len(self.values):
            return [], 0
        seen: dict[int, float] = {}
        live = [0]

        def measure(rows: list[int]) -> None:
            new = [x for x in dict.fromkeys(rows) if x not in seen]
            if new:
                seen.update(zip(new, self.block(q[None], self.values[new])[0].tolist(), strict=True))

        for level, (centres, reach, kids) in enumerate(self.levels):
            rows = centres[live].tolist()
            measure(rows)
            best = heapq.nsmallest(k, seen.values())[-1] if len(seen) >= k else np.inf
            limit = best * (1 + 1e-9) + 1e-12
            live = [i for i, x in zip(live, rows, strict=True) if seen[x] - reach[i] <= limit]
            if level + 1 < len(self.levels):
                live = [c for i in live for c in kids[i]]
        for i in live:
            measure(self.members[i].tolist())
        return heapq.nsmallest(k, ((d, i) for i, d in seen.items())), len(seen)


class BallTree:
    """Depth-first search of nested balls; works for any metric with a block form."""

    def __init__(self, values: np.ndarray, block: Callable, leaf: int = 32):
        self.values, self.block, self.leaf = values, block, leaf
        self.evaluations = 0
        self.root = self._grow(np.arange(len(values))) if len(values) else None

    def _grow(self, own: np.ndarray):
        d = self.block(self.values[own[:1]], self.values[own])[0]
        self.evaluations += len(own)
        if len(own) <= self.leaf or d.max() == 0:
            return own[0], float(d.max()), own, None, None
        a = own[d.argmax()]
        da = self.block(self.values[[a]], self.values[own])[0]
        b = own[da.argmax()]
        db = self.block(self.values[[b]], self.values[own])[0]
        self.evaluations += 2 * len(own)
        near = da <= db
        return own[0], float(d.max()), own, self._grow(own[near]), self._grow(own[~near])

    def search(self, q: np.ndarray, k: int) -> tuple[list[tuple[float, int]], int]:
        best: list[tuple[float, int]] = []
        count = 0

        def visit(node) -> None:
            nonlocal count, best
            centre, radius, own, left, right = node
            if left is None:
                d = self.block(q[None], self.values[own])[0]
                count += len(own)
                best = heapq.nsmallest(k, [*best, *zip(d.tolist(), own.tolist(), strict=True)])
                return
            gaps = []
            for child in (left, right):
                d = float(self.block(q[None], self.values[[child[0]]])[0, 0])
                count += 1
                gaps.append((d - child[1], d, child))
            for gap, _, child in sorted(gaps, key=lambda g: g[1]):
                if len(best) < k or gap <= best[-1][0] * (1 + 1e-9) + 1e-12:
                    visit(child)

        if self.root is not None:
            visit(self.root)
        return best, count


class KdTree:
    """Median splits by the widest axis, for few dimensions and l2."""

    def __init__(self, values: np.ndarray, block: Callable, leaf: int = 32):
        self.values, self.block, self.leaf = values, block, leaf
        self.evaluations = 0
        self.root = self._grow(np.arange(len(values))) if len(values) else None

    def _grow(self, own: np.ndarray):
        box = self.values[own]
        low, high = box.min(axis=0), box.max(axis=0)
        axis = int((high - low).argmax())
        if len(own) <= self.leaf or low[axis] == high[axis]:
            return low, high, own, None, None
        order = own[np.argsort(box[:, axis], kind="stable")]
        half = len(own) // 2
        return low, high, own, self._grow(order[:half]), self._grow(order[half:])

    def search(self, q: np.ndarray, k: int) -> tuple[list[tuple[float, int]], int]:
        best: list[tuple[float, int]] = []
        count = 0

        def gap(node) -> float:
            return float(np.sqrt((np.maximum(0, np.maximum(node[0] - q, q - node[1])) ** 2).sum()))

        def visit(node) -> None:
            nonlocal count, best
            if node[3] is None:
                d = self.block(q[None], self.values[node[2]])[0]
                count += len(node[2])
                best = heapq.nsmallest(k, [*best, *zip(d.tolist(), node[2].tolist(), strict=True)])
                return
            for g, _, child in sorted((gap(c), i, c) for i, c in enumerate(node[3:])):
                if len(best) < k or g <= best[-1][0] * (1 + 1e-9) + 1e-12:
                    visit(child)

        if self.root is not None:
            visit(self.root)
        return best, count


def search(kind: type, q: PointSet, x: PointSet, k: int = 1, chunks: int = 1) -> DataFrame:
    """``query_id, neighbor_id, dist, rank_no, evaluations`` (summed over chunks) by trees of ``chunks`` parts of X."""
    q_ids, q_vals = bf.collected(q)
    block = x.metric.block
    schema = bf.schema_of(q, x, T.StructField("evaluations", T.LongType()))

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        table = pa.Table.from_batches(held)
        ids, values = bf.ids_of(table.column(0)), bf.matrix(table.column(1))
        order = np.argsort(ids, kind="stable")
        ids, values = ids[order], values[order]
        tree = kind(values, block)
        rows = [(own, ids[i], d, n if place == 0 else 0) for own, v in zip(q_ids, q_vals, strict=True) for found, n in [tree.search(v, k)] for place, (d, i) in enumerate(found)]
        if rows:
            own, near, dist, n = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(list(map(_plain, own))), pa.array(list(map(_plain, near))), pa.array(dist, pa.float64()), pa.array(n, pa.int64())], schema.names)

    cut = x.df.select("point_id", "value").repartition(chunks, F.xxhash64("point_id")) if chunks > 1 else x.df.select("point_id", "value").coalesce(1)
    found = cut.mapInArrow(task, schema)
    work = found.groupBy("query_id").agg(F.sum("evaluations").alias("evaluations"))
    return bf.reduce_rows(found.drop("evaluations"), k).join(work, "query_id")


def _plain(x):
    return x.item() if hasattr(x, "item") else x
