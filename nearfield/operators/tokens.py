"""Jaccard distances of token sets in blocks: the sent sets are posting lists, and a batch counts what it shares with all of them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nearfield.operators import bruteforce as bf
from nearfield.operators.kernels import first_of
from nearfield.sources.points import PointSet

#: Cells of a block, and shared tokens that it counts at once.
BLOCK, SHARED = 1 << 18, 1 << 21


class Postings:
    """Fixed sets by token, in the order of their ids."""

    def __init__(self, table: pa.Table):
        ids = bf.ids_of(table.column("point_id"))
        order = np.argsort(ids, kind="stable")
        sets = table.column("value").combine_chunks().take(pa.array(order))
        self.ids, self.sizes = ids[order], _sizes(sets)
        coded = sets.flatten().dictionary_encode()
        self.words, code = coded.dictionary, coded.indices.to_numpy(zero_copy_only=False)
        by_word = np.argsort(code, kind="stable")
        self.owner = np.repeat(np.arange(len(self.ids)), self.sizes)[by_word]
        self.start = np.searchsorted(code[by_word], np.arange(len(self.words) + 1))

    def blocks(self, sets: pa.ListArray) -> Iterator[tuple[slice, np.ndarray]]:
        """Rows of ``sets`` and their distances to all fixed sets, part by part."""
        sizes = _sizes(sets)
        code = pc.index_in(sets.flatten(), self.words)
        known = code.is_valid().to_numpy(zero_copy_only=False)
        row, code = np.repeat(np.arange(len(sets)), sizes)[known], code.drop_null().to_numpy()
        shared = (self.start[1:] - self.start[:-1])[code]
        ends = np.cumsum(np.bincount(row, shared, minlength=len(sets)))
        at, n = 0, len(self.ids)
        while at < len(sets):
            done = ends[at - 1] if at else 0
            to = max(at + 1, min(at + max(1, BLOCK // max(1, n)), int(np.searchsorted(ends, done + SHARED, "right"))))
            a, b = np.searchsorted(row, (at, to))
            times, first = shared[a:b], self.start[code[a:b]]
            place = np.repeat(first - (np.cumsum(times) - times), times) + np.arange(int(times.sum()))
            both = np.bincount(np.repeat(row[a:b] - at, times) * n + self.owner[place], minlength=(to - at) * n).reshape(to - at, n)
            union = sizes[at:to, None] + self.sizes[None, :] - both
            yield slice(at, to), np.where(union == 0, 0.0, 1.0 - both / np.maximum(union, 1))
            at = to


def _sizes(sets: pa.ListArray) -> np.ndarray:
    return pc.list_value_length(sets).to_numpy(zero_copy_only=False).astype(np.int64)


def sent(points: PointSet, limit: int = bf.BROADCAST_BYTES) -> Postings | None:
    """The sets, if they may be sent to every task by their real size."""
    known = points.df.where(F.col("value").isNotNull()).select("point_id", "value")
    size = known.agg(F.sum(F.length(F.array_join("value", " ")) + 8 * F.size("value") + 24)).first()[0] or 0
    return Postings(known.toArrow()) if size <= limit else None


class _Best:
    """Each fixed set's k least of rows that come in blocks; ties to the smaller id."""

    def __init__(self, n: int, k: int):
        self.n, self.k, self.own, self.ids, self.dist = n, k, np.empty(0, np.int64), None, np.empty(0)

    def add(self, ids: np.ndarray, block: np.ndarray) -> None:
        k = min(self.k, len(ids))
        edge = block.min(axis=0) if k == 1 else np.partition(block, k - 1, axis=0)[k - 1]
        row, own = np.nonzero((block <= edge[None, :]) & np.isfinite(block))
        own, near, dist = np.concatenate((self.own, own)), ids[row] if self.ids is None else np.concatenate((self.ids, ids[row])), np.concatenate((self.dist, block[row, own]))
        names, code = np.unique(near, return_inverse=True)
        places, dists = first_of(own, code, dist, self.n, self.k)
        self.own, rank = np.nonzero(np.isfinite(dists))
        self.ids, self.dist = names[places[self.own, rank]], dists[self.own, rank]


def nearest(q: PointSet, x: PointSet, k: int, small: str, not_self: bool = False) -> DataFrame | None:
    """k rows for each query and task: ``query_id, neighbor_id, dist``; None if the small side may not be sent."""
    fixed = sent(q if small == "q" else x)
    if fixed is None:
        return None
    schema = bf.schema_of(q, x)

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = _Best(len(fixed.ids), k)
        for batch in batches:
            ids = bf.ids_of(batch.column(0))
            for part, block in fixed.blocks(batch.column(1)) if len(fixed.ids) and len(ids) else ():
                own = ids[part]
                if not_self:
                    block = np.where(own[:, None] == fixed.ids[None, :], np.inf, block)
                if small == "q":
                    best.add(own, block)
                    continue
                near = np.argsort(block, axis=1, kind="stable")[:, :k] if k > 1 else block.argmin(axis=1)[:, None]
                row, rank = np.nonzero(np.isfinite(np.take_along_axis(block, near, axis=1)))
                col = near[row, rank]
                yield bf._batch(schema, own[row], fixed.ids[col], block[row, col])
        if best.ids is not None:
            yield bf._batch(schema, fixed.ids[best.own], best.ids, best.dist)

    big = (x if small == "q" else q).df.where(F.col("value").isNotNull())
    return big.select("point_id", "value").mapInArrow(search, schema)


def scan(q: PointSet, kept: DataFrame, lists: DataFrame, k: int, limit: int = bf.BROADCAST_BYTES) -> DataFrame | None:
    """The k nearest of each query and task in the spans (query_id, pivot_id, lo, hi) of owned lists; None if queries or spans may not be sent."""
    spans = kept.where(F.col("hi") >= F.col("lo")).select("query_id", "pivot_id", "lo", "hi").persist()
    try:
        queries, names = spans.select("query_id").distinct().count(), spans.select("pivot_id").distinct().count()
        fixed = sent(q) if 16 * queries * names <= limit else None
        asked = spans.toArrow() if fixed is not None else None
    finally:
        spans.unpersist()
    if asked is None:
        return None
    pivots, code = np.unique(bf.ids_of(asked.column("pivot_id")), return_inverse=True)
    lo, hi = np.full((len(pivots), len(fixed.ids)), np.inf), np.full((len(pivots), len(fixed.ids)), -np.inf)
    own = np.searchsorted(fixed.ids, bf.ids_of(asked.column("query_id")))
    lo[code, own], hi[code, own] = asked.column("lo").to_numpy(), asked.column("hi").to_numpy()
    schema = bf.schema_of(q, PointSet(lists.select("point_id", "value"), q.metric))

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = _Best(len(fixed.ids), k)
        for batch in batches:
            if not batch.num_rows or not len(pivots):
                continue
            named = bf.ids_of(batch.column(0))
            at = np.minimum(np.searchsorted(pivots, named), len(pivots) - 1)
            dist = batch.column(1).to_numpy()
            wanted = np.flatnonzero((pivots[at] == named) & (dist >= lo[at].min(axis=1)) & (dist <= hi[at].max(axis=1)))
            ids, at, dist = bf.ids_of(batch.column(2))[wanted], at[wanted], dist[wanted]
            for part, block in fixed.blocks(batch.column(3).take(pa.array(wanted))) if len(wanted) else ():
                d = dist[part, None]
                best.add(ids[part], np.where((d >= lo[at[part]]) & (d <= hi[at[part]]), block, np.inf))
        if best.ids is not None:
            yield bf._batch(schema, fixed.ids[best.own], best.ids, best.dist)

    return lists.select("pivot_id", "owner_dist", "point_id", "value").mapInArrow(search, schema)
