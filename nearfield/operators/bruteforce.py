"""The brute-force primitive: all distances of two sets, then a reduction.

Distances are computed block by block and reduced inside the block, so what is
shuffled is k rows for each query and batch, never a pair; the reduction ends in
a partial and a final step by query.  Ties go to the smaller id everywhere.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nearfield.operators.kernels import CELLS, Boxes, Cells, Near
from nearfield.plans.planner import BLOCK_ROWS, BROADCAST_BYTES, bytes_of, choose_pairing
from nearfield.sources.points import PointSet


def matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """An Arrow list column of equal widths as a matrix."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    return column.flatten().to_numpy(zero_copy_only=False).reshape(n, -1) if n else np.empty((0, 0))


def ids_of(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    if pa.types.is_string(column.type) or pa.types.is_large_string(column.type):
        return np.array(column.to_pylist(), dtype=str)
    return column.to_numpy() if isinstance(column, pa.ChunkedArray) else column.to_numpy(zero_copy_only=False)


def as_arrow(ids: np.ndarray) -> pa.Array:
    return pa.array(ids.tolist(), pa.string()) if ids.dtype.kind == "U" else pa.array(ids)


def collected(points: PointSet, rows: int | None = None, limit: int = BROADCAST_BYTES) -> tuple[np.ndarray, np.ndarray]:
    """Ids and matrix of a set that may be sent to the tasks, ordered by id.

    ``rows`` is its size, where that is known and has been checked; otherwise it
    is counted, and a set over the limit is an error.
    """
    if rows is None:
        rows = points.df.count()
    if bytes_of(rows, points) > limit:
        raise ValueError(f"{rows} rows take more than the {limit} bytes that may be sent to every task")
    table = points.df.select("point_id", "value").toArrow()
    ids, values = ids_of(table.column("point_id")), matrix(table.column("value"))
    order = np.argsort(ids, kind="stable")
    return ids[order], values[order] if len(order) else values


def schema_of(q: PointSet, x: PointSet, *more: T.StructField) -> T.StructType:
    return T.StructType([T.StructField("query_id", q.id_type), T.StructField("neighbor_id", x.id_type), T.StructField("dist", T.DoubleType()), *more])


def _batch(schema: T.StructType, q_ids, x_ids, dists) -> pa.RecordBatch:
    kinds = [pa.int64() if f.dataType == T.LongType() else pa.int32() if f.dataType == T.IntegerType() else pa.string() if f.dataType == T.StringType() else pa.float64() for f in schema]
    plain = lambda c: c.tolist() if getattr(c, "dtype", None) is not None and c.dtype.kind == "U" else c
    return pa.RecordBatch.from_arrays([pa.array(plain(c), t) for c, t in zip((q_ids, x_ids, dists), kinds, strict=False)], schema.names)


#: Blocks of each side where strings or sets meet and neither side may be sent.
_GRID = 64


class Best:
    """The k best so far of a fixed set of queries, over all batches of a task."""

    def __init__(self, queries: int, k: int):
        self.k, self.dist, self.ids = k, np.full((queries, 0), np.inf), None

    def add(self, part: slice, places: np.ndarray, dist: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Merge a block's least places for some of the queries; ties to the smaller id."""
        near = ids[places]
        if self.ids is not None:
            dist, near = np.concatenate((self.dist[part], dist), axis=1), np.concatenate((self.ids[part], near), axis=1)
        if dist.shape[1] == 1:
            return dist, near
        order = np.lexsort((near, dist), axis=1)[:, : self.k]
        return np.take_along_axis(dist, order, axis=1), np.take_along_axis(near, order, axis=1)


def _kernel(q: PointSet, x: PointSet, k: int, small: str, not_self: bool, rows_q: int, rows_x: int) -> DataFrame:
    """k rows for each query and task (or for each query, if the queries are the large side)."""
    schema, metric = schema_of(q, x), q.metric
    s_ids, s_vals = collected(*((q, rows_q) if small == "q" else (x, rows_x)))
    if k == 1 and not not_self and metric.name == "l2":
        return _first_of_slabs(q, x, s_ids, s_vals, rows_x) if small == "q" else _first_of_sent(q, x, s_ids, s_vals)

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if not len(s_ids):
            return
        best = Best(len(s_ids), k)
        fixed = Near(metric, s_vals) if small == "x" else None
        for batch in batches:
            ids, values = ids_of(batch.column(0)), matrix(batch.column(1))
            if not len(ids):
                continue
            order = np.argsort(ids, kind="stable")
            ids, values = ids[order], values[order]
            a_ids, a_vals, b_ids = (s_ids, s_vals, ids) if small == "q" else (ids, values, s_ids)
            near_of = Near(metric, values) if small == "q" else fixed
            step = max(1, CELLS // len(b_ids))
            dists, nears = [], []
            for at in range(0, len(a_ids), step):
                own = a_ids[at : at + step]
                places, dist = near_of.least(a_vals[at : at + step], k, own[:, None] == b_ids[None, :] if not_self else None)
                if small == "q":
                    dist, near = best.add(slice(at, at + step), places, dist, b_ids)
                    dists.append(dist)
                    nears.append(near)
                    continue
                row, place = np.nonzero(np.isfinite(dist))
                yield _batch(schema, own[row], b_ids[places[row, place]], dist[row, place])
            if small == "q":
                best.dist, best.ids = np.concatenate(dists), np.concatenate(nears)
        if best.ids is not None:
            row, place = np.nonzero(np.isfinite(best.dist))
            yield _batch(schema, s_ids[row], best.ids[row, place], best.dist[row, place])

    big = x if small == "q" else q
    return big.df.select("point_id", "value").mapInArrow(search, schema)


def _first_of_sent(q: PointSet, x: PointSet, x_ids: np.ndarray, x_vals: np.ndarray) -> DataFrame:
    """The nearest of a sent X for each query, slab by slab."""
    schema, metric = schema_of(q, x), q.metric

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if not len(x_ids):
            return
        near_of = Near(metric, x_vals)
        for slab in slabs(batches, SENT_SLAB):
            ids, values = slab.column(0).combine_chunks(), matrix(slab.column(1))
            place, dist = near_of.nearest(values)
            some = np.flatnonzero(np.isfinite(dist))
            yield pa.RecordBatch.from_arrays([ids.take(pa.array(some)), as_arrow(x_ids[place[some]]), pa.array(dist[some])], schema.names)

    return q.df.select("point_id", "value").mapInArrow(search, schema)


#: Rows of X that bound the distances of sent queries before X is searched, and the least work for which they are read.
SAMPLED, PAID = 1 << 14, 10**10


def _bounds(q_vals: np.ndarray, x: PointSet, rows_x: int) -> np.ndarray:
    """No query's answer is farther than this: the distance to its nearest of some rows of X, a little loosened."""
    if len(q_vals) * rows_x < PAID or not np.isfinite(q_vals).all():
        return np.full(len(q_vals), np.inf)
    every = max(1, rows_x // SAMPLED)
    seen = matrix(x.df.where(F.pmod(F.xxhash64("value"), F.lit(every)) == 0).select("value").toArrow().column("value"))
    if not len(seen) or not np.isfinite(seen).all():
        return np.full(len(q_vals), np.inf)
    return Near(x.metric, seen).nearest(q_vals)[1] * (1 + 1e-9)


def _first_of_slabs(q: PointSet, x: PointSet, q_ids: np.ndarray, q_vals: np.ndarray, rows_x: int) -> DataFrame:
    """The nearest row of each task for sent queries: a task puts its rows into boxes, slab by slab.

    What some rows of X show to be too far is neither measured nor shuffled.
    """
    schema, metric = schema_of(q, x), q.metric
    limit = _bounds(q_vals, x, rows_x)
    names = as_arrow(q_ids)

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if not len(q_ids):
            return
        best = limit.copy()
        for slab in slabs(batches, slab_rows(metric)):
            order = np.argsort(ids_of(slab.column(0)), kind="stable")
            slab = slab.take(pa.array(order))
            ids, values = slab.column(0).combine_chunks(), matrix(slab.column(1))
            if len(values) >= Boxes.ROWS and Boxes.fits(metric, q_vals, values):
                place, dist = Boxes(metric, values).nearest(q_vals, best)
            else:
                place, dist = Near(metric, values).nearest(q_vals)
            # What a later slab finds as far is kept too: ties are settled by the ids.
            some = np.flatnonzero((dist <= best) & np.isfinite(dist))
            best[some] = dist[some]
            yield pa.RecordBatch.from_arrays([names.take(pa.array(some)), ids.take(pa.array(place[some])), pa.array(dist[some])], schema.names)

    return x.df.select("point_id", "value").mapInArrow(search, schema)


def _nested(q: PointSet, x: PointSet, small: str | None, not_self: bool) -> DataFrame:
    """All pairs as rows, measured by the Column: the small side is broadcast, or blocks of both meet where neither is."""
    a = q.df.select(F.col("point_id").alias("query_id"), F.col("value").alias("qv"))
    b = x.df.select(F.col("point_id").alias("neighbor_id"), F.col("value").alias("xv"))
    if small is None:
        n = _GRID
        a = a.withColumn("row", F.pmod(F.xxhash64("query_id"), F.lit(n))).withColumn("cell", F.explode(F.sequence(F.col("row") * n, F.col("row") * n + n - 1))).drop("row")
        b = b.withColumn("own", F.pmod(F.xxhash64("neighbor_id"), F.lit(n))).withColumn("cell", F.explode(F.sequence(F.col("own"), F.col("own") + n * (n - 1), F.lit(n).cast("long")))).drop("own")
        both = a.join(b, "cell")
    else:
        both = F.broadcast(a).join(b, F.lit(True)) if small == "q" else a.join(F.broadcast(b), F.lit(True))
    if not_self:
        both = both.where(F.col("query_id") != F.col("neighbor_id"))
    return both.select("query_id", "neighbor_id", q.metric.column(F.col("qv"), F.col("xv")).alias("dist"))


def blocks(q: PointSet, x: PointSet, k: int, rows: int = BLOCK_ROWS, rows_q: int | None = None, rows_x: int | None = None, not_self: bool = False) -> DataFrame:
    """Block grid: each block of Q meets each block of X once, in one task.

    A row travels once for each block of the other side; a task holds one block
    of each.  ``k`` rows for each query and pair of blocks come out.
    """
    n_q = max(1, -(-(rows_q if rows_q is not None else q.df.count()) // rows))
    n_x = max(1, -(-(rows_x if rows_x is not None else x.df.count()) // rows))
    own_q, own_x = (F.pmod(F.xxhash64("point_id"), F.lit(n)) for n in (n_q, n_x))
    a = q.df.select("point_id", "value", own_q.alias("own"), F.explode(F.sequence(F.lit(0), F.lit(n_x - 1))).alias("other")).select("point_id", "value", (F.col("own") * n_x + F.col("other")).alias("cell"))
    b = x.df.select("point_id", "value", own_x.alias("own"), F.explode(F.sequence(F.lit(0), F.lit(n_q - 1))).alias("other")).select("point_id", "value", (F.col("other") * n_x + F.col("own")).alias("cell"))
    schema, metric = schema_of(q, x), q.metric

    def meet(left: pa.Table, right: pa.Table) -> pa.Table:
        out = []
        if left.num_rows and right.num_rows:
            q_ids, q_vals = ids_of(left.column("point_id")), matrix(left.column("value"))
            x_ids, x_vals = ids_of(right.column("point_id")), matrix(right.column("value"))
            order = np.argsort(x_ids, kind="stable")
            x_ids, x_vals = x_ids[order], x_vals[order]
            near_of, step = Near(metric, x_vals), max(1, CELLS // len(x_ids))
            for at in range(0, len(q_ids), step):
                own = q_ids[at : at + step]
                places, dist = near_of.least(q_vals[at : at + step], k, own[:, None] == x_ids[None, :] if not_self else None)
                row, place = np.nonzero(np.isfinite(dist))
                out.append(_batch(schema, own[row], x_ids[places[row, place]], dist[row, place]))
        return pa.Table.from_batches(out or [_batch(schema, [], [], [])])

    return a.groupBy("cell").cogroup(b.groupBy("cell")).applyInArrow(meet, schema)


def reduce_top_k(found: DataFrame, k: int) -> DataFrame:
    """``query_id, neighbor_id, dist, rank_no`` from candidates; a neighbour counts once."""
    if k == 1:
        # A plain minimum first: it is summed on the map side without sorting structs.
        least = found.groupBy("query_id").agg(F.min("dist").alias("dist"))
        tied = found.join(least, ["query_id", "dist"], "left_semi")
        return tied.groupBy("query_id").agg(F.min("neighbor_id").alias("neighbor_id"), F.min("dist").alias("dist"), F.lit(1).alias("rank_no"))
    order = Window.partitionBy("query_id").orderBy("dist", "neighbor_id")
    once = found.groupBy("query_id", "neighbor_id").agg(F.min("dist").alias("dist"))
    return once.withColumn("rank_no", F.row_number().over(order)).where(F.col("rank_no") <= k).select("query_id", "neighbor_id", "dist", "rank_no")


def reduce_rows(found: DataFrame, k: int) -> DataFrame:
    """As ``reduce_top_k`` for candidates that are few for each query: one window, one shuffle."""
    order = Window.partitionBy("query_id").orderBy("dist", "neighbor_id")
    return found.select("query_id", "neighbor_id", "dist").distinct().withColumn("rank_no", F.row_number().over(order)).where(F.col("rank_no") <= k)


def candidates(q: PointSet, x: PointSet, k: int, not_self: bool = False, rows_q: int | None = None, rows_x: int | None = None) -> DataFrame:
    rows_q = q.df.count() if rows_q is None else rows_q
    rows_x = x.df.count() if rows_x is None else rows_x
    plan = choose_pairing(q, x, rows_q, rows_x)
    if plan.kind == "grid" and x.is_vector:
        return blocks(q, x, k, rows_q=rows_q, rows_x=rows_x, not_self=not_self)
    if plan.kind == "kernel":
        return _kernel(q, x, k, plan.small, not_self, rows_q, rows_x)
    if plan.kind == "nested" and q.metric.name in ("jaccard", "edit"):
        from nearfield.operators import edits, tokens

        found = (tokens if q.metric.name == "jaccard" else edits).nearest(q, x, k, plan.small, not_self)
        if found is not None:
            return found
    return _nested(q, x, plan.small if plan.kind == "nested" else None, not_self)


def nearest(q: PointSet, x: PointSet, k: int = 1, not_self: bool = False, **sizes: int) -> DataFrame:
    """The k nearest of X for each query: ``query_id, neighbor_id, dist, rank_no``."""
    found = candidates(q, x, k, not_self, **sizes)
    return reduce_rows(found, k) if x.is_vector else reduce_top_k(found, k)


def nearest_in(q: PointSet, x: PointSet, ids: DataFrame, k: int = 1) -> DataFrame:
    """Brute force over the part of X whose ids are listed."""
    return nearest(q, PointSet(x.df.join(ids.select("point_id").distinct(), "point_id", "left_semi"), x.metric), k)


def nearest_in_lists(q: PointSet, pairs: DataFrame, lists: DataFrame, k: int = 1) -> DataFrame:
    """Brute force with a list of its own for each query: ``pairs`` (query_id, pivot_id), ``lists`` (pivot_id, point_id, value)."""
    named = q.df.select(F.col("point_id").alias("query_id"), F.col("value").alias("qv"))
    met = pairs.join(named, "query_id").join(lists.select("pivot_id", F.col("point_id").alias("neighbor_id"), F.col("value").alias("xv")), "pivot_id")
    return reduce_top_k(met.select("query_id", "neighbor_id", q.metric.column(F.col("qv"), F.col("xv")).alias("dist")), k)


def nearest_one(value, x: PointSet, k: int = 1) -> DataFrame:
    """One query as a literal: a scan, and the k least rows kept as they pass."""
    literal = F.array(*[F.lit(float(v)) for v in value]) if x.is_vector else F.lit(value)
    scored = x.df.select(F.col("point_id").alias("neighbor_id"), x.metric.column(literal, F.col("value")).alias("dist"))
    return scored.orderBy("dist", "neighbor_id").limit(k)


def all_distances(q: PointSet, r: PointSet) -> DataFrame:
    """Every distance to a small set R, kept: ``query_id, pivot_id, dist``."""
    return _nested(q, r, "x", False).withColumnRenamed("neighbor_id", "pivot_id")


#: Rows that a task of a range search gathers before it looks for their neighbours, and pairs that leave it at once.
SLAB, PAIRS = 1 << 18, 1 << 16
#: Queries that a task gathers before it asks a sent side.
SENT_SLAB = 1 << 16


def within(q: PointSet, x: PointSet, eps: float, digits: int | None = None) -> DataFrame:
    """All pairs at most ``eps`` apart: ``query_id, neighbor_id, dist``, rounded to ``digits`` where they are measured.

    Queries are sent and rows are read where they lie.  Where each axis bounds the
    distance, only rows of neighbouring cells of the width of the range are measured.
    """
    if not x.is_vector:
        return _rounded(_nested(q, x, "q", False).where(F.col("dist") <= eps), digits)
    rows = q.df.count()
    if bytes_of(rows, q) > BROADCAST_BYTES:
        return _rounded(_nested(q, x, None, False).where(F.col("dist") <= eps), digits)
    schema, metric = schema_of(q, x), q.metric
    q_ids, q_vals = collected(q, rows)
    names = as_arrow(q_ids)

    def paired(ids: pa.Array, own: np.ndarray, row: np.ndarray, dist: np.ndarray) -> Iterator[pa.RecordBatch]:
        if digits is not None:
            # Halves go up, as in SQL.
            dist = np.floor(dist * 10.0**digits + 0.5) / 10.0**digits
        for at in range(0, len(own), PAIRS):
            some = slice(at, at + PAIRS)
            yield pa.RecordBatch.from_arrays([names.take(pa.array(own[some])), ids.take(pa.array(row[some])), pa.array(dist[some])], schema.names)

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells = Cells(metric, q_vals, eps) if len(q_ids) and Cells.fits(metric, q_vals, eps) else None
        for table in slabs(batches, SLAB):
            ids, values = table.column(0).combine_chunks(), matrix(table.column(1))
            if cells is not None:
                for own, row, dist in cells.within(values):
                    yield from paired(ids, own, row, dist)
                continue
            step = max(1, CELLS // max(1, len(ids)))
            for at in range(0, len(q_ids), step):
                block = metric.block(q_vals[at : at + step], values)
                own, col = np.nonzero(block <= eps)
                yield from paired(ids, at + own, col, block[own, col])

    return x.df.select("point_id", "value").mapInArrow(search, schema)


def _rounded(found: DataFrame, digits: int | None) -> DataFrame:
    return found if digits is None else found.withColumn("dist", F.round("dist", digits))


def slab_rows(metric) -> int:
    """Rows that a task may gather of vectors of this width: wide ones by their bytes."""
    return min(SLAB, max(1 << 14, (1 << 22) // max(1, metric.width or 1)))


def slabs(batches: Iterator[pa.RecordBatch], most: int) -> Iterator[pa.Table]:
    """Batches of a task together, about ``most`` rows at a time."""
    held, rows = [], 0
    for batch in batches:
        if batch.num_rows:
            held.append(batch)
            rows += batch.num_rows
        if rows >= most:
            yield pa.Table.from_batches(held)
            held, rows = [], 0
    if held:
        yield pa.Table.from_batches(held)


def self_nearest(x: PointSet, k: int = 1) -> DataFrame:
    """The k nearest others of every point of X."""
    return nearest(x, x, k, not_self=True)
