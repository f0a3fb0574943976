"""Pivot covers: owned lists of the exact layout, s-nearest lists of the one-shot layout.

Lists are flat rows (pivot_id, owner_dist, point_id, value): they shuffle, filter
and store like any table, and a bound on owner_dist is a predicate that Parquet
statistics understand.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nearfield.functions.metrics import PRODUCT
from nearfield.operators import bruteforce as bf
from nearfield.operators.kernels import CELLS, Boxes, Near
from nearfield.operators.sampling import bernoulli_pivots
from nearfield.plans.planner import BROADCAST_BYTES, bytes_of
from nearfield.sources.points import PointSet


@dataclass(frozen=True)
class Cover:
    """``pivots``: pivot_id, value, psi, list_size, alive.  ``lists``: pivot_id, owner_dist, point_id, value.

    A pivot that was deleted is no longer ``alive``: it goes on routing to its list,
    but it is no answer and bounds none.
    """

    pivots: DataFrame
    lists: DataFrame
    points: PointSet
    layout: str
    #: The pivots of a fresh cover as they were drawn, without what the lists tell of them.
    sampled: DataFrame | None = None

    @property
    def pivot_set(self) -> PointSet:
        return PointSet(self.pivots.select(F.col("pivot_id").alias("point_id"), "value"), self.points.metric)


def owners(x: PointSet, pivots: PointSet, n_pivots: int | None = None) -> DataFrame:
    """Each point with its nearest pivot: ``point_id, value, pivot_id, owner_dist``; ties to the smaller pivot.

    Without a shuffle while the pivots may be sent to the tasks; beyond that size
    by the block grid and a join back.
    """
    n_pivots = pivots.df.count() if n_pivots is None else n_pivots
    if not x.is_vector or bytes_of(n_pivots, pivots) > BROADCAST_BYTES:
        best = bf.nearest(x, pivots, 1).select(F.col("query_id").alias("point_id"), F.col("neighbor_id").alias("pivot_id"), F.col("dist").alias("owner_dist"))
        return x.df.join(best, "point_id").select("point_id", "value", "pivot_id", "owner_dist")
    r_ids, r_vals = bf.collected(pivots, n_pivots)
    metric = x.metric
    schema = T.StructType([*x.df.select("point_id", "value").schema.fields, T.StructField("pivot_id", pivots.id_type), T.StructField("owner_dist", T.DoubleType())])

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        near_of = Near(metric, r_vals)
        for slab in bf.slabs(batches, bf.SENT_SLAB):
            places, near = near_of.nearest(bf.matrix(slab.column(1)))
            owned = pa.Table.from_arrays([slab.column(0), slab.column(1), bf.as_arrow(r_ids[places]), pa.array(near)], schema.names)
            yield from owned.combine_chunks().to_batches(max_chunksize=1 << 14)

    return x.df.select("point_id", "value").mapInArrow(assign, schema)


def radii(lists: DataFrame) -> DataFrame:
    """``pivot_id, psi, list_size``."""
    return lists.groupBy("pivot_id").agg(F.max("owner_dist").alias("psi"), F.count(F.lit(1)).alias("list_size"))


def sized(sampled: DataFrame, lists: DataFrame) -> DataFrame:
    """Drawn pivots (pivot_id, value) with the radius and size of their lists; all are alive."""
    met = sampled.join(radii(lists), "pivot_id", "left")
    return met.select("pivot_id", "value", F.coalesce("psi", F.lit(0.0)).alias("psi"), F.coalesce("list_size", F.lit(0)).alias("list_size"), F.lit(True).alias("alive"))


def _covered(x: PointSet, pivots: PointSet, lists: DataFrame, layout: str) -> Cover:
    named = pivots.df.select(F.col("point_id").alias("pivot_id"), "value")
    return Cover(sized(named, lists), lists, x, layout, named)


def build_exact(x: PointSet, n_r: float, seed: int = 1, n: int | None = None, levels: int = 1) -> Cover:
    """The exact layout: every point belongs to its nearest pivot.

    With two levels the pivots have a cover of their own and every point finds
    its pivot by an exact search through it: about the square root of the pivots
    for each point instead of all of them.  Exact, so all bounds stay valid.
    """
    n = x.df.count() if n is None else n
    pivots = bernoulli_pivots(x, n_r, n, seed)
    if levels == 1:
        return from_pivots(x, pivots)
    from nearfield.operators import exact

    # Pivots and lists of the upper cover are read for every batch of points: both are written.
    from nearfield.operators import storage

    pivots = storage.at_rest(pivots)
    top = storage.settled(build_exact(pivots, max(1.0, n_r**0.5), seed + 1, max(1, int(n_r))))
    best = exact.search(PointSet(x.df, x.metric), top).select(F.col("query_id").alias("point_id"), F.col("neighbor_id").alias("pivot_id"), F.col("dist").alias("owner_dist"))
    lists = x.df.join(best, "point_id").select("pivot_id", "owner_dist", "point_id", "value")
    return _covered(x, pivots, lists, "exact")


def from_pivots(x: PointSet, pivots: PointSet) -> Cover:
    """The exact layout around given pivots."""
    return _covered(x, pivots, owners(x, pivots).select("pivot_id", "owner_dist", "point_id", "value"), "exact")


def around(x: PointSet, pivots: PointSet) -> Cover:
    """Pivots whose lists nobody reads: X stands for them."""
    return Cover(pivots.df.select(F.col("point_id").alias("pivot_id"), "value"), x.df, x, "exact")


def build_oneshot(x: PointSet, n_r: float, s: int, seed: int = 1, n: int | None = None) -> Cover:
    """The one-shot layout: each pivot has its s nearest points, and lists may overlap.

    Every batch of X gives s rows at most for each pivot; when X is much larger
    than that, a sample of X first gives each pivot a radius that holds s points
    in all likelihood, and only rows inside it are ranked; a count over X gives
    pivots whose radius holds fewer none.
    """
    n = x.df.count() if n is None else n
    pivots = bernoulli_pivots(x, n_r, n, seed)
    return _covered(x, pivots, nearest_points(pivots, x, s, n), "oneshot")


def nearest_points(pivots: PointSet, x: PointSet, s: int, n: int) -> DataFrame:
    """``pivot_id, owner_dist, point_id, value``: the s nearest points of every pivot, ties to the smaller id."""
    if not x.is_vector:
        found = bf.nearest(pivots, x, s)
        return found.join(x.df.select(F.col("point_id").alias("neighbor_id"), "value"), "neighbor_id").select(F.col("query_id").alias("pivot_id"), F.col("dist").alias("owner_dist"), F.col("neighbor_id").alias("point_id"), "value")
    r_ids, r_vals = bf.collected(pivots)
    cut = _holding(x, r_vals, _cutoffs(x, r_vals, s, n), min(s, n))
    metric = x.metric
    schema = T.StructType([T.StructField("pivot_id", pivots.id_type), T.StructField("owner_dist", T.DoubleType()), *x.df.select("point_id", "value").schema.fields])

    def near(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = bf.matrix(batch.column(1))
            if not len(values):
                continue
            step = max(1, CELLS // len(values))
            for at in range(0, len(r_ids), step):
                block = metric.block(r_vals[at : at + step], values)
                limit = cut[at : at + step]
                if s < block.shape[1]:
                    # A batch's own s-th distance bounds what it can add to a list.
                    limit = np.minimum(limit, np.partition(block, s - 1, axis=1)[:, s - 1])
                row, col = np.divmod(np.flatnonzero(block <= limit[:, None]), block.shape[1])
                take = pa.array(col.astype(np.int64))
                yield pa.RecordBatch.from_arrays([bf.as_arrow(r_ids[at + row]), pa.array(block[row, col]), batch.column(0).take(take), batch.column(1).take(take)], schema.names)

    order = Window.partitionBy("pivot_id").orderBy("owner_dist", "point_id")
    ranked = x.df.select("point_id", "value").mapInArrow(near, schema).withColumn("position", F.row_number().over(order))
    return ranked.where(F.col("position") <= s).drop("position")


def nearest_values(pivots: PointSet, x: PointSet, s: int, n: int, rows: PointSet) -> DataFrame:
    """``nearest_points`` by value: ``x`` has each value of the ``n`` rows once, under its least id, with its ``copies``.

    A value is on a list if its least id is among the s nearest rows.  Only where
    several values share the distance at which a list ends do the ids of their
    rows decide, and those rows are looked up.
    """
    from nearfield.operators import storage

    r_ids, r_vals = bf.collected(pivots)
    cut = _holding(x, r_vals, _cutoffs(x, r_vals, s, n), min(s, n))
    metric = x.metric
    source = x.df.select("point_id", "value", "copies")
    schema = T.StructType([T.StructField("pivot_id", pivots.id_type), T.StructField("owner_dist", T.DoubleType()), *source.schema.fields])

    def near(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = bf.as_arrow(r_ids)

        def listed(table: pa.Table, row: np.ndarray, col: np.ndarray, dist: np.ndarray) -> Iterator[pa.RecordBatch]:
            for at in range(0, len(row), 1 << 14):
                some, take = slice(at, at + (1 << 14)), pa.array(col[at : at + (1 << 14)].astype(np.int64))
                yield pa.RecordBatch.from_arrays([names.take(pa.array(row[some])), pa.array(dist[some]), *[c.take(take).combine_chunks() for c in table.columns]], schema.names)

        for slab in bf.slabs(batches, bf.slab_rows(metric)):
            slab = slab.combine_chunks()
            values = bf.matrix(slab.column(1))
            boxed = r_vals.shape[1] <= PRODUCT and Boxes.fits(metric, r_vals, values)
            if boxed:
                for row, col, dist in Boxes(metric, values).within(r_vals, np.where(np.isfinite(cut), cut, -1.0)):
                    yield from listed(slab, row, col, dist)
            left = np.flatnonzero(~np.isfinite(cut)) if boxed else np.arange(len(cut))
            step = max(1, CELLS // max(1, len(values)))
            for at in range(0, len(left), step):
                some = left[at : at + step]
                block, limit = metric.block(r_vals[some], values), cut[some]
                if s < block.shape[1] and not np.isfinite(limit).all():
                    # A value stands for one row at least, so a slab's own s-th distance bounds what it can add to a list.
                    limit = np.minimum(limit, np.partition(block, s - 1, axis=1)[:, s - 1])
                row, col = np.divmod(np.flatnonzero(block <= limit[:, None]), block.shape[1])
                yield from listed(slab, some[row], col, block[row, col])

    own = Window.partitionBy("pivot_id").orderBy("owner_dist")
    tied = Window.partitionBy("pivot_id", "owner_dist")
    ranked = source.mapInArrow(near, schema).withColumn("closed", F.sum("copies").over(own.rangeBetween(Window.unboundedPreceding, Window.currentRow)))
    ranked = ranked.withColumn("before", F.col("closed") - F.sum("copies").over(tied)).where(F.col("before") < s)
    ranked = ranked.withColumn("open", (F.col("closed") > s) & (F.count(F.lit(1)).over(tied) > 1))
    ranked = storage.at_rest(PointSet(ranked, metric)).df
    listed = ["pivot_id", "owner_dist", "point_id", "value"]
    sure, edge = ranked.where(~F.col("open")).select(listed), ranked.where("open")
    if edge.isEmpty():
        return sure
    met = rows.df.select(F.col("point_id").alias("member"), "value").join(F.broadcast(edge), "value")
    placed = met.withColumn("place", F.row_number().over(Window.partitionBy("pivot_id").orderBy("member")))
    return sure.unionByName(placed.where((F.col("member") == F.col("point_id")) & (F.col("before") + F.col("place") <= s)).select(listed))


def _cutoffs(x: PointSet, r_vals: np.ndarray, s: int, n: int, sample: int = 4096) -> np.ndarray:
    """A radius for each pivot that holds s points with a margin of four deviations; infinite where a sample can't tell."""
    if n < 16 * sample or not len(r_vals):
        return np.full(len(r_vals), np.inf)
    from nearfield.operators.sampling import fixed_pivots

    _, seen = bf.collected(fixed_pivots(x, sample, seed=99))
    share = s / n * len(seen)
    place = int(share + 4 * share**0.5 + 4)
    if place >= len(seen):
        return np.full(len(r_vals), np.inf)
    return np.array([np.partition(x.metric.block(r_vals[i : i + 1], seen)[0], place)[place] for i in range(len(r_vals))])


def _holding(x: PointSet, r_vals: np.ndarray, cut: np.ndarray, least: int) -> np.ndarray:
    """The radii, infinite for pivots where fewer than ``least`` points of X are within."""
    if not np.isfinite(cut).any():
        return cut
    metric, weighed = x.metric, "copies" in x.df.columns

    def within(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = np.zeros(len(cut), np.int64)
        for slab in bf.slabs(batches, bf.slab_rows(metric)):
            values = bf.matrix(slab.column(1))
            copies = slab.column(2).to_numpy() if weighed else np.ones(len(values), np.int64)
            for row, col in _inside(metric, r_vals, cut, values):
                np.add.at(held, row, copies[col])
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(cut), dtype=np.int32)), pa.array(held)], ["pivot", "held"])

    held = np.zeros(len(cut), np.int64)
    for r in x.df.select("point_id", "value", *["copies"] * weighed).mapInArrow(within, "pivot int, held long").groupBy("pivot").agg(F.sum("held").alias("held")).collect():
        held[r.pivot] = r.held
    return np.where(held < least, np.inf, cut)


def _inside(metric, r_vals: np.ndarray, cut: np.ndarray, values: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(pivot, row) of all pairs within the pivot's radius, by boxes where the metric and finite radii allow."""
    narrow = r_vals.shape[1] <= PRODUCT and Boxes.fits(metric, r_vals, values)
    if narrow:
        for row, col, _ in Boxes(metric, values).within(r_vals, np.where(np.isfinite(cut), cut, -1.0)):
            yield row, col
    left = np.flatnonzero(~np.isfinite(cut)) if narrow else np.arange(len(cut))
    step = max(1, CELLS // max(1, len(values)))
    for at in range(0, len(left), step):
        some = left[at : at + step]
        block = metric.block(r_vals[some], values)
        row, col = np.divmod(np.flatnonzero(block <= cut[some, None]), block.shape[1])
        yield some[row], col


def append(cover: Cover, more: PointSet) -> Cover:
    """New points join the lists of their nearest pivots; radii grow where they must."""
    fresh = owners(more, cover.pivot_set).select("pivot_id", "owner_dist", "point_id", "value")
    grown = radii(fresh).select("pivot_id", F.col("psi").alias("p2"), F.col("list_size").alias("n2"))
    pivots = cover.pivots.join(grown, "pivot_id", "left").select(
        "pivot_id", "value", F.greatest("psi", F.coalesce("p2", F.lit(0.0))).alias("psi"), (F.col("list_size") + F.coalesce("n2", F.lit(0))).alias("list_size"), "alive"
    )
    return Cover(pivots, cover.lists.unionByName(fresh), PointSet(cover.points.df.unionByName(more.df.select(cover.points.df.columns)), more.metric), cover.layout)


def delete(cover: Cover, ids: DataFrame) -> Cover:
    """Points leave their lists.  A radius stays an upper bound; a deleted pivot goes on routing but is no answer."""
    gone = ids.select("point_id").distinct()
    lists = cover.lists.join(gone, "point_id", "left_anti").select(cover.lists.columns)
    sizes = lists.groupBy("pivot_id").agg(F.count(F.lit(1)).alias("n"))
    dead = gone.select(F.col("point_id").alias("pivot_id"), F.lit(True).alias("dead"))
    pivots = cover.pivots.join(sizes, "pivot_id", "left").join(dead, "pivot_id", "left")
    left = pivots.select("pivot_id", "value", "psi", F.coalesce("n", F.lit(0)).alias("list_size"), (F.col("alive") & F.col("dead").isNull()).alias("alive"))
    return Cover(left, lists, PointSet(cover.points.df.join(gone, "point_id", "left_anti"), cover.points.metric), cover.layout)


def describe(cover: Cover) -> DataFrame:
    """One row: pivots, entries, distinct points, largest and mean list, largest radius."""
    lists = cover.lists.agg(F.count(F.lit(1)).alias("entries"), F.count_distinct("point_id").alias("covered"))
    pivots = cover.pivots.agg(F.count(F.lit(1)).alias("n_pivots"), F.max("list_size").alias("largest_list"), F.round(F.avg("list_size"), 6).alias("mean_list"), F.round(F.max("psi"), 6).alias("largest_psi"))
    return pivots.join(lists, F.lit(True)).select("n_pivots", "entries", "covered", "largest_list", "mean_list", "largest_psi")
