"""Locality-sensitive hashing for l2, hashed by Spark's own library: the other probabilistic search."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.ml.feature import BucketedRandomProjectionLSH
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nearfield.operators import bruteforce as bf
from nearfield.operators.kernels import Boxes, Near
from nearfield.sources.points import PointSet


def search(q: PointSet, x: PointSet, eps: float, bucket: float, tables: int = 4, k: int = 1, seed: int = 3) -> DataFrame:
    """The k nearest found nearer than ``eps`` among rows that share a bucket; queries with none are missing."""
    named = [p.df.select("point_id", "value", array_to_vector("value").alias("features")) for p in (q, x)]
    model = BucketedRandomProjectionLSH(inputCol="features", outputCol="hashes", bucketLength=bucket, numHashTables=tables, seed=seed).fit(named[1])
    rows = q.df.count() if k == 1 and x.metric.name == "l2" else None
    if rows is not None and bf.bytes_of(rows, q) + 8 * tables * rows <= bf.BROADCAST_BYTES:
        codes = F.array(*[vector_to_array(F.col("hashes")[i])[0] for i in range(tables)])
        return bf.reduce_rows(_in_buckets(q, x, eps, *[model.transform(n).select("point_id", "value", codes.alias("codes")) for n in named]), 1)
    met = model.approxSimilarityJoin(*named, eps, distCol="dist")
    return bf.reduce_top_k(met.select(F.col("datasetA.point_id").alias("query_id"), F.col("datasetB.point_id").alias("neighbor_id"), "dist"), k)


def _in_buckets(q: PointSet, x: PointSet, eps: float, asking: DataFrame, hashed: DataFrame) -> DataFrame:
    """Each task's nearest row of any shared bucket: queries are sent with their hashes, and a bucket is searched by boxes, never as pairs."""
    schema, metric = bf.schema_of(q, x), q.metric
    table = asking.toArrow()
    names, q_vals, q_codes = table.column("point_id").combine_chunks(), bf.matrix(table.column("value")), bf.matrix(table.column("codes"))

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        limit = np.full(len(q_vals), np.nextafter(eps, -np.inf))
        for slab in bf.slabs(batches, bf.slab_rows(metric)) if len(q_vals) else ():
            slab = slab.take(pa.array(np.argsort(bf.ids_of(slab.column(0)), kind="stable")))
            values, codes = bf.matrix(slab.column(1)), bf.matrix(slab.column(2))
            place, dist = np.full(len(q_vals), len(values), np.int64), np.full(len(q_vals), np.inf)
            for t in range(codes.shape[1]):
                for own, rows in _shared(q_codes[:, t], codes[:, t]):
                    near, far = _nearest(metric, q_vals[own], values[rows], limit[own])
                    near = rows[near]
                    # A farther row of another bucket is dropped, an equal one of a smaller id is taken.
                    better = np.isfinite(far) & ((far < dist[own]) | ((far == dist[own]) & (near < place[own])))
                    place[own[better]], dist[own[better]] = near[better], far[better]
                limit = np.minimum(limit, dist)
            some = np.flatnonzero(np.isfinite(dist))
            yield pa.RecordBatch.from_arrays([names.take(pa.array(some)), slab.column(0).combine_chunks().take(pa.array(place[some])), pa.array(dist[some])], schema.names)

    return hashed.mapInArrow(search, schema)


def _shared(a: np.ndarray, b: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places in ``a`` and in ``b`` (both rising) of every code that both hold."""
    in_a, in_b = np.argsort(a, kind="stable"), np.argsort(b, kind="stable")
    for code in np.intersect1d(a, b):
        yield tuple(order[np.searchsorted(held[order], code, "left") : np.searchsorted(held[order], code, "right")] for order, held in ((in_a, a), (in_b, b)))


def _nearest(metric, a: np.ndarray, values: np.ndarray, limit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The nearest row of each within its limit; place 0 and an infinite distance if there is none."""
    if len(values) >= Boxes.GROUP and Boxes.fits(metric, a, values):
        place, dist = Boxes(metric, values).nearest(a, limit)
    else:
        place, dist = Near(metric, values).nearest(a)
    dist = np.where(dist <= limit, dist, np.inf)
    return np.where(np.isfinite(dist), place, 0), dist
