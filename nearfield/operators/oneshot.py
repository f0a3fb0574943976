"""One-shot search: each query reads the list of its nearest pivot, or of its t nearest, and no other."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nearfield.operators import bruteforce as bf
from nearfield.operators import exact
from nearfield.operators.cover import Cover
from nearfield.sources.points import PointSet


def nearest_pivots(q: PointSet, cover: Cover, probes: int = 1) -> DataFrame:
    """``query_id, pivot_id, dist_qr`` of each query's nearest pivots."""
    found = bf.nearest(q, cover.pivot_set, probes)
    return found.select("query_id", F.col("neighbor_id").alias("pivot_id"), F.col("dist").alias("dist_qr"))


def _read(q: PointSet, cover: Cover, k: int | None, probes: int, eps: float = float("inf")) -> DataFrame:
    spans = nearest_pivots(q, cover, probes).join(cover.pivots.select("pivot_id", "psi"), "pivot_id").select("query_id", "pivot_id", "dist_qr", F.lit(0.0).alias("lo"), F.col("psi").alias("hi"))
    if not q.is_vector:
        return exact._by_join(q, spans, cover, eps)
    return exact._answers(exact.scan_lists(q, spans.withColumn("limit", F.lit(float(eps))), cover, k))


def search(q: PointSet, cover: Cover, k: int = 1, probes: int = 1) -> DataFrame:
    """``query_id, neighbor_id, dist, rank_no``; a neighbour on several lists counts once."""
    found = _read(q, cover, k, probes)
    return bf.reduce_rows(found, k) if q.is_vector else bf.reduce_top_k(found, k)


def within(q: PointSet, cover: Cover, eps: float, probes: int = 1) -> DataFrame:
    found = _read(q, cover, None, probes, eps)
    return found.select("query_id", "neighbor_id", "dist").distinct()


def certified(q: PointSet, cover: Cover) -> DataFrame:
    """Answers with ``certified``: true where dist_qr + dist < psi proves the answer exact.

    The list holds all points nearer to the pivot than its radius, and every
    point nearer to the query than the answer is among them.
    """
    near = nearest_pivots(q, cover, 1).join(cover.pivots.select("pivot_id", "psi"), "pivot_id")
    return search(q, cover).join(near, "query_id").select("query_id", "neighbor_id", "dist", ((F.col("dist_qr") + F.col("dist")) * (1 + exact.SLACK) < F.col("psi")).alias("certified"))


def then_exact(q: PointSet, oneshot: Cover, full: Cover) -> DataFrame:
    """One-shot answers where they are certified, exact search for the rest."""
    first = certified(q, oneshot)
    sure = first.where("certified").select("query_id", "neighbor_id", "dist", F.lit(1).alias("rank_no"))
    rest = q.df.join(sure.select(F.col("query_id").alias("point_id")), "point_id", "left_anti")
    return sure.unionByName(exact.search(PointSet(rest, q.metric), full))
