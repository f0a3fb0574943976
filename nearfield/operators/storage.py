"""Covers at rest: lists clustered by pivot and owner distance.

Range clustering packs small lists together and splits large ones over files, and
row-group statistics on (pivot_id, owner_dist) let a reader skip what a bound
excludes.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nearfield.operators.cover import Cover, sized
from nearfield.sources.scratch import shared_dir
from nearfield.sources.points import PointSet


def cluster_by_pivot(lists: DataFrame, files: int | None = None) -> DataFrame:
    cut = lists.repartitionByRange(files, "pivot_id", "owner_dist") if files else lists.repartitionByRange("pivot_id", "owner_dist")
    return cut.sortWithinPartitions("pivot_id", "owner_dist")


def write_cover(cover: Cover, path: str, files: int | None = None, mode: str = "error") -> None:
    cluster_by_pivot(cover.lists, files).write.mode(mode).parquet(f"{path}/lists")
    cover.pivots.coalesce(1).write.mode(mode).parquet(f"{path}/pivots")


def read_cover(spark: SparkSession, path: str, points: PointSet, layout: str = "exact") -> Cover:
    return Cover(spark.read.parquet(f"{path}/pivots"), spark.read.parquet(f"{path}/lists"), points, layout)


def read_spans(spark: SparkSession, path: str, spans: list[tuple]) -> DataFrame:
    """Few-query mode: (pivot, lo, hi) literals are pushed to the files and skip row groups."""
    lists = spark.read.parquet(f"{path}/lists")
    wanted = F.lit(False)
    for pivot, lo, hi in spans:
        wanted = wanted | ((F.col("pivot_id") == pivot) & F.col("owner_dist").between(float(lo), float(hi)))
    return lists.where(wanted)


def chunked(lists: DataFrame, most: int) -> DataFrame:
    """Lists cut into chunks of about ``most`` entries by owner distance: ``pivot_id, chunk, ...``; a hot list becomes many keys.

    Chunk bounds come from approximate quantiles, so no list is sorted in one task.
    """
    sizes = lists.groupBy("pivot_id").agg(F.count(F.lit(1)).alias("n"), F.percentile_approx("owner_dist", F.array(*[F.lit(i / 16) for i in range(1, 16)])).alias("cuts"))
    met = lists.join(F.broadcast(sizes), "pivot_id")
    place = F.size(F.filter("cuts", lambda c: c < F.col("owner_dist")))
    return met.withColumn("chunk", F.when(F.col("n") > most, place).otherwise(0)).drop("n", "cuts")


def at_rest(points: PointSet) -> PointSet:
    """The set written once to the session's shared folder: counting, sampling and assigning then read rows that are made."""
    spark = points.df.sparkSession
    path = f"{shared_dir(spark)}/points-{uuid.uuid4().hex}"
    points.df.write.parquet(path)
    return PointSet(spark.read.schema(points.df.schema).parquet(path), points.metric)


def settled(cover: Cover, clustered: bool = False) -> Cover:
    """The cover written once to the session's shared folder: every point is assigned once, however often it is searched.

    ``clustered`` also sorts the lists by (pivot, owner distance) for a cover that is searched again and again.
    """
    spark = cover.lists.sparkSession
    path = f"{shared_dir(spark)}/cover-{uuid.uuid4().hex}"
    lists = cluster_by_pivot(cover.lists) if clustered else cover.lists
    lists.write.parquet(f"{path}/lists")
    kept = spark.read.schema(cover.lists.schema).parquet(f"{path}/lists")
    pivots = cover.pivots
    if cover.sampled is not None:
        # Radii and sizes of a fresh cover come from the lists as they were written.
        pivots = sized(cover.sampled, kept)
    pivots.coalesce(1).write.parquet(f"{path}/pivots")
    return Cover(spark.read.schema(pivots.schema).parquet(f"{path}/pivots"), kept, cover.points, cover.layout)
