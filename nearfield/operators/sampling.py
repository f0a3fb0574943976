"""Pivot sampling by the hash of an id: the same rows whatever the partitions, and in SQL."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from nearfield.sources.points import PointSet


def draw(point_id: Column, seed: int) -> Column:
    """Eight hexadecimal digits, even over all ids."""
    return F.substring(F.md5(F.concat(point_id.cast("string"), F.lit(f":{seed}"))), 1, 8)


def threshold(n_r: float, n: int) -> str:
    """The eight digits under which about ``n_r`` of ``n`` draws fall."""
    return format(min(int(n_r / max(1, n) * 2**32), 2**32 - 1), "08x")


def draw_sql(point_id: str, seed: int) -> str:
    return f"substr(md5({point_id}||':{seed}'),1,8)"


def bernoulli_pivots(x: PointSet, n_r: float, n: int, seed: int = 1) -> PointSet:
    """Each point on its own with chance n_r / n; the point of the least draw if no other."""
    d = draw(F.col("point_id"), seed)
    chosen = x.df.where(d < threshold(n_r, n))
    if chosen.isEmpty():
        chosen = x.df.orderBy(d, "point_id").limit(1)
    return PointSet(chosen, x.metric)


def fixed_pivots(x: PointSet, k: int, seed: int = 1) -> PointSet:
    """Exactly k points (all, if fewer): those of the least draws."""
    return PointSet(x.df.orderBy(draw(F.col("point_id"), seed), "point_id").limit(k), x.metric)


def nested_pivots(x: PointSet, n_r: float, n_top: float, n: int, seed: int = 1) -> tuple[PointSet, PointSet]:
    """Two levels: the top one is a part of the lower one, since it is the same draw with a lower threshold."""
    low = bernoulli_pivots(x, n_r, n, seed)
    return low, PointSet(_top(low.df, n_top, n, seed), x.metric)


def _top(low: DataFrame, n_top: float, n: int, seed: int) -> DataFrame:
    d = draw(F.col("point_id"), seed)
    top = low.where(d < threshold(n_top, n))
    return top if not top.isEmpty() else low.orderBy(d, "point_id").limit(1)


def farthest_first(x: PointSet, k: int) -> DataFrame:
    """k points, each the farthest from those before it, from the least id on: ``place, point_id``.

    One pass over X for each point: for a small k only.  Each pass holds the
    pivots so far as literals and takes the greatest least distance.
    """
    spark = x.df.sparkSession
    first = x.df.orderBy("point_id").limit(1).collect()
    chosen = first
    while first and len(chosen) < k:
        near = [x.metric.column(F.array(*[F.lit(float(v)) for v in r.value]) if x.is_vector else F.lit(r.value), F.col("value")) for r in chosen]
        gap = F.least(*near) if len(near) > 1 else near[0]
        row = x.df.select("point_id", "value", gap.alias("gap")).orderBy(F.desc("gap"), "point_id").limit(1).collect()[0]
        if row.gap <= 0:
            break
        chosen = [*chosen, row]
    return spark.createDataFrame([(i, r.point_id) for i, r in enumerate(chosen)], f"place int, point_id {x.id_type.simpleString()}")
