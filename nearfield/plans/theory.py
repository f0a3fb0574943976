"""Intrinsic dimension, parameter settings and predicted costs."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

from nearfield.operators import bruteforce as bf
from nearfield.operators import byvalue, storage
from nearfield.operators.sampling import fixed_pivots
from nearfield.sources.points import PointSet, spread


def exact_params(n: int, c: float, alpha: float | None = None) -> int:
    """Pivots of the exact cover: c^1.5 * sqrt(n), or alpha * sqrt(n); at least 1 and at most n / 2."""
    wanted = (alpha if alpha is not None else c**1.5) * math.sqrt(n)
    return max(1, min(int(wanted), max(1, n // 2)))


def oneshot_params(n: int, c: float, delta: float) -> tuple[int, int]:
    """Pivots and list length for success with chance 1 - delta: both c * sqrt(n * ln(1 / delta))."""
    wanted = int(math.ceil(c * math.sqrt(n) * math.sqrt(math.log(1 / delta))))
    return max(1, min(wanted, n)), max(1, min(wanted, n))


def oneshot_failure(n: int, n_r: float, s: float, c: float) -> float:
    """The bound on a one-shot miss; only the product of pivots and list length counts."""
    return math.exp(-n_r * s / (c * c * n))


def predicted_cost(method: str, n: int, c: float = 2.0, n_r: float | None = None, delta: float = 0.01, p: int = 1) -> float:
    """Distance evaluations for each query."""
    if method == "brute":
        return float(n)
    if method == "exact":
        n_r = exact_params(n, c) if n_r is None else n_r
        return n_r + c**3 * n / n_r
    if method == "oneshot":
        return float(sum(oneshot_params(n, c, delta)))
    if method == "tree":
        return c**6 * math.log(n)
    if method == "tree_chunked":
        return c**6 * math.log(max(math.e, n / p))
    raise ValueError(method)


def cost_table(spark: SparkSession, sizes: list[int], c: float, delta: float, p: int) -> DataFrame:
    methods = ("brute", "oneshot", "exact", "tree", "tree_chunked")
    rows = [(m, n, round(predicted_cost(m, n, c, delta=delta, p=p), 6)) for n in sizes for m in methods]
    return spark.createDataFrame(rows, "method string, n long, evaluations double")


def ball_counts(centres: PointSet, x: PointSet, radii: list[float]) -> DataFrame:
    """Points of X in the closed balls around each centre: ``centre_id, radius, points``.

    Each pair is measured once and counted for every radius it reaches, as often as the point has ``copies``, if X names them.
    """
    d = bf.within(centres, x, max(radii)) if x.is_vector else bf._nested(centres, x, "q", False)
    copies = F.lit(1)
    if "copies" in x.df.columns:
        d, copies = d.join(x.df.select(F.col("point_id").alias("neighbor_id"), "copies"), "neighbor_id"), F.col("copies")
    counts = d.groupBy("query_id").agg(*[F.sum(F.when(F.col("dist") <= r, copies).otherwise(0)).alias(f"r{i}") for i, r in enumerate(radii)])
    stacked = ", ".join(f"CAST({r!r} AS DOUBLE), CAST(r{i} AS LONG)" for i, r in enumerate(radii))
    return counts.selectExpr("query_id AS centre_id", f"stack({len(radii)}, {stacked}) AS (radius, points)").where("points > 0")


def exact_expansion_rate(x: PointSet) -> DataFrame:
    """``centre_id, rate``: the worst ratio of ball sizes at 2r and r over all r, for a small set.

    Ball sizes change only at distances that occur; just below each, the smaller
    ball has as many points as lie strictly nearer, so the worst ratio at a centre
    is read off the ranks.
    """
    if x.is_vector:
        return _rates_by_value(x)
    d = bf._nested(x, x, "q", False)
    by_dist = Window.partitionBy("query_id").orderBy("dist").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    ranked = d.withColumn("closed", F.count(F.lit(1)).over(by_dist)).select("query_id", "dist", "closed").distinct()
    # For a ball at radius r = dist / 2: the outer one has just reached dist.
    inner = ranked.select("query_id", F.col("dist").alias("inner"), F.col("closed").alias("few"))
    outer = ranked.select("query_id", F.col("dist").alias("outer"), F.col("closed").alias("many")).where("outer > 0")
    met = outer.join(inner, "query_id").where(F.col("inner") * 2 <= F.col("outer")).groupBy("query_id", "outer", "many").agg(F.max("few").alias("few"))
    return met.groupBy(F.col("query_id").alias("centre_id")).agg(F.max(F.col("many") / F.col("few")).alias("rate"))


def _rates_by_value(x: PointSet) -> DataFrame:
    """The same for vectors: each value's sorted distances to all values, weighed by copies, in the task that holds it."""
    own = storage.at_rest(PointSet(spread(byvalue.heads(x)).df, x.metric))
    held = own.df.select("value", "copies").toArrow()
    values, copies, metric, kind = bf.matrix(held.column("value")), held.column("copies").to_numpy(), x.metric, to_arrow_type(x.id_type)

    def rates(batches):
        for batch in batches:
            ids, rates = [], []
            for i, v in zip(batch.column(0).to_pylist(), bf.matrix(batch.column(1)), strict=True):
                d = metric.cells(v[None, :], values)
                order = np.argsort(d, kind="stable")
                d, closed = d[order], np.cumsum(copies[order])
                outer = np.flatnonzero(d > 0)
                if len(outer):
                    many, few = (closed[np.searchsorted(d, at, "right") - 1] for at in (d[outer], d[outer] / 2))
                    ids.append(i)
                    rates.append(float((many / few).max()))
            yield pa.RecordBatch.from_arrays([pa.array(ids, kind), pa.array(rates, pa.float64())], ["query_id", "rate"])

    schema = T.StructType([T.StructField("query_id", x.id_type), T.StructField("rate", T.DoubleType())])
    found = own.df.select("point_id", "value").mapInArrow(rates, schema)
    return byvalue.everyone(byvalue.members(x, own), found).select(F.col("query_id").alias("centre_id"), "rate")


def sampled_expansion_rate(x: PointSet, n_centres: int, radii: list[float], seed: int = 1) -> DataFrame:
    """One row: the largest ratio of ball sizes at 2r and r over sampled centres and the given radii, and its log."""
    centres = fixed_pivots(x, n_centres, seed)
    doubled = sorted({*radii, *(2 * r for r in radii)})
    counts = ball_counts(centres, x, doubled)
    inner = counts.select("centre_id", "radius", F.col("points").alias("few"))
    outer = counts.select("centre_id", (F.col("radius") / 2).alias("radius"), F.col("points").alias("many"))
    ratios = inner.where(F.col("radius").isin([float(r) for r in radii])).join(outer, ["centre_id", "radius"]).select((F.col("many") / F.col("few")).alias("ratio"))
    return ratios.agg(F.round(F.max("ratio"), 6).alias("rate"), F.round(F.log2(F.max("ratio")), 6).alias("dimension"), F.count(F.lit(1)).alias("balls"))


def grid(spark: SparkSession, side: int, d: int) -> DataFrame:
    """The integer points of a cube: ``point_id, value``."""
    coords = [(F.floor(F.col("id") / side**i) % side).cast("double") for i in range(d)]
    return spark.range(side**d).select(F.col("id").alias("point_id"), F.array(*coords).alias("value"))
