"""Metrics as one object each: a Column, a block kernel for numpy and DuckDB text.

All three forms of a metric compute the same sums in the same order, so answers
can be compared between engines after rounding.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Wider vectors are folded by a higher-order function instead of an unrolled sum.
UNROLL = 32


@dataclass(frozen=True)
class Metric:
    """``column(a, b)``, ``sql(a, b)`` and, for vectors, numpy forms of one metric.

    ``cells`` measures along the last axis of two arrays that broadcast;
    ``block(A, B)`` is every row of one side by every row of the other.
    """

    name: str
    column: Callable[[Column, Column], Column]
    sql: Callable[[str, str], str]
    cells: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None
    width: int | None = None

    def block(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        if self.name == "l2" and a.shape[1] > PRODUCT and len(b):
            return _l2_block(a, b)
        return self.cells(a[:, None, :], b[None, :, :])


def _terms(width: int, term: Callable[[int], Column]) -> Column:
    total = term(0)
    for i in range(1, width):
        total = total + term(i)
    return total


def _sql_terms(width: int, term: Callable[[int], str]) -> str:
    return "(" + " + ".join(term(i + 1) for i in range(width)) + ")"


def _by_axis(a: np.ndarray, b: np.ndarray, step: Callable[[np.ndarray], np.ndarray], fold=np.add) -> np.ndarray:
    """Fold ``step`` of the differences axis by axis, in the order of the unrolled sum."""
    total = step(a[..., 0] - b[..., 0])
    for i in range(1, a.shape[-1]):
        total = fold(total, step(a[..., i] - b[..., i]))
    return total


#: Wider vectors are measured by a matrix product.
PRODUCT = 8


def _l2_block(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Distances by squares and products; where these cancel, by the differences themselves.

    Both sides are centred first, and a cell under a millionth of its squares is
    measured again, so the relative error stays under a billionth and equal
    points are at distance 0.
    """
    centre = b.mean(axis=0)
    a, b = a - centre, b - centre
    squares = (a * a).sum(axis=1)[:, None] + (b * b).sum(axis=1)[None, :]
    out = squares - 2 * (a @ b.T)
    row, col = np.nonzero(out < 1e-6 * squares)
    for at in range(0, len(row), 1 << 16):
        i, j = row[at : at + (1 << 16)], col[at : at + (1 << 16)]
        out[i, j] = ((a[i] - b[j]) ** 2).sum(axis=1)
    return np.sqrt(np.maximum(out, 0))


def _folded(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The sum of products along the last axis, axis by axis."""
    total = a[..., 0] * b[..., 0]
    for i in range(1, a.shape[-1]):
        total = total + a[..., i] * b[..., i]
    return total


def l2(width: int) -> Metric:
    def column(a: Column, b: Column) -> Column:
        if width > UNROLL:
            return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))
        return F.sqrt(_terms(width, lambda i: (a[i] - b[i]) * (a[i] - b[i])))

    return Metric("l2", column, lambda a, b: f"sqrt({_sql_terms(width, lambda i: f'({a}[{i}]-{b}[{i}])*({a}[{i}]-{b}[{i}])')})", lambda a, b: np.sqrt(_by_axis(a, b, np.square)), width)


def l1(width: int) -> Metric:
    return Metric("l1", lambda a, b: _terms(width, lambda i: F.abs(a[i] - b[i])), lambda a, b: _sql_terms(width, lambda i: f"abs({a}[{i}]-{b}[{i}])"), lambda a, b: _by_axis(a, b, np.abs), width)


def linf(width: int) -> Metric:
    def column(a: Column, b: Column) -> Column:
        parts = [F.abs(a[i] - b[i]) for i in range(width)]
        return F.greatest(*parts) if width > 1 else parts[0]

    return Metric("linf", column, lambda a, b: "greatest(" + ", ".join(f"abs({a}[{i + 1}]-{b}[{i + 1}])" for i in range(width)) + ")", lambda a, b: _by_axis(a, b, np.abs, np.maximum), width)


def lp(width: int, p: float) -> Metric:
    """The p-norm of the difference; a metric for p of at least 1."""
    if p < 1:
        raise ValueError("a p-norm is a metric only for p >= 1")
    return Metric(
        f"l{p:g}",
        lambda a, b: F.pow(_terms(width, lambda i: F.pow(F.abs(a[i] - b[i]), F.lit(float(p)))), F.lit(1.0 / p)),
        lambda a, b: f"pow({_sql_terms(width, lambda i: f'pow(abs({a}[{i}]-{b}[{i}]), {float(p)})')}, {1.0 / p})",
        lambda a, b: _by_axis(a, b, lambda d: np.abs(d) ** p) ** (1.0 / p),
        width,
    )


def weighted_l2(weights: list[float]) -> Metric:
    w, width = [float(x) for x in weights], len(weights)
    return Metric(
        "weighted_l2",
        lambda a, b: F.sqrt(_terms(width, lambda i: F.lit(w[i]) * (a[i] - b[i]) * (a[i] - b[i]))),
        lambda a, b: f"sqrt({_sql_terms(width, lambda i: f'{w[i - 1]}*({a}[{i}]-{b}[{i}])*({a}[{i}]-{b}[{i}])')})",
        lambda a, b: np.sqrt(_by_axis(a * np.sqrt(w), b * np.sqrt(w), np.square)),
        width,
    )


def hamming(width: int) -> Metric:
    """The number of places that differ."""
    return Metric("hamming", lambda a, b: _terms(width, lambda i: (a[i] != b[i]).cast("double")), lambda a, b: _sql_terms(width, lambda i: f"({a}[{i}]<>{b}[{i}])::DOUBLE"), lambda a, b: _by_axis(a, b, lambda d: (d != 0).astype(float)), width)


def angular(width: int) -> Metric:
    """The angle between two vectors other than zero."""

    def column(a: Column, b: Column) -> Column:
        dot = _terms(width, lambda i: a[i] * b[i])
        norms = F.sqrt(_terms(width, lambda i: a[i] * a[i])) * F.sqrt(_terms(width, lambda i: b[i] * b[i]))
        return F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), dot / norms)))

    def sql(a: str, b: str) -> str:
        dot, na, nb = (_sql_terms(width, lambda i, x=x, y=y: f"{x}[{i}]*{y}[{i}]") for x, y in ((a, b), (a, a), (b, b)))
        return f"acos(greatest(-1.0, least(1.0, {dot} / (sqrt({na}) * sqrt({nb})))))"

    def cells(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        dot, aa, bb = (_folded(x, y) for x, y in ((a, b), (a, a), (b, b)))
        return np.arccos(np.clip(dot / (np.sqrt(aa) * np.sqrt(bb)), -1, 1))

    return Metric("angular", column, sql, cells, width)


def haversine() -> Metric:
    """Great-circle distance on the unit sphere of (latitude, longitude) in radians."""

    def column(a: Column, b: Column) -> Column:
        s, t = F.sin((a[0] - b[0]) / 2), F.sin((a[1] - b[1]) / 2)
        return F.lit(2.0) * F.asin(F.least(F.lit(1.0), F.sqrt(s * s + F.cos(a[0]) * F.cos(b[0]) * t * t)))

    def cells(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        s, t = (np.sin((a[..., i] - b[..., i]) / 2) for i in (0, 1))
        return 2 * np.arcsin(np.minimum(1, np.sqrt(s * s + np.cos(a[..., 0]) * np.cos(b[..., 0]) * t * t)))

    return Metric("haversine", column, lambda a, b: f"2.0*asin(least(1.0, sqrt(pow(sin(({a}[1]-{b}[1])/2), 2) + cos({a}[1])*cos({b}[1])*pow(sin(({a}[2]-{b}[2])/2), 2))))", cells, 2)


def edit() -> Metric:
    """Insertions, deletions and replacements between two strings."""
    return Metric("edit", lambda a, b: F.levenshtein(a, b).cast("double"), lambda a, b: f"levenshtein({a}, {b})::DOUBLE")


def jaccard() -> Metric:
    """One less the shared part of two token sets; two empty sets are equal."""

    def column(a: Column, b: Column) -> Column:
        union = F.size(F.array_union(a, b))
        return F.when(union == 0, F.lit(0.0)).otherwise(F.lit(1.0) - F.size(F.array_intersect(a, b)) / union)

    def sql(a: str, b: str) -> str:
        both = f"len(list_intersect({a}, {b}))"
        return f"CASE WHEN len({a}) + len({b}) = 0 THEN 0.0 ELSE 1.0 - {both}::DOUBLE / (len({a}) + len({b}) - {both}) END"

    return Metric("jaccard", column, sql)


def axiom_violations(points: DataFrame, metric: Metric, slack: float = 1e-9) -> DataFrame:
    """How many pairs or triples of a sample break each axiom: ``axiom, violations``.

    Vectors are counted by value: equal ones are measured once and weigh as many as
    they are, and triples are made and counted in numpy blocks, never as rows.  The
    work is the cube of the different values.  Metrics that are Columns alone join
    the sample three times, so theirs must be a stated one of at most a few hundred rows.
    """
    if metric.cells is not None:
        return _by_value(points, metric, slack)
    a = points.select(F.col("point_id").alias("ia"), F.col("value").alias("va"))
    b = points.select(F.col("point_id").alias("ib"), F.col("value").alias("vb"))
    pair = a.join(F.broadcast(b), F.lit(True)).select("ia", "ib", metric.column(F.col("va"), F.col("vb")).alias("d"), metric.column(F.col("vb"), F.col("va")).alias("e"))
    two = pair.agg(
        F.sum(((F.col("ia") == F.col("ib")) & (F.abs("d") > slack)).cast("long")).alias("identity"),
        F.sum((F.abs(F.col("d") - F.col("e")) > slack).cast("long")).alias("symmetry"),
        F.sum((F.col("d") < -slack).cast("long")).alias("sign"),
    )
    ab, bc, ac = (pair.select(F.col("ia").alias(x), F.col("ib").alias(y), F.col("d").alias(x + y)) for x, y in ("ab", "bc", "ac"))
    three = ab.join(bc, "b").join(ac, ["a", "c"]).agg(F.sum((F.col("ac") > F.col("ab") + F.col("bc") + slack).cast("long")).alias("triangle"))
    return two.join(three, F.lit(True)).selectExpr(_STACKED)


_STACKED = "stack(4, 'identity', identity, 'symmetry', symmetry, 'sign', sign, 'triangle', triangle) AS (axiom, violations)"


def _by_value(points: DataFrame, metric: Metric, slack: float) -> DataFrame:
    from nearfield.operators import bruteforce as bf
    from nearfield.operators.kernels import CELLS

    spark = points.sparkSession
    known = points.where(F.col("value").isNotNull())
    held = known.groupBy("value").agg(F.count(F.lit(1)).alias("copies")).toArrow()
    values, copies = bf.matrix(held.column("value")), held.column("copies").to_numpy()
    n = len(copies)
    cells = metric.cells

    def count(batches):
        own = np.concatenate([np.empty(0, np.int64), *[b.column(0).to_numpy() for b in batches]])
        symmetry = sign = triangle = 0
        if len(own):
            there = np.stack([cells(values[i][None, :], values) for i in own])
            back = np.stack([cells(values, values[i][None, :]) for i in own])
            symmetry = int(((np.abs(there - back) > slack) @ copies) @ copies[own])
            sign = int(((there < -slack) @ copies) @ copies[own])
        step = max(1, CELLS // max(1, n))
        for at in range(0, n, step) if len(own) else ():
            onward = cells(values[at : at + step, None, :], values[None, :, :])
            for place, a in enumerate(own):
                broken = there[place][None, :] > onward + there[place, at : at + step, None] + slack
                if broken.any():
                    triangle += int(copies[a]) * int(copies[at : at + step] @ (broken @ copies))
        yield pa.RecordBatch.from_arrays([pa.array([x], pa.int64()) for x in (symmetry, sign, triangle)], ["symmetry", "sign", "triangle"])

    # A task holds the distances of its own rows to all: few rows where there are many values.
    tasks = max(1, min(n, max(spark.sparkContext.defaultParallelism, -(-n * n // (1 << 22)))))
    counts = spark.range(0, n, 1, tasks).mapInArrow(count, "symmetry long, sign long, triangle long")
    summed = counts.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("symmetry", "sign", "triangle")])
    same = known.select("point_id", F.col("value").alias("va")).join(known.select("point_id", F.col("value").alias("vb")), "point_id")
    identity = same.agg(F.coalesce(F.sum((F.abs(metric.column(F.col("va"), F.col("vb"))) > slack).cast("long")), F.lit(0)).alias("identity"))
    return identity.join(summed, F.lit(True)).selectExpr(_STACKED)
