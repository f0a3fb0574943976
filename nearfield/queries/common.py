"""Hold-out splits and the SQL fragments that the registered queries share."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nearfield.operators import byvalue, storage
from nearfield.operators import cover as cv
from nearfield.operators.sampling import bernoulli_pivots, draw_sql, threshold
from nearfield.sources import features
from nearfield.sources.points import PointSet, spread

#: Queries are the rows whose key is divisible by this; the database is every other row.
EVERY = 100
SEED = 1

Query = Callable[[SparkSession, str], DataFrame]


def key_sql(name: str) -> str:
    return "split_part(id, '-', 1)::BIGINT" if name.startswith(("line", "lift")) else "id"


def split(spark: SparkSession, sf_dir: str, name: str, every: int = EVERY) -> tuple[PointSet, PointSet]:
    """Queries and database of a feature set, as they are read."""
    return side(spark, sf_dir, name, True, every), side(spark, sf_dir, name, False, every)


def side(spark: SparkSession, sf_dir: str, name: str, asks: bool, every: int = EVERY) -> PointSet:
    """The queries of a feature set, or its database."""
    keep = lambda k: k % every == 0 if asks else ~(k % every == 0)
    if name.startswith(("line", "lift")):
        return features.SETS[name](spark, sf_dir, keep)
    return features.SETS[name](spark, sf_dir).where(keep(F.col("point_id")))


def held_out(spark: SparkSession, sf_dir: str, name: str, every: int = EVERY) -> tuple[PointSet, PointSet]:
    """Queries and database of a feature set."""
    q, x = split(spark, sf_dir, name, every)
    return spread(q, spark.sparkContext.defaultParallelism), spread(x)


def by_value(spark: SparkSession, sf_dir: str, name: str, every: int = EVERY) -> tuple[DataFrame, PointSet, PointSet]:
    """``query_id, head_id`` of all queries, and both sides with one row a value; lifted sets are lifted afterwards, from rows at rest."""
    width = int(name[4:]) if name.startswith("lift") else None
    asking, points = split(spark, sf_dir, features.lift_base(width) if width else name, every)
    q, x = storage.at_rest(byvalue.heads(asking)), spread(byvalue.heads(points))
    asked = byvalue.members(asking, q)
    q = spread(q, spark.sparkContext.defaultParallelism)
    return (asked, features.lift(q, width), features.lift(storage.at_rest(x), width)) if width else (asked, q, x)


def drawn(spark: SparkSession, sf_dir: str, name: str, alpha: float, seed: int, n: int, every: int = EVERY) -> PointSet:
    """The pivots that a cover of all ``n`` rows would draw, each value once."""
    points = side(spark, sf_dir, name, False, every)
    return storage.at_rest(byvalue.heads(bernoulli_pivots(points, n_pivots(n, alpha), n, seed)))


def oneshot_by_value(spark: SparkSession, sf_dir: str, name: str, x: PointSet, alpha: float) -> cv.Cover:
    """The one-shot cover of all rows of ``x``, whose values are listed once each: n_r = s = alpha * sqrt(rows)."""
    x = storage.at_rest(x)
    n = x.df.agg(F.sum("copies")).first()[0] or 0
    n_r = n_pivots(n, alpha)
    pivots = drawn(spark, sf_dir, name, alpha, SEED, n)
    rows = side(spark, sf_dir, name, False)
    return storage.settled(cv._covered(x, pivots, cv.nearest_values(pivots, x, n_r, n, rows), "oneshot"))


def metric_of(name: str):
    from nearfield.functions import metrics

    widths = {"line4": 4, "line8": 8, "orders2": 2, "events3": 3, "part2": 2, "cust2": 2, "supp2": 2, "emb64": 64, "doc54": 54, "part2_l1": 2}
    if name in ("urls", "passages"):
        return metrics.edit()
    if name == "doc_tokens":
        return metrics.jaccard()
    if name.startswith("lift"):
        return metrics.l2(int(name[4:]))
    if name.startswith("rp"):
        return metrics.l2(int(name[2:]))
    return metrics.l1(2) if name == "part2_l1" else metrics.l2(widths[name])


def sets_sql(name: str, every: int = EVERY, source: str | None = None) -> str:
    """CTEs ``s``, ``q`` and ``x``; materialised, so that each is computed once."""
    return f"s AS MATERIALIZED ({source or features.SQL[name]}), q AS MATERIALIZED (SELECT * FROM s WHERE {key_sql(name)} % {every} = 0), x AS MATERIALIZED (SELECT * FROM s WHERE {key_sql(name)} % {every} <> 0)"


def nearest_sql(name: str, k: int = 1, every: int = EVERY, metric=None, source: str | None = None, ranked: bool = False) -> str:
    """Brute force: the k nearest by (distance, id)."""
    d = (metric or metric_of(name)).sql("q.v", "x.v")
    if k == 1 and not ranked:
        return f"WITH {sets_sql(name, every, source)}, m AS (SELECT q.id AS query_id, min(struct_pack(d := {d}, i := x.id)) AS b FROM q, x GROUP BY q.id) SELECT query_id, b.i AS neighbor_id, round(b.d, 6) AS dist FROM m"
    return f"WITH {sets_sql(name, every, source)}, p AS (SELECT q.id AS query_id, x.id AS neighbor_id, {d} AS d FROM q, x) SELECT query_id, neighbor_id, round(d, 6) AS dist, row_number() OVER (PARTITION BY query_id ORDER BY d, neighbor_id)::INTEGER AS rank_no FROM p QUALIFY rank_no <= {k}"


def within_sql(name: str, eps: float, every: int = EVERY, metric=None) -> str:
    d = (metric or metric_of(name)).sql("q.v", "x.v")
    return f"WITH {sets_sql(name, every)}, p AS (SELECT q.id AS query_id, x.id AS neighbor_id, {d} AS d FROM q, x) SELECT query_id, neighbor_id, round(d, 6) AS dist FROM p WHERE d <= {eps}"


def pivots_sql(alpha: float, n_rows: str = "(SELECT count(*) FROM x)", seed: int = SEED) -> str:
    """CTE ``r``: the pivots of ``x`` for n_r = alpha * sqrt(n), by the same draw and threshold as in Spark.

    The threshold is floor(n_r / n * 2^32) in eight hexadecimal digits.
    """
    n_r = f"greatest(1, least(floor({float(alpha)} * sqrt({n_rows}))::BIGINT, {n_rows} // 2))"
    digits = f"lpad(lower(to_hex(least(floor({n_r}::DOUBLE / {n_rows} * 4294967296.0)::BIGINT, 4294967295))), 8, '0')"
    return f"r AS MATERIALIZED (SELECT id, v FROM x WHERE {draw_sql('id', seed)} < {digits})"


def n_pivots(n: int, alpha: float) -> int:
    return max(1, min(math.floor(alpha * math.sqrt(n)), n // 2))


def lists_sql(metric) -> str:
    """CTEs ``l`` (exact lists) and ``pv`` (pivots with psi and size) from ``x`` and ``r``."""
    d = metric.sql("x.v", "r.v")
    return f"o AS MATERIALIZED (SELECT x.id AS point_id, any_value(x.v) AS v, min(struct_pack(d := {d}, i := r.id)) AS b FROM x, r GROUP BY x.id), l AS MATERIALIZED (SELECT b.i AS pivot_id, b.d AS owner_dist, point_id, v FROM o), pv AS MATERIALIZED (SELECT r.id AS pivot_id, any_value(r.v) AS v, coalesce(max(owner_dist), 0.0) AS psi, count(point_id) AS list_size FROM r LEFT JOIN l ON l.pivot_id = r.id GROUP BY r.id)"


def rounded(found: DataFrame, *columns: str) -> DataFrame:
    picked = columns or ("query_id", "neighbor_id", "dist")
    return found.select(*[F.round(c, 6).alias(c) if c == "dist" else F.col(c) for c in picked])


__all__ = ["EVERY", "SEED", "Query", "draw_sql", "threshold"]
