"""The experiment workloads: speedup over brute force, accuracy against speedup, trees, numbers of pivots.

Times are medians of warm runs into the ``noop`` sink; every row also has the
work, in distance evaluations for each query, which no machine changes.
"""

from __future__ import annotations

import time
from statistics import median

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nearfield.functions import projection
from nearfield.operators import bruteforce as bf
from nearfield.operators import cover as cv
from nearfield.operators import exact, oneshot, storage, trees
from nearfield.operators.sampling import fixed_pivots
from nearfield.plans import evaluate
from nearfield.plans.planner import choose_method
from nearfield.queries.common import SEED, held_out, n_pivots
from nearfield.sources import features
from nearfield.sources.points import PointSet, spread


def drained(df: DataFrame) -> float:
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def timed(make, runs: int = 3) -> float:
    """Median seconds of ``runs`` after one that warms up."""
    drained(make())
    return median(drained(make()) for _ in range(runs))


def settled(points: PointSet) -> PointSet:
    """The set in memory, so that a run measures the search and not the scan."""
    df = points.df.persist()
    df.count()
    return PointSet(df, points.metric)


def split(spark: SparkSession, sf_dir: str, name: str, every: int = 100) -> tuple[PointSet, PointSet]:
    """Queries and database of a set; ``rp<k>`` is the projection of the embeddings to k dimensions."""
    if name.startswith("rp"):
        points = projection.project(features.emb64(spark, sf_dir), int(name[2:]))
        asks = F.col("point_id") % every == 0
        return settled(points.where(asks)), settled(spread(points.where(~asks)))
    q, x = held_out(spark, sf_dir, name, every)
    return settled(q), settled(x)


def _built(make, x: PointSet) -> tuple[cv.Cover, float]:
    """A cover at rest, its lists sorted by (pivot, distance), and the seconds that it took."""
    began = time.perf_counter()
    c = storage.settled(make(), clustered=True)
    return c, time.perf_counter() - began


def speedup(spark: SparkSession, sf_dir: str, name: str, alpha: float = 4.0, oneshot_alpha: float = 1.0, every: int = 100, runs: int = 1) -> dict:
    """Exact and one-shot search against brute force on one set: seconds, work and mean rank.

    The one-shot cover has n_r = s = oneshot_alpha * sqrt(n), so its lists hold
    oneshot_alpha^2 * n entries.
    """
    q, x = split(spark, sf_dir, name, every)
    n, m = x.df.count(), q.df.count()
    n_r, n_o = n_pivots(n, alpha), n_pivots(n, oneshot_alpha)
    brute = timed(lambda: bf.nearest(q, x, rows_q=m, rows_x=n), runs)
    (e, e_build), (o, o_build) = _built(lambda: cv.build_exact(x, n_r, SEED, n), x), _built(lambda: cv.build_oneshot(x, n_o, n_o, SEED, n), x)
    t_exact, t_oneshot = timed(lambda: exact.search(q, e), runs), timed(lambda: oneshot.search(q, o), runs)
    examined = _examined(q, e, m)
    rank = evaluate.rank_summary(evaluate.rank_errors(oneshot.search(q, o), q, x)).first()
    return {
        "set": name, "n": n, "queries": m, "n_r": n_r, "oneshot_n_r": n_o, "brute_s": brute, "exact_s": t_exact, "oneshot_s": t_oneshot,
        "exact_build_s": e_build, "oneshot_build_s": o_build, "oneshot_entries": n_o * n_o, "exact_q_s": m / t_exact,
        "exact_speedup": brute / t_exact, "oneshot_speedup": brute / t_oneshot, "examined": examined, "exact_work_speedup": n / (n_r + examined),
        "oneshot_work_speedup": n / (2 * n_o), "oneshot_mean_rank": rank.mean_rank, "oneshot_exact_share": rank.exact_share,
    }


def _examined(q: PointSet, c: cv.Cover, m: int) -> float:
    """List distances for each query, as the kernels count them."""
    return (exact.measured(q, c).agg(F.sum("examined")).first()[0] or 0) / max(1, m)


def sweep_oneshot(spark: SparkSession, sf_dir: str, name: str, alphas=(0.25, 0.5, 1, 2, 4, 8, 16), every: int = 100) -> list[dict]:
    """Mean rank against work speedup for n_r = s = alpha * sqrt(n)."""
    q, x = split(spark, sf_dir, name, every)
    n, rows = x.df.count(), []
    for alpha in alphas:
        n_r = n_pivots(n, alpha)
        o = storage.settled(cv.build_oneshot(x, n_r, n_r, SEED, n))
        rank = evaluate.rank_summary(evaluate.rank_errors(oneshot.search(q, o), q, x)).first()
        rows.append({"set": name, "alpha": alpha, "n_r": n_r, "work_speedup": n / (2 * n_r), "mean_rank": rank.mean_rank, "exact_share": rank.exact_share})
    return rows


def tuned_oneshot(spark: SparkSession, sf_dir: str, name: str, target: float = 0.1, every: int = 100, rounds: int = 6) -> dict:
    """The smallest alpha (by bisection on its logarithm) whose mean rank is at most ``target``."""
    low, high, best = -3.0, 4.0, None
    for _ in range(rounds):
        mid = (low + high) / 2
        row = sweep_oneshot(spark, sf_dir, name, (2.0**mid,), every)[0]
        if row["mean_rank"] <= target:
            high, best = mid, row
        else:
            low = mid
    return best or row


def tree_comparison(spark: SparkSession, sf_dir: str, name: str, alpha: float = 4.0, every: int = 100) -> dict:
    """A net tree on one core against the exact cover on all: seconds and evaluations for each query."""
    q, x = split(spark, sf_dir, name, every)
    n, m = x.df.count(), q.df.count()
    c, _ = _built(lambda: cv.build_exact(x, n_pivots(n, alpha), SEED, n), x)
    t_tree, t_cover = timed(lambda: trees.search(trees.NetTree, q, x), 1), timed(lambda: exact.search(q, c), 1)
    seen = trees.search(trees.NetTree, q, x).agg(F.avg("evaluations")).first()[0]
    evaluations = c.pivots.count() + _examined(q, c, m)
    return {"set": name, "n": n, "queries": m, "tree_s": t_tree, "cover_s": t_cover, "ratio": t_tree / t_cover, "tree_evaluations": seen, "cover_evaluations": evaluations, "tree_q_s": m / t_tree, "cover_q_s": m / t_cover}


def sensitivity(spark: SparkSession, sf_dir: str, name: str, alphas=(0.5, 1, 2, 4, 8), every: int = 100) -> list[dict]:
    """Work of the exact search against the number of pivots."""
    q, x = split(spark, sf_dir, name, every)
    n, m, rows = x.df.count(), q.df.count(), []
    for alpha in alphas:
        n_r = n_pivots(n, alpha)
        c, _ = _built(lambda n_r=n_r: cv.build_exact(x, n_r, SEED, n), x)
        examined = _examined(q, c, m)
        rows.append({"set": name, "alpha": alpha, "n_r": n_r, "examined": examined, "work_speedup": n / (n_r + examined)})
    return rows


def explain_search(q: PointSet, x: PointSet, k: int = 1, sample: int = 64, cover: cv.Cover | None = None) -> tuple[int, int, float, str]:
    """Points, pivots, what a sample of the queries has to examine on the mean, and the method that follows."""
    n = x.df.count()
    n_r = n_pivots(n, 4.0)
    c = cover or storage.settled(cv.build_exact(x, n_r, SEED, n))
    seen = exact.measured(fixed_pivots(q, sample), c, k).agg(F.sum("examined")).first()[0] or 0
    mean = seen / max(1, min(sample, q.df.count()))
    return n, n_r, float(mean), choose_method(n, mean / max(1, n), True, n_r)


def auto_search(q: PointSet, x: PointSet, k: int = 1, sample: int = 64, wants_exact: bool = True) -> DataFrame:
    """Search by the method that a sample of the queries favours: exact cover, brute force or one-shot."""
    n = x.df.count()
    n_r = n_pivots(n, 4.0)
    if not wants_exact:
        return oneshot.search(q, storage.settled(cv.build_oneshot(x, n_r, max(k, n_r), SEED, n)), k)
    c = storage.settled(cv.build_exact(x, n_r, SEED, n))
    method = explain_search(q, x, k, sample, c)[-1]
    return bf.nearest(q, x, k, rows_x=n) if method == "brute" else exact.search(q, c, k)
