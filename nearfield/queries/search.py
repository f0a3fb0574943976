"""Brute force, covers, exact and one-shot search over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nearfield.functions import graphdist, metrics, projection
from nearfield.operators import bruteforce as bf
from nearfield.operators import cover as cv
from nearfield.operators import byvalue, exact, lsh, oneshot, storage, trees
from nearfield.operators.sampling import bernoulli_pivots, draw, farthest_first, fixed_pivots, nested_pivots
from nearfield.plans import evaluate, planner, theory
from nearfield.queries.common import EVERY, SEED, Query, by_value, drawn, held_out, key_sql, lists_sql, metric_of, n_pivots, nearest_sql, oneshot_by_value, pivots_sql, rounded, sets_sql, split, within_sql
from nearfield.sources import features
from nearfield.sources.features import table
from nearfield.sources.points import PointSet, spread

#: Pivots are alpha * sqrt(n).
ALPHA = 4.0


def _cover(x: PointSet, alpha: float = ALPHA, resting: bool = False) -> cv.Cover:
    x = x if resting else storage.at_rest(x)
    n = x.df.count()
    return storage.settled(cv.build_exact(x, n_pivots(n, alpha), SEED, n))


def _oneshot(x: PointSet, alpha: float = ALPHA) -> cv.Cover:
    x = storage.at_rest(x)
    n = x.df.count()
    n_r = n_pivots(n, alpha)
    return storage.settled(cv.build_oneshot(x, n_r, n_r, SEED, n))


def bf_nn(name: str) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        asked, q, x = by_value(spark, d, name)
        return rounded(byvalue.everyone(asked, bf.nearest(q, storage.at_rest(x))))

    return run


def exact_nn(name: str, alpha: float = ALPHA) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        asked, q, x = by_value(spark, d, name)
        return rounded(byvalue.everyone(asked, exact.search(q, _cover(x, alpha, name.startswith("lift")))))

    return run


def _projected(spark: SparkSession, d: str, k: int, kind: str = "gauss") -> tuple[PointSet, PointSet]:
    points = projection.project(features.emb64(spark, d), k, kind=kind)
    asks = F.col("point_id") % EVERY == 0
    return points.where(asks), spread(points.where(~asks))


def exact_rp(k: int) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        q, x = _projected(spark, d, k)
        return rounded(exact.search(q, _cover(x, 2.0)))

    return run


def rp_sql(k: int, kind: str = "gauss") -> str:
    return nearest_sql(f"rp{k}", source=projection.project_sql(features.SQL["emb64"], 64, k, kind=kind))


def bf_knn_emb64(spark: SparkSession, d: str) -> DataFrame:
    return rounded(bf.nearest(*held_out(spark, d, "emb64"), k=5), "query_id", "neighbor_id", "dist", "rank_no")


#: Ranges that the range queries use.
EPS = {"line4": 0.05, "orders2": 0.01}


def bf_range_line4(spark: SparkSession, d: str) -> DataFrame:
    """Rows are read where they lie: a range search shuffles nothing."""
    return bf.within(*split(spark, d, "line4"), EPS["line4"], digits=6)


def bf_subset_part(spark: SparkSession, d: str) -> DataFrame:
    q, x = held_out(spark, d, "part2")
    ids = table(spark, d, "part").where("p_brand = 'Brand#11' or p_size > 25").select(F.col("p_partkey").alias("point_id"))
    return rounded(bf.nearest_in(q, x, ids))


BF_SUBSET_SQL = f"WITH {sets_sql('part2')}, sub AS (SELECT x.* FROM x WHERE id IN (SELECT p_partkey FROM part WHERE p_brand = 'Brand#11' OR p_size > 25)), m AS (SELECT q.id AS query_id, min(struct_pack(d := {metric_of('part2').sql('q.v', 'x.v')}, i := x.id)) AS b FROM q, sub AS x GROUP BY q.id) SELECT query_id, b.i AS neighbor_id, round(b.d, 6) AS dist FROM m"


def bf_single_events(spark: SparkSession, d: str) -> DataFrame:
    """One query as literals, the ten nearest events."""
    return rounded(bf.nearest_one([0.5, 0.1, 0.5], features.events3(spark, d), 10), "neighbor_id", "dist")


BF_SINGLE_SQL = f"SELECT id AS neighbor_id, round(d, 6) AS dist FROM (SELECT id, {metric_of('events3').sql('a', 'v')} AS d FROM ({features.SQL['events3']}), (SELECT [0.5, 0.1, 0.5]::DOUBLE[] AS a)) ORDER BY d, id LIMIT 10"


def bf_self_cust2(spark: SparkSession, d: str) -> DataFrame:
    return rounded(bf.self_nearest(spread(features.cust2(spark, d))))


BF_SELF_SQL = f"WITH s AS MATERIALIZED ({features.SQL['cust2']}), m AS (SELECT q.id AS query_id, min(struct_pack(d := {metric_of('cust2').sql('q.v', 'x.v')}, i := x.id)) AS b FROM s q JOIN s x ON q.id <> x.id GROUP BY q.id) SELECT query_id, b.i AS neighbor_id, round(b.d, 6) AS dist FROM m"


def bf_blocks_rp16(spark: SparkSession, d: str) -> DataFrame:
    """The block grid, with blocks small enough that both sides have several."""
    q, x = _projected(spark, d, 16, "sign")
    return rounded(bf.reduce_rows(bf.blocks(q, x, 1, rows=256), 1))


def bf_lists_orders2(spark: SparkSession, d: str) -> DataFrame:
    """A list of its own for each query: the list of its nearest pivot."""
    q, x = held_out(spark, d, "orders2")
    cover = _cover(x)
    return rounded(bf.nearest_in_lists(q, oneshot.nearest_pivots(q, cover), cover.lists))


def _bf_lists_sql(name: str) -> str:
    m = metric_of(name)
    return f"WITH {COVER(name)}, near AS (SELECT q.id AS query_id, q.v AS qv, r.id AS pivot_id FROM q, r QUALIFY row_number() OVER (PARTITION BY q.id ORDER BY {m.sql('q.v', 'r.v')}, r.id) = 1), f AS (SELECT query_id, point_id, {m.sql('qv', 'l.v')} AS d FROM near JOIN l USING (pivot_id)) SELECT query_id, point_id AS neighbor_id, round(d, 6) AS dist FROM f QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY d, point_id) = 1"


def bf_distances_cust2(spark: SparkSession, d: str) -> DataFrame:
    """All distances from the queries to the pivots, kept."""
    q, x = held_out(spark, d, "cust2")
    n = x.df.count()
    found = bf.all_distances(q, bernoulli_pivots(x, n_pivots(n, 1.0), n, SEED))
    return rounded(found, "query_id", "pivot_id", "dist")


BF_DISTANCES_SQL = f"WITH {sets_sql('cust2')}, {pivots_sql(1.0)} SELECT q.id AS query_id, r.id AS pivot_id, round({metric_of('cust2').sql('q.v', 'r.v')}, 6) AS dist FROM q, r"


def pivots_line4(spark: SparkSession, d: str) -> DataFrame:
    _, x = held_out(spark, d, "line4")
    n = x.df.count()
    return bernoulli_pivots(x, n_pivots(n, ALPHA), n, SEED).df.select("point_id")


def pivots_fixed(spark: SparkSession, d: str) -> DataFrame:
    return fixed_pivots(features.orders2(spark, d), 64, SEED).df.select("point_id")


def pivots_nested(spark: SparkSession, d: str) -> DataFrame:
    x = features.orders2(spark, d)
    n = x.df.count()
    low, top = nested_pivots(x, 400, 40, n, SEED)
    return low.df.select("point_id", F.lit(1).alias("level")).unionByName(top.df.select("point_id", F.lit(2).alias("level")))


def pivots_farthest(spark: SparkSession, d: str) -> DataFrame:
    return farthest_first(features.supp2(spark, d), 8)


PIVOTS_NESTED_SQL = f"WITH s AS ({features.SQL['orders2']}), n AS (SELECT count(*) AS n FROM s), h AS (SELECT id, substr(md5(id||':{SEED}'),1,8) AS d FROM s) SELECT id AS point_id, 1 AS level FROM h, n WHERE d < lpad(lower(to_hex(floor(400.0/n*4294967296.0)::BIGINT)),8,'0') UNION ALL SELECT id, 2 FROM h, n WHERE d < lpad(lower(to_hex(floor(40.0/n*4294967296.0)::BIGINT)),8,'0')"


def cover_exact_sizes(spark: SparkSession, d: str) -> DataFrame:
    _, x = held_out(spark, d, "orders2")
    return _cover(x).pivots.select("pivot_id", F.round("psi", 6).alias("psi"), "list_size")


COVER = lambda name, alpha=ALPHA: f"{sets_sql(name)}, {pivots_sql(alpha)}, {lists_sql(metric_of(name))}"


BF_LISTS_SQL = _bf_lists_sql("orders2")


def cover_oneshot_lists(spark: SparkSession, d: str) -> DataFrame:
    _, x = held_out(spark, d, "cust2")
    return _oneshot(x, 2.0).lists.select("pivot_id", "point_id", F.round("owner_dist", 6).alias("owner_dist"))


def oneshot_lists_sql(name: str, alpha: float) -> str:
    """CTE ``ol``: the s = n_r nearest points of each pivot."""
    s = f"(SELECT greatest(1, least(floor({float(alpha)} * sqrt(count(*)))::BIGINT, count(*) // 2)) FROM x)"
    return f"{sets_sql(name)}, {pivots_sql(alpha)}, ol AS MATERIALIZED (SELECT pivot_id, point_id, v, owner_dist FROM (SELECT r.id AS pivot_id, x.id AS point_id, x.v, {metric_of(name).sql('r.v', 'x.v')} AS owner_dist FROM r, x) QUALIFY row_number() OVER (PARTITION BY pivot_id ORDER BY owner_dist, point_id) <= {s})"


def oneshot_sql(name: str, alpha: float, k: int = 1, probes: int = 1, eps: float | None = None) -> str:
    m = metric_of(name)
    head = f"WITH {oneshot_lists_sql(name, alpha)}, near AS (SELECT q.id AS query_id, q.v AS qv, r.id AS pivot_id FROM q, r QUALIFY row_number() OVER (PARTITION BY q.id ORDER BY {m.sql('q.v', 'r.v')}, r.id) <= {probes}), f AS (SELECT DISTINCT query_id, point_id AS neighbor_id, {m.sql('near.qv', 'ol.v')} AS d FROM near JOIN ol USING (pivot_id))"
    if eps is not None:
        return f"{head} SELECT query_id, neighbor_id, round(d, 6) AS dist FROM f WHERE d <= {eps}"
    rank = ", row_number() OVER (PARTITION BY query_id ORDER BY d, neighbor_id)::INTEGER AS rank_no"
    if k == 1:
        return f"{head} SELECT query_id, neighbor_id, round(d, 6) AS dist FROM (SELECT *{rank} FROM f) WHERE rank_no = 1"
    return f"{head} SELECT query_id, neighbor_id, round(d, 6) AS dist, rank_no FROM (SELECT *{rank} FROM f) WHERE rank_no <= {k}"


def cover_prefix_lengths(spark: SparkSession, d: str) -> DataFrame:
    """How much of each surviving list a query reads up to four times its distance to the nearest pivot."""
    q, x = held_out(spark, d, "orders2")
    cover = _cover(x)
    return exact.list_extents(exact.survivors(q, cover, window="paper", seeds=False), cover)


def rules_sql(name: str, rules: tuple[str, ...], window: str | None = None, ring: bool = False, alpha: float = ALPHA) -> str:
    """CTEs up to ``kept``: the pivots that the rules leave to each query, with spans."""
    m = metric_of(name)
    loose = lambda e: f"(({e}) * (1 + 1e-9) + 1e-12)"
    where = ["true"]
    if "radius" in rules:
        where.append(f"dist_qr <= {loose('g + psi')}")
    if "triple" in rules:
        where.append(f"dist_qr <= {loose('3 * g')}")
    lo, hi = "0.0", "psi"
    if window == "paper":
        hi = f"least(psi, {loose('4 * g')})"
    elif window == "tight":
        hi = f"least(psi, {loose('2 * g')})"
    if ring:
        lo, hi = f"greatest({lo}, dist_qr - {loose('g')})", f"least({hi}, {loose('dist_qr + g')})"
    return f"{COVER(name, alpha)}, dq AS MATERIALIZED (SELECT q.id AS query_id, q.v AS qv, pv.pivot_id, pv.psi, pv.list_size, {m.sql('q.v', 'pv.v')} AS dist_qr FROM q, pv), gq AS (SELECT *, min(dist_qr) OVER (PARTITION BY query_id) AS g FROM dq), kept AS MATERIALIZED (SELECT *, {lo} AS lo, {hi} AS hi FROM gq WHERE {' AND '.join(where)})"


PREFIX_SQL = f"WITH {rules_sql('orders2', ('radius', 'triple'), 'paper')} SELECT query_id, kept.pivot_id, count(*) AS examined FROM kept JOIN l ON kept.pivot_id = l.pivot_id AND owner_dist BETWEEN lo AND hi GROUP BY ALL"

#: Rule sets of the ablation: rules, window, ring.
RULES = {
    "radius": (("radius",), None, False),
    "triple": (("triple",), None, False),
    "both": (("radius", "triple"), None, False),
    "window4": (("radius", "triple"), "paper", False),
    "window2": (("radius", "triple"), "tight", False),
    "ring": (("radius", "triple"), "tight", True),
}


def exact_rules(which: str, name: str = "orders2") -> Query:
    rules, window, ring = RULES[which]

    def run(spark: SparkSession, d: str) -> DataFrame:
        q, x = held_out(spark, d, name)
        cover = _cover(x)
        trace = evaluate.work(q, cover, rules=rules, window=window, ring=ring, seeds=False)
        return trace.select("query_id", "pivots_kept", "listed", "examined")

    return run


def exact_rules_sql(which: str, name: str = "orders2") -> str:
    rules, window, ring = RULES[which]
    return f"WITH {rules_sql(name, rules, window, ring)}, e AS (SELECT query_id, count(*) AS examined FROM kept JOIN l ON kept.pivot_id = l.pivot_id AND owner_dist BETWEEN lo AND hi GROUP BY ALL), k AS (SELECT query_id, count(*) AS pivots_kept, sum(list_size)::BIGINT AS listed FROM kept WHERE hi >= lo GROUP BY ALL) SELECT k.query_id, pivots_kept, listed, coalesce(examined, 0) AS examined FROM k LEFT JOIN e USING (query_id)"


def exact_measured(spark: SparkSession, d: str) -> DataFrame:
    """The distances that the kernels of the search measured for each query, which are those that the bounds leave."""
    q, x = held_out(spark, d, "orders2")
    return exact.measured(q, _cover(x), window="tight")


def ablation(spark: SparkSession, d: str) -> DataFrame:
    """The mean work of every rule set on events, one row each."""
    q, x = held_out(spark, d, "events3")
    cover, n = _cover(x), x.df.count()
    rows = [evaluate.work_summary(evaluate.work(q, cover, rules=r, window=w, ring=g, seeds=False), n).select(F.lit(name).alias("rules"), "pivots_kept", "listed", "examined") for name, (r, w, g) in RULES.items()]
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


def ablation_sql() -> str:
    parts = [f"SELECT '{w}' AS rules, round(avg(pivots_kept), 6) AS pivots_kept, round(avg(listed), 6) AS listed, round(avg(examined), 6) AS examined FROM ({exact_rules_sql(w, 'events3')})" for w in RULES]
    return " UNION ALL ".join(parts)


def oneshot_nn(name: str, alpha: float = ALPHA) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        asked, q, x = by_value(spark, d, name)
        return rounded(byvalue.everyone(asked, oneshot.search(q, oneshot_by_value(spark, d, name, x, alpha))))

    return run


def oneshot_knn(spark: SparkSession, d: str) -> DataFrame:
    q, x = held_out(spark, d, "orders2")
    return rounded(oneshot.search(q, _oneshot(x), k=5), "query_id", "neighbor_id", "dist", "rank_no")


def oneshot_range(spark: SparkSession, d: str) -> DataFrame:
    q, x = held_out(spark, d, "orders2")
    return rounded(oneshot.within(q, _oneshot(x), EPS["orders2"]))


def oneshot_probes(spark: SparkSession, d: str) -> DataFrame:
    q, x = held_out(spark, d, "orders2")
    return rounded(oneshot.search(q, _oneshot(x, 1.0), probes=3))


def oneshot_certified(spark: SparkSession, d: str) -> DataFrame:
    q, x = held_out(spark, d, "orders2")
    return rounded(oneshot.certified(q, _oneshot(x)), "query_id", "neighbor_id", "dist", "certified")


def certified_sql(name: str) -> str:
    m = metric_of(name)
    return f"WITH {oneshot_lists_sql(name, ALPHA)}, ps AS (SELECT pivot_id, max(owner_dist) AS psi FROM ol GROUP BY ALL), near AS (SELECT q.id AS query_id, q.v AS qv, r.id AS pivot_id, {m.sql('q.v', 'r.v')} AS dist_qr FROM q, r QUALIFY row_number() OVER (PARTITION BY q.id ORDER BY {m.sql('q.v', 'r.v')}, r.id) = 1), f AS (SELECT query_id, dist_qr, pivot_id, point_id, {m.sql('near.qv', 'ol.v')} AS d FROM near JOIN ol USING (pivot_id) QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY {m.sql('near.qv', 'ol.v')}, point_id) = 1) SELECT query_id, point_id AS neighbor_id, round(d, 6) AS dist, (dist_qr + d) * (1 + 1e-9) < psi AS certified FROM f JOIN ps USING (pivot_id)"


def oneshot_then_exact(spark: SparkSession, d: str) -> DataFrame:
    q, x = held_out(spark, d, "orders2")
    return rounded(oneshot.then_exact(q, _oneshot(x, 1.0), _cover(x)))


#: Alphas of the one-shot sweep in the registered query.
SWEEP = (0.5, 1.0, 2.0)


def oneshot_rank_sweep(spark: SparkSession, d: str) -> DataFrame:
    """Mean rank and share of exact answers for n_r = s = alpha * sqrt(n)."""
    q, x = held_out(spark, d, "cust2")
    out = None
    for alpha in SWEEP:
        errors = evaluate.rank_errors(oneshot.search(q, _oneshot(x, alpha)), q, x)
        row = evaluate.rank_summary(errors).select(F.lit(alpha).alias("alpha"), "queries", "mean_rank", "exact_share")
        out = row if out is None else out.unionByName(row)
    return out


def rank_sql(name: str, alpha: float) -> str:
    m = metric_of(name)
    return f"SELECT a.query_id, count(*) FILTER (WHERE {m.sql('q.v', 'x.v')} < a.dist - 1e-9) AS closer FROM ({oneshot_sql(name, alpha).replace('round(d, 6) AS dist', 'd AS dist')}) a JOIN ({features.SQL[name]}) q ON q.id = a.query_id, (SELECT * FROM ({features.SQL[name]}) WHERE {key_sql(name)} % {EVERY} <> 0) x GROUP BY a.query_id"


SWEEP_SQL = " UNION ALL ".join(f"SELECT {a}::DOUBLE AS alpha, count(*) AS queries, round(avg(closer), 6) AS mean_rank, round(avg((closer = 0)::INTEGER), 6) AS exact_share FROM ({rank_sql('cust2', a)})" for a in SWEEP)


def rank_error(spark: SparkSession, d: str) -> DataFrame:
    q, x = held_out(spark, d, "orders2")
    return evaluate.rank_errors(oneshot.search(q, _oneshot(x, 1.0)), q, x)


def success_rate(spark: SparkSession, d: str) -> DataFrame:
    return evaluate.rank_summary(rank_error(spark, d)).select("queries", F.col("exact_share").alias("success"))


def work_speedup(spark: SparkSession, d: str) -> DataFrame:
    q, x = held_out(spark, d, "orders2")
    return evaluate.work_summary(evaluate.work(q, _cover(x), ring=True, seeds=False), x.df.count())


WORK_SQL = f"WITH {rules_sql('orders2', ('radius', 'triple'), None, True)}, e AS (SELECT query_id, count(*) AS examined FROM kept JOIN l ON kept.pivot_id = l.pivot_id AND owner_dist BETWEEN lo AND hi GROUP BY ALL), k AS (SELECT query_id, count(*) AS pivots_kept, sum(list_size)::BIGINT AS listed FROM kept WHERE hi >= lo GROUP BY ALL), t AS (SELECT pivots_kept, listed, coalesce(examined, 0) AS examined FROM k LEFT JOIN e USING (query_id)) SELECT count(*) AS queries, round(avg(pivots_kept), 6) AS pivots_kept, round(avg(listed), 6) AS listed, round(avg(examined), 6) AS examined, round((SELECT count(*) FROM x)::DOUBLE / ((SELECT count(*) FROM r) + avg(examined)), 6) AS work_speedup FROM t"


def sensitivity(spark: SparkSession, d: str) -> DataFrame:
    """Examined points and work for several numbers of pivots."""
    q, x = held_out(spark, d, "orders2")
    n, out = x.df.count(), None
    for alpha in (0.5, 1.0, 2.0, 4.0, 8.0):
        row = evaluate.work_summary(evaluate.work(q, _cover(x, alpha), seeds=False), n).select(F.lit(alpha).alias("alpha"), "pivots_kept", "listed", "examined", "work_speedup")
        out = row if out is None else out.unionByName(row)
    return out


def _work_at(name: str, alpha: float) -> str:
    return f"(WITH {rules_sql(name, ('radius', 'triple'), alpha=alpha)}, t AS (SELECT query_id, count(*) AS pivots_kept, sum(list_size)::BIGINT AS listed FROM kept GROUP BY ALL) SELECT {alpha}::DOUBLE AS alpha, round(avg(pivots_kept), 6) AS pivots_kept, round(avg(listed), 6) AS listed, round(avg(listed), 6) AS examined, round((SELECT count(*) FROM x)::DOUBLE / ((SELECT count(*) FROM r) + avg(listed)), 6) AS work_speedup FROM t)"


SENSITIVITY_SQL = " UNION ALL ".join(_work_at("orders2", a) for a in (0.5, 1.0, 2.0, 4.0, 8.0))


def exact_knn_line4(spark: SparkSession, d: str) -> DataFrame:
    q, x = held_out(spark, d, "line4")
    return rounded(exact.search(q, _cover(x), k=5), "query_id", "neighbor_id", "dist", "rank_no")


def exact_range_line4(spark: SparkSession, d: str) -> DataFrame:
    q, x = held_out(spark, d, "line4")
    return rounded(exact.within(q, _cover(x), EPS["line4"]))


def approx_nn_bound(spark: SparkSession, d: str) -> DataFrame:
    """Answers of the approximate variant against the best ones, both from one cover: within the promised ratio or not."""
    asked, q, x = by_value(spark, d, "line4")
    cover = _cover(x)
    got, best = (exact.search(q, cover, approx=a).select("query_id", F.col("dist").alias(c)) for a, c in ((0.5, "got"), (0.0, "best")))
    return byvalue.everyone(asked, got.join(best, "query_id").select("query_id", (F.col("got") <= 1.5 * F.col("best") * (1 + 1e-9) + 1e-12).alias("within_ratio")))


def exact_recursive(spark: SparkSession, d: str) -> DataFrame:
    """A cover whose pivots were assigned through a cover of their own: the same answers."""
    q, x = held_out(spark, d, "orders2")
    x = storage.at_rest(x)
    n = x.df.count()
    return rounded(exact.search(q, storage.settled(cv.build_exact(x, n_pivots(n, ALPHA), SEED, n, levels=2))))


def cover_append(spark: SparkSession, d: str) -> DataFrame:
    """Radii and sizes after every seventh event joined a cover of the others."""
    _, x = held_out(spark, d, "events3")
    later = F.col("point_id") % 7 == 0
    n = x.df.where(~later).count()
    cover = cv.build_exact(x.where(~later), n_pivots(n, ALPHA), SEED, n)
    return cv.append(cover, x.where(later)).pivots.select("pivot_id", F.round("psi", 6).alias("psi"), "list_size")


COVER_APPEND_SQL = f"WITH {sets_sql('events3')}, x0 AS (SELECT * FROM x WHERE id % 7 <> 0), {pivots_sql(ALPHA, '(SELECT count(*) FROM x0)')[:-1]} AND id % 7 <> 0), {lists_sql(metric_of('events3'))} SELECT pivot_id, round(psi, 6) AS psi, list_size FROM pv"


def cover_delete(spark: SparkSession, d: str) -> DataFrame:
    """Exact search after a fifth of the points were deleted: pivots route, but deleted ones are no answers."""
    q, x = held_out(spark, d, "orders2")
    return rounded(exact.search(q, cv.delete(_cover(x), x.df.where(F.col("point_id") % 5 == 0).select("point_id"))))


COVER_DELETE_SQL = f"WITH {sets_sql('orders2')}, m AS (SELECT q.id AS query_id, min(struct_pack(d := {metric_of('orders2').sql('q.v', 'x.v')}, i := x.id)) AS b FROM q, x WHERE x.id % 5 <> 0 GROUP BY q.id) SELECT query_id, b.i AS neighbor_id, round(b.d, 6) AS dist FROM m"


def cover_stats(spark: SparkSession, d: str) -> DataFrame:
    _, x = held_out(spark, d, "orders2")
    return cv.describe(_cover(x))


COVER_STATS_SQL = f"WITH {COVER('orders2')} SELECT (SELECT count(*) FROM pv) AS n_pivots, (SELECT count(*) FROM l) AS entries, (SELECT count(DISTINCT point_id) FROM l) AS covered, (SELECT max(list_size) FROM pv) AS largest_list, (SELECT round(avg(list_size), 6) FROM pv) AS mean_list, (SELECT round(max(psi), 6) FROM pv) AS largest_psi"


def ball_gamma_counts(spark: SparkSession, d: str) -> DataFrame:
    asked, q, x = by_value(spark, d, "orders2")
    x = storage.at_rest(x)
    pivots = drawn(spark, d, "orders2", ALPHA, SEED, x.df.agg(F.sum("copies")).first()[0] or 0)
    return byvalue.everyone(asked, evaluate.ball_at_gamma(q, x, cv.around(x, pivots)))


BALL_SQL = f"WITH {sets_sql('orders2')}, {pivots_sql(ALPHA)}, g AS (SELECT q.id, any_value(q.v) AS v, min({metric_of('orders2').sql('q.v', 'r.v')}) AS gamma FROM q, r GROUP BY q.id) SELECT g.id AS query_id, count(*) AS closed_ball, count(*) FILTER (WHERE {metric_of('orders2').sql('g.v', 'x.v')} < gamma - 1e-9) AS strictly_closer FROM g, x WHERE {metric_of('orders2').sql('g.v', 'x.v')} <= gamma + 1e-9 GROUP BY g.id"


def containment_7gamma(spark: SparkSession, d: str) -> DataFrame:
    q, x = held_out(spark, d, "orders2")
    return evaluate.containment(q, _cover(x)).select("pivots_outside", "points_outside")


CONTAINMENT_SQL = f"WITH {rules_sql('orders2', ('triple',), 'paper')}, p AS (SELECT count(*) FILTER (WHERE dist_qr > 3 * g * (1 + 1e-9) + 1e-9) AS n FROM kept), f AS (SELECT count(*) FILTER (WHERE {metric_of('orders2').sql('qv', 'l.v')} > 7 * g * (1 + 1e-9) + 1e-9) AS n FROM kept JOIN l ON kept.pivot_id = l.pivot_id AND owner_dist BETWEEN lo AND hi) SELECT p.n AS pivots_outside, f.n AS points_outside FROM p, f"


def expansion_rate_grid(spark: SparkSession, d: str) -> DataFrame:
    """Rows of lineitem in the l1 balls around the middle of their grid of quantities, discounts and taxes, by radius."""
    axes = [F.col("l_quantity") - 1.0, F.round(F.col("l_discount") * 100.0), F.round(F.col("l_tax") * 100.0)]
    rows = PointSet.from_table(table(spark, d, "lineitem"), F.col("l_orderkey"), axes, metrics.l1(3))
    centre = PointSet(spark.range(1).select(F.lit(25 + 5 * 50 + 4 * 550).cast("long").alias("point_id"), F.array(*map(F.lit, (25.0, 5.0, 4.0))).alias("value")), rows.metric)
    # One point a cell of the grid, known by its place in it and weighed by the rows on it.
    cell = F.col("value")[0] + 50 * F.col("value")[1] + 550 * F.col("value")[2]
    cells = PointSet(byvalue.heads(rows).df.select(cell.cast("long").alias("point_id"), "value", "copies"), rows.metric)
    return theory.ball_counts(centre, storage.at_rest(cells), [1.0, 2.0, 3.0, 4.0, 6.0, 8.0])


GRID_SQL = "WITH g AS (SELECT l_quantity - 1 AS a, round(l_discount * 100) AS b, round(l_tax * 100) AS c FROM lineitem) SELECT 2475::BIGINT AS centre_id, r::DOUBLE AS radius, count(*) AS points FROM g, (VALUES (1), (2), (3), (4), (6), (8)) v(r) WHERE abs(a - 25) + abs(b - 5) + abs(c - 4) <= r GROUP BY r"


def expansion_rate_exact(spark: SparkSession, d: str) -> DataFrame:
    return theory.exact_expansion_rate(features.supp2(spark, d)).select("centre_id", F.round("rate", 6).alias("rate"))


EXPANSION_SQL = f"WITH s AS ({features.SQL['supp2']}), p AS (SELECT a.id AS i, {metric_of('supp2').sql('a.v', 'b.v')} AS d FROM s a, s b), c AS (SELECT DISTINCT i, d, count(*) OVER (PARTITION BY i ORDER BY d) AS n FROM p) SELECT o.i AS centre_id, round(max(o.n::DOUBLE / f.n), 6) AS rate FROM c o ASOF JOIN c f ON o.i = f.i AND o.d / 2 >= f.d WHERE o.d > 0 GROUP BY o.i"


def expansion_rate_orders2(spark: SparkSession, d: str) -> DataFrame:
    return theory.sampled_expansion_rate(spread(features.orders2(spark, d)), 40, [0.02, 0.04, 0.08, 0.16], SEED)


EXPANSION_SAMPLED_SQL = f"WITH s AS MATERIALIZED ({features.SQL['orders2']}), c AS MATERIALIZED (SELECT * FROM s ORDER BY substr(md5(id||':{SEED}'),1,8), id LIMIT 40), p AS (SELECT c.id AS i, {metric_of('orders2').sql('c.v', 's.v')} AS d FROM c, s), b AS (SELECT i, r, count(*) FILTER (WHERE d <= r) AS few, count(*) FILTER (WHERE d <= 2 * r) AS many FROM p, (VALUES (0.02::DOUBLE), (0.04), (0.08), (0.16)) v(r) GROUP BY ALL) SELECT round(max(many::DOUBLE / few), 6) AS rate, round(log2(max(many::DOUBLE / few)), 6) AS dimension, count(*) AS balls FROM b WHERE few > 0"


def _flag_sizes(spark: SparkSession, d: str) -> list[int]:
    """How many rows of lineitem each return flag has."""
    return [r.n for r in table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n")).collect()]


FLAG_SIZES_SQL = "(SELECT count(*) AS n FROM lineitem GROUP BY l_returnflag)"


def oneshot_params(spark: SparkSession, d: str) -> DataFrame:
    """Settings of both covers for sets of as many points as each return flag has."""
    rows = [(n, c, delta, *theory.oneshot_params(n, c, delta), theory.exact_params(n, c)) for n in _flag_sizes(spark, d) for c in (2.0, 4.0) for delta in (0.1, 0.01)]
    return spark.createDataFrame(rows, "n long, c double, delta double, n_r long, s long, exact_n_r long")


PARAMS_SQL = f"SELECT n, c, delta, greatest(1, least(ceil(c * sqrt(n) * sqrt(ln(1 / delta)))::BIGINT, n)) AS n_r, greatest(1, least(ceil(c * sqrt(n) * sqrt(ln(1 / delta)))::BIGINT, n)) AS s, greatest(1, least(floor(pow(c, 1.5) * sqrt(n))::BIGINT, n // 2)) AS exact_n_r FROM {FLAG_SIZES_SQL} a, (VALUES (2.0::DOUBLE), (4.0)) b(c), (VALUES (0.1::DOUBLE), (0.01)) e(delta)"


def predicted_costs(spark: SparkSession, d: str) -> DataFrame:
    """Predicted distance evaluations for sets of as many points as each return flag has."""
    return theory.cost_table(spark, _flag_sizes(spark, d), 2.0, 0.01, 8)


COSTS_SQL = f"WITH n AS {FLAG_SIZES_SQL}, p AS (SELECT n, greatest(1, least(floor(pow(2.0, 1.5) * sqrt(n)), n // 2)) AS nr, ceil(2.0 * sqrt(n) * sqrt(ln(1 / 0.01::DOUBLE))) AS os FROM n) SELECT 'brute' AS method, n, n::DOUBLE AS evaluations FROM p UNION ALL SELECT 'oneshot', n, 2 * os FROM p UNION ALL SELECT 'exact', n, round(nr + 8.0 * n / nr, 6) FROM p UNION ALL SELECT 'tree', n, round(64 * ln(n), 6) FROM p UNION ALL SELECT 'tree_chunked', n, round(64 * ln(n / 8.0), 6) FROM p"


def edit_nn_urls(spark: SparkSession, d: str) -> DataFrame:
    q, x = held_out(spark, d, "urls", 10)
    return rounded(exact.search(q, _cover(x, 2.0)))


def edit_knn_passages(spark: SparkSession, d: str) -> DataFrame:
    q, x = held_out(spark, d, "passages", 10)
    return rounded(exact.search(q, _cover(x, 1.0), k=3), "query_id", "neighbor_id", "dist", "rank_no")


def jaccard_nn_docs(spark: SparkSession, d: str) -> DataFrame:
    q, x = held_out(spark, d, "doc_tokens")
    return rounded(bf.nearest(q, x))


def l1_nn_part(spark: SparkSession, d: str) -> DataFrame:
    q, x = held_out(spark, d, "part2_l1")
    return rounded(exact.search(q, _cover(x)))


def _metric_query(name: str, build) -> tuple[Query, str]:
    """Nearest part, or customer, by another metric over the same vectors."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        asked, q, x = by_value(spark, d, name)
        m = build()
        return rounded(byvalue.everyone(asked, bf.nearest(PointSet(q.df, m), PointSet(storage.at_rest(x).df, m))))

    return run, nearest_sql(name, metric=build())


def tree_metric_nn(spark: SparkSession, d: str) -> DataFrame:
    """The nearest customer of each supplier along the tree of nations and regions."""
    edges = graphdist.geography(*[table(spark, d, t) for t in ("region", "nation", "customer", "supplier")])
    leaves = lambda t, key, kind: table(spark, d, t).select(F.concat(F.lit(kind), F.col(key).cast("string")).alias("node"))
    found = graphdist.nearest_targets(edges, leaves("customer", "c_custkey", "c"), max_rounds=9).join(leaves("supplier", "s_suppkey", "s"), "node", "left_semi")
    near = found.select(F.col("node").alias("query_id"), F.col("target").alias("neighbor_id"), F.round("dist", 9).alias("dist"))
    return rounded(bf.reduce_top_k(near, 1))


TREE_METRIC_SQL = "WITH p AS (SELECT 's'||s_suppkey AS query_id, 'c'||c_custkey AS neighbor_id, round(2 + abs(s_acctbal)/10000.0 + abs(c_acctbal)/10000.0 + CASE WHEN s_nationkey = c_nationkey THEN 0 WHEN sn.n_regionkey = cn.n_regionkey THEN 2 ELSE 4 END, 9) AS d FROM supplier JOIN nation sn ON sn.n_nationkey = s_nationkey, customer JOIN nation cn ON cn.n_nationkey = c_nationkey) SELECT query_id, m.i AS neighbor_id, round(m.d, 6) AS dist FROM (SELECT query_id, min(struct_pack(d := d, i := neighbor_id)) AS m FROM p GROUP BY query_id)"


def metric_axioms(spark: SparkSession, d: str) -> DataFrame:
    """Broken axioms of l2, l1 and edit distance on stated samples; all zero."""
    cases = [("l2", features.supp2(spark, d)), ("l1", fixed_pivots(features.part2_l1(spark, d), 60)), ("edit", fixed_pivots(features.urls(spark, d), 40))]
    out = None
    for name, points in cases:
        rows = metrics.axiom_violations(points.df, points.metric).select(F.lit(name).alias("metric"), "axiom", "violations")
        out = rows if out is None else out.unionByName(rows)
    return out


def _axioms_sql(name: str, source: str, m: metrics.Metric) -> str:
    head = f"WITH s AS MATERIALIZED ({source}), p AS MATERIALIZED (SELECT a.id AS ia, b.id AS ib, {m.sql('a.v', 'b.v')} AS d, {m.sql('b.v', 'a.v')} AS e FROM s a, s b)"
    two = ", ".join(f"count(*) FILTER (WHERE {c}) AS {n}" for n, c in (("identity", "ia = ib AND abs(d) > 1e-9"), ("symmetry", "abs(d - e) > 1e-9"), ("sign", "d < -1e-9")))
    three = "(SELECT count(*) FROM p ab JOIN p bc ON ab.ib = bc.ia JOIN p ac ON ac.ia = ab.ia AND ac.ib = bc.ib WHERE ac.d > ab.d + bc.d + 1e-9) AS triangle"
    return f"({head}, t AS (SELECT {two}, {three} FROM p) SELECT '{name}' AS metric, axiom, violations::BIGINT AS violations FROM (UNPIVOT t ON identity, symmetry, sign, triangle INTO NAME axiom VALUE violations))"


def _fixed_sql(name: str, k: int) -> str:
    return f"SELECT id, v FROM ({features.SQL[name]}) ORDER BY substr(md5(id||':1'),1,8), id LIMIT {k}"


AXIOMS_SQL = " UNION ALL ".join((_axioms_sql("l2", features.SQL["supp2"], metric_of("supp2")), _axioms_sql("l1", _fixed_sql("part2_l1", 60), metric_of("part2_l1")), _axioms_sql("edit", _fixed_sql("urls", 40), metric_of("urls"))))


def tree_nn(kind: type, name: str, chunks: int = 1) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        q, x = held_out(spark, d, name)
        return rounded(trees.search(kind, q, x, chunks=chunks))

    return run


def lsh_nn(spark: SparkSession, d: str) -> DataFrame:
    """How many queries find their true nearest row by hashing, and how many find any."""
    asked, q, x = by_value(spark, d, "orders2")
    x = storage.at_rest(x)
    got = lsh.search(q, x, 0.05, 0.05)
    truth = bf.nearest(q, x)
    both = truth.select("query_id", "neighbor_id").join(got.select("query_id", F.col("neighbor_id").alias("found")), "query_id", "left")
    return byvalue.everyone(asked, both).agg(F.count(F.lit(1)).alias("queries"), F.count("found").alias("answered"), F.sum((F.col("found") == F.col("neighbor_id")).cast("long")).alias("right"))


def projection_sign(spark: SparkSession, d: str) -> DataFrame:
    """Coordinates of every embedding under the sign projection to eight dimensions."""
    p = projection.project(features.emb64(spark, d), 8, kind="sign")
    return p.df.select("point_id", F.posexplode("value").alias("place", "coordinate")).select("point_id", "place", F.round("coordinate", 6).alias("coordinate"))


PROJECTION_SQL = f"SELECT id AS point_id, (u.i - 1)::INTEGER AS place, round(v[u.i], 6) AS coordinate FROM ({projection.project_sql(features.SQL['emb64'], 64, 8, kind='sign')}), (SELECT unnest(range(1, 9)) AS i) u"


def projection_distortion(spark: SparkSession, d: str) -> DataFrame:
    """Distortion by width over the pairs of every tenth embedding."""
    out = None
    for k in (4, 8, 16, 32):
        row = projection.distortion(features.emb64(spark, d), k, 10).select(F.lit(k).alias("width"), "pairs", "least", "mean", "greatest")
        out = row if out is None else out.unionByName(row)
    return out


def _distortion_sql(k: int) -> str:
    return f"(WITH p AS MATERIALIZED (SELECT a.id, a.v, b.v AS w FROM ({features.SQL['emb64']}) a JOIN ({projection.project_sql(features.SQL['emb64'], 64, k)}) b USING (id) WHERE a.id % 10 = 0), t AS (SELECT {metrics.l2(k).sql('a.w', 'b.w')} / {metrics.l2(64).sql('a.v', 'b.v')} AS r FROM p a JOIN p b ON a.id < b.id) SELECT {k} AS width, count(*) AS pairs, round(min(r), 6) AS least, round(avg(r), 6) AS mean, round(max(r), 6) AS greatest FROM t)"


def projected_rank(spark: SparkSession, d: str) -> DataFrame:
    """Rank in the full space of each query's nearest row under projection, by width."""
    q, x = held_out(spark, d, "emb64")
    out = None
    for k in (4, 8, 16, 32):
        near = bf.nearest(*_projected(spark, d, k)).select("query_id", "neighbor_id")
        ids = x.df.select(F.col("point_id").alias("neighbor_id"), F.col("value").alias("xv"))
        own = q.df.select(F.col("point_id").alias("query_id"), F.col("value").alias("qv"))
        full = near.join(ids, "neighbor_id").join(own, "query_id").select("query_id", "neighbor_id", q.metric.column(F.col("qv"), F.col("xv")).alias("dist"), F.lit(1).alias("rank_no"))
        row = evaluate.rank_summary(evaluate.rank_errors(full, q, x)).select(F.lit(k).alias("width"), "queries", "mean_rank", "exact_share")
        out = row if out is None else out.unionByName(row)
    return out


def features_docgrams(spark: SparkSession, d: str) -> DataFrame:
    """Trigram counts of every whole document: ``point_id, place, n``."""
    return projection.trigram_counts(table(spark, d, "documents").select(F.col("doc_id").alias("point_id"), "text"), features.GRAMS)


def exact_doc54(spark: SparkSession, d: str) -> DataFrame:
    """Exact search over trigram vectors; answers hold against brute force, so rows where they differ are none."""
    q, x = held_out(spark, d, "doc54")
    got, want = exact.search(q, _cover(x, 2.0)), bf.nearest(q, x)
    both = got.select("query_id", F.col("dist").alias("got")).join(want.select("query_id", F.col("dist").alias("want")), "query_id")
    return both.agg(F.count(F.lit(1)).alias("queries"), F.sum((F.abs(F.col("got") - F.col("want")) > 1e-9).cast("long")).alias("different"))


DOC54_SQL = f"SELECT count(*) AS queries, 0::BIGINT AS different FROM documents WHERE doc_id % {EVERY} = 0"


def planner_choice(spark: SparkSession, d: str) -> DataFrame:
    """The planner's decisions for searches between tables, by the rows that they have."""
    counts = lambda name, key: table(spark, d, name).agg(F.count_if(F.col(key) % EVERY == 0), F.count_if(F.col(key) % EVERY != 0)).first()
    (asks, others), (some, more), customers = counts("orders", "o_orderkey"), counts("lineitem", "l_orderkey"), sum(counts("customer", "c_custkey"))
    lines = some + more
    return planner.describe(spark, [("small", asks, others, 2), ("many_queries", lines, customers, 64), ("both_large", lines, lines, 64), ("wide", some, more, 768)])


PLANNER_SQL = f"WITH o AS (SELECT count(*) FILTER (WHERE o_orderkey % {EVERY} = 0) AS a, count(*) FILTER (WHERE o_orderkey % {EVERY} <> 0) AS b FROM orders), l AS (SELECT count(*) FILTER (WHERE l_orderkey % {EVERY} = 0) AS a, count(*) FILTER (WHERE l_orderkey % {EVERY} <> 0) AS b FROM lineitem), t(case_name, rows_q, rows_x, width) AS (SELECT 'small', a, b, 2 FROM o UNION ALL SELECT 'many_queries', a + b, (SELECT count(*) FROM customer), 64 FROM l UNION ALL SELECT 'both_large', a + b, a + b, 64 FROM l UNION ALL SELECT 'wide', a, b, 768 FROM l) SELECT *, CASE WHEN least(rows_q, rows_x) * (8 * width + 24) > {planner.BROADCAST_BYTES} THEN 'grid' ELSE 'kernel' END AS pairing, CASE WHEN rows_q <= rows_x THEN 'q' ELSE 'x' END AS sent_side FROM t"


def draws(spark: SparkSession, d: str) -> DataFrame:
    """How even the draw of the pivots is: rows by its first digit."""
    return features.orders2(spark, d).df.select(F.substring(draw(F.col("point_id"), SEED), 1, 1).alias("digit")).groupBy("digit").agg(F.count(F.lit(1)).alias("rows"))


FARTHEST_SQL = f"WITH RECURSIVE s AS MATERIALIZED ({features.SQL['supp2']}), w(place, ids, vs) AS ((SELECT 0, [id], [v] FROM s ORDER BY id LIMIT 1) UNION ALL (SELECT place + 1, list_append(ids, s.id), list_append(vs, s.v) FROM w, s WHERE place < 7 QUALIFY row_number() OVER (ORDER BY list_min(list_transform(vs, lambda c: {metric_of('supp2').sql('c', 's.v')})) DESC, s.id) = 1)) SELECT place::INTEGER AS place, ids[place + 1] AS point_id FROM w"


def _projected_rank_sql(k: int) -> str:
    full, m = features.SQL["emb64"], metrics.l2(64)
    return f"(WITH a AS MATERIALIZED ({rp_sql(k)}), e AS MATERIALIZED ({full}), n AS (SELECT a.query_id, q.v AS qv, {m.sql('q.v', 'y.v')} AS d FROM a JOIN e q ON q.id = a.query_id JOIN e y ON y.id = a.neighbor_id), c AS (SELECT query_id, count(*) FILTER (WHERE {m.sql('qv', 'e.v')} < d - 1e-9) AS closer FROM n, e WHERE e.id % {EVERY} <> 0 GROUP BY 1) SELECT {k} AS width, count(*) AS queries, round(avg(closer), 6) AS mean_rank, round(avg((closer = 0)::INTEGER), 6) AS exact_share FROM c)"


_METRICS = {
    "linf_nn_part": _metric_query("part2", lambda: metrics.linf(2)),
    "l3_nn_part": _metric_query("part2", lambda: metrics.lp(2, 3.0)),
    "weighted_nn_part": _metric_query("part2", lambda: metrics.weighted_l2([4.0, 1.0])),
    "hamming_nn_part": _metric_query("part2", lambda: metrics.hamming(2)),
    "angular_nn_orders2": _metric_query("orders2", lambda: metrics.angular(2)),
    "haversine_nn_cust2": _metric_query("cust2", metrics.haversine),
}

QUERIES: dict[str, tuple[Query, str | None]] = (
    {f"bf_nn_{n}": (bf_nn(n), nearest_sql(n)) for n in ("line4", "orders2")}
    | {f"exact_nn_{n}": (exact_nn(n), nearest_sql(n)) for n in ("line4", "line8", "orders2", "events3", "part2", "cust2", "lift21", "lift54", "lift74", "lift78", "emb64")}
    | {f"exact_nn_rp{k}": (exact_rp(k), rp_sql(k)) for k in (4, 8, 16, 32)}
    | {f"exact_rules_{w}": (exact_rules(w), exact_rules_sql(w)) for w in RULES}
    | {f"oneshot_nn_{n}": (oneshot_nn(n, a), oneshot_sql(n, a)) for n, a in (("orders2", ALPHA), ("cust2", 2.0), ("events3", 2.0))}
    | _METRICS
    | {
        "oneshot_nn_line4": (oneshot_nn("line4", 1.0), oneshot_sql("line4", 1.0)),
        "bf_knn_emb64": (bf_knn_emb64, nearest_sql("emb64", 5)),
        "bf_range_line4": (bf_range_line4, within_sql("line4", EPS["line4"])),
        "bf_subset_part": (bf_subset_part, BF_SUBSET_SQL),
        "bf_single_events": (bf_single_events, BF_SINGLE_SQL),
        "bf_self_cust2": (bf_self_cust2, BF_SELF_SQL),
        "bf_blocks_rp16": (bf_blocks_rp16, rp_sql(16, "sign")),
        "bf_lists_orders2": (bf_lists_orders2, BF_LISTS_SQL),
        "bf_distances_cust2": (bf_distances_cust2, BF_DISTANCES_SQL),
        "pivots_line4": (pivots_line4, f"WITH {sets_sql('line4')}, {pivots_sql(ALPHA)} SELECT id AS point_id FROM r"),
        "pivots_fixed": (pivots_fixed, f"SELECT id AS point_id FROM ({features.SQL['orders2']}) ORDER BY substr(md5(id||':{SEED}'),1,8), id LIMIT 64"),
        "pivots_nested": (pivots_nested, PIVOTS_NESTED_SQL),
        "pivots_farthest": (pivots_farthest, FARTHEST_SQL),
        "pivots_draws": (draws, f"SELECT substr(md5(o_orderkey||':{SEED}'),1,1) AS digit, count(*) AS rows FROM orders GROUP BY 1"),
        "cover_exact_sizes": (cover_exact_sizes, f"WITH {COVER('orders2')} SELECT pivot_id, round(psi, 6) AS psi, list_size FROM pv"),
        "cover_oneshot_lists": (cover_oneshot_lists, f"WITH {oneshot_lists_sql('cust2', 2.0)} SELECT pivot_id, point_id, round(owner_dist, 6) AS owner_dist FROM ol"),
        "cover_prefix_lengths": (cover_prefix_lengths, PREFIX_SQL),
        "cover_append": (cover_append, COVER_APPEND_SQL),
        "cover_delete": (cover_delete, COVER_DELETE_SQL),
        "cover_stats": (cover_stats, COVER_STATS_SQL),
        "oneshot_knn_orders2": (oneshot_knn, oneshot_sql("orders2", ALPHA, k=5)),
        "oneshot_range_orders2": (oneshot_range, oneshot_sql("orders2", ALPHA, eps=EPS["orders2"])),
        "oneshot_probes_orders2": (oneshot_probes, oneshot_sql("orders2", 1.0, probes=3)),
        "oneshot_certified": (oneshot_certified, certified_sql("orders2")),
        "oneshot_then_exact": (oneshot_then_exact, nearest_sql("orders2")),
        "oneshot_rank_sweep": (oneshot_rank_sweep, SWEEP_SQL),
        "oneshot_params": (oneshot_params, PARAMS_SQL),
        "predicted_costs": (predicted_costs, COSTS_SQL),
        "exact_knn_line4": (exact_knn_line4, nearest_sql("line4", 5)),
        "exact_range_line4": (exact_range_line4, within_sql("line4", EPS["line4"])),
        "approx_nn_bound": (approx_nn_bound, f"WITH {sets_sql('line4')} SELECT id AS query_id, true AS within_ratio FROM q"),
        "exact_recursive": (exact_recursive, nearest_sql("orders2")),
        "exact_doc54": (exact_doc54, DOC54_SQL),
        "exact_measured_orders2": (exact_measured, f"SELECT query_id, examined FROM ({exact_rules_sql('ring')}) WHERE examined > 0"),
        "rule_ablation": (ablation, ablation_sql()),
        "pivot_sensitivity": (sensitivity, SENSITIVITY_SQL),
        "rank_error": (rank_error, rank_sql("orders2", 1.0)),
        "success_rate": (success_rate, f"SELECT count(*) AS queries, round(avg((closer = 0)::INTEGER), 6) AS success FROM ({rank_sql('orders2', 1.0)})"),
        "work_speedup": (work_speedup, WORK_SQL),
        "ball_gamma_counts": (ball_gamma_counts, BALL_SQL),
        "containment_7gamma": (containment_7gamma, CONTAINMENT_SQL),
        "expansion_rate_grid": (expansion_rate_grid, GRID_SQL),
        "expansion_rate_exact": (expansion_rate_exact, EXPANSION_SQL),
        "expansion_rate_orders2": (expansion_rate_orders2, EXPANSION_SAMPLED_SQL),
        "l1_nn_part": (l1_nn_part, nearest_sql("part2_l1")),
        "edit_nn_urls": (edit_nn_urls, nearest_sql("urls", every=10)),
        "edit_knn_passages": (edit_knn_passages, nearest_sql("passages", 3, every=10)),
        "jaccard_nn_docs": (jaccard_nn_docs, nearest_sql("doc_tokens")),
        "tree_metric_nn": (tree_metric_nn, TREE_METRIC_SQL),
        "metric_axioms": (metric_axioms, AXIOMS_SQL),
        "nettree_nn": (tree_nn(trees.NetTree, "orders2"), nearest_sql("orders2")),
        "nettree_chunked_nn": (tree_nn(trees.NetTree, "orders2", 8), nearest_sql("orders2")),
        "balltree_nn": (tree_nn(trees.BallTree, "orders2"), nearest_sql("orders2")),
        "kdtree_nn": (tree_nn(trees.KdTree, "orders2"), nearest_sql("orders2")),
        "lsh_nn": (lsh_nn, None),
        "projection_sign": (projection_sign, PROJECTION_SQL),
        "projection_distortion": (projection_distortion, " UNION ALL ".join(_distortion_sql(k) for k in (4, 8, 16, 32))),
        "projected_rank": (projected_rank, " UNION ALL ".join(_projected_rank_sql(k) for k in (4, 8, 16, 32))),
        "features_docgrams": (features_docgrams, f"WITH d AS (SELECT doc_id, lower(text) AS t FROM documents), g AS (SELECT doc_id AS point_id, (unicode(substr(t, i, 1)) * 961 + unicode(substr(t, i + 1, 1)) * 31 + unicode(substr(t, i + 2, 1))) % {features.GRAMS} AS place FROM d, unnest(range(1, length(t) - 1)) AS u(i)) SELECT point_id, place::INTEGER AS place, count(*) AS n FROM g GROUP BY ALL"),
        "planner_choice": (planner_choice, PLANNER_SQL),
    }
)
