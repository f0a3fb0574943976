"""What is measured around the searches: accuracy, work against theory, other metrics, and the method that is chosen."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nearfield.functions import metrics
from nearfield.operators import bruteforce as bf
from nearfield.operators import cover as cv
from nearfield.operators import byvalue, exact, oneshot, storage
from nearfield.plans import evaluate, theory, workloads
from nearfield.queries.common import EVERY, SEED, Query, by_value, drawn, held_out, key_sql, metric_of, n_pivots, nearest_sql, pivots_sql, rounded, sets_sql
from nearfield.queries.search import ALPHA, COVER, _cover, _oneshot, oneshot_lists_sql, oneshot_sql, rank_sql, rules_sql
from nearfield.sources import features
from nearfield.sources.features import table
from nearfield.sources.points import PointSet

#: Seeds of the repeated experiments, and the ratio that the approximate search promises.
SEEDS, RATIO = (1, 2, 3, 4, 5), 0.5


def _stacked(rows: list[DataFrame]) -> DataFrame:
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


# exact search under other metrics


def exact_by(name: str, build, alpha: float = ALPHA) -> tuple[Query, str]:
    """The exact search with another metric over the same values: pruning takes the triangle inequality alone."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        q, x = held_out(spark, d, name)
        m = build()
        return rounded(exact.search(PointSet(q.df, m), _cover(PointSet(x.df, m), alpha)))

    return run, nearest_sql(name, metric=build())


def exact_grid_l1(spark: SparkSession, d: str) -> DataFrame:
    """The nearest of a cube's even integer points to each of a few odd places, under l1."""
    cube = theory.grid(spark, 12, 3)
    even = F.forall("value", lambda v: v % 2 == 0)
    q = PointSet(cube.where(F.col("point_id") % 97 == 5).where(~even), metrics.l1(3))
    return rounded(exact.search(q, _cover(PointSet(cube.where(even), metrics.l1(3)), 2.0)))


GRID_L1_SQL = "WITH g AS (SELECT i AS id, i % 12 AS a, i // 12 % 12 AS b, i // 144 AS c FROM range(1728) t(i)), x AS (SELECT * FROM g WHERE a % 2 = 0 AND b % 2 = 0 AND c % 2 = 0), q AS (SELECT * FROM g WHERE id % 97 = 5 AND NOT (a % 2 = 0 AND b % 2 = 0 AND c % 2 = 0)) SELECT q.id AS query_id, x.id AS neighbor_id, (abs(q.a - x.a) + abs(q.b - x.b) + abs(q.c - x.c))::DOUBLE AS dist FROM q, x QUALIFY row_number() OVER (PARTITION BY q.id ORDER BY abs(q.a - x.a) + abs(q.b - x.b) + abs(q.c - x.c), x.id) = 1"


# approximate answers


def approx_nn_line4(spark: SparkSession, d: str) -> DataFrame:
    """The approximate variant's own answers: bounds shrunk by its ratio."""
    q, x = held_out(spark, d, "line4")
    return rounded(exact.search(q, _cover(x), approx=RATIO))


def approx_sql(name: str, e: float) -> str:
    """The same bounds in SQL: the nearest pivot, or what the shrunk spans hold up to it."""
    m = metric_of(name)
    loose = lambda x: f"(({x}) * (1 + 1e-9) + 1e-12)"
    b = f"(g / {1 + e})"
    return (
        f"WITH {COVER(name)}, dq AS MATERIALIZED (SELECT q.id AS query_id, q.v AS qv, pv.pivot_id, pv.psi, {m.sql('q.v', 'pv.v')} AS dist_qr FROM q, pv), gq AS (SELECT *, min(dist_qr) OVER (PARTITION BY query_id) AS g FROM dq), "
        f"kept AS MATERIALIZED (SELECT *, greatest(0.0, dist_qr - {loose(b)}) AS lo, least(psi, {loose(f'dist_qr + {b}')}) AS hi FROM gq WHERE dist_qr <= {loose(f'{b} + psi')} AND dist_qr <= {loose(f'2 * {b} + g')}), "
        f"f AS (SELECT query_id, point_id, {m.sql('qv', 'l.v')} AS d, g FROM kept JOIN l ON kept.pivot_id = l.pivot_id AND owner_dist BETWEEN lo AND hi UNION ALL SELECT query_id, pivot_id, dist_qr, g FROM gq WHERE dist_qr = g) "
        f"SELECT query_id, point_id AS neighbor_id, round(d, 6) AS dist FROM f WHERE d <= {loose('g')} QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY d, point_id) = 1"
    )


# accuracy


def recall_oneshot(spark: SparkSession, d: str) -> DataFrame:
    """How many of the five true neighbours a one-shot search finds, how far its fifth is, and what the index holds."""
    q, x = held_out(spark, d, "orders2")
    cover = _oneshot(x, 1.0)
    return evaluate.recall(oneshot.search(q, cover, k=5), bf.nearest(q, x, 5), 5).crossJoin(cover.lists.agg(F.count(F.lit(1)).alias("entries")))


def recall_sql(name: str, alpha: float, k: int) -> str:
    got = oneshot_sql(name, alpha, k=k).replace("round(d, 6) AS dist", "d AS dist")
    want = nearest_sql(name, k, ranked=True).replace("round(d, 6) AS dist", "d AS dist")
    return (
        f"WITH got AS MATERIALIZED ({got}), want AS MATERIALIZED ({want}) SELECT round(avg((got.neighbor_id IS NOT NULL)::INTEGER), 6) AS recall, "
        "(SELECT round(avg(CASE WHEN b.d > 0 THEN a.d / b.d ELSE 1.0 END), 6) FROM (SELECT query_id, max(dist) AS d FROM got GROUP BY 1) a JOIN (SELECT query_id, max(dist) AS d FROM want GROUP BY 1) b USING (query_id)) AS mean_ratio, "
        f"(SELECT count(*) FROM (WITH {oneshot_lists_sql(name, alpha)} SELECT * FROM ol)) AS entries FROM want LEFT JOIN got USING (query_id, neighbor_id)"
    )


def certified_share(spark: SparkSession, d: str) -> DataFrame:
    """How many one-shot answers prove themselves exact, and how many are exact."""
    q, x = held_out(spark, d, "events3")
    told = oneshot.certified(q, _oneshot(x, 2.0)).select("query_id", "dist", "certified")
    best = bf.nearest(q, x).select("query_id", F.col("dist").alias("best"))
    right = F.col("dist") <= F.col("best") + 1e-9
    return told.join(best, "query_id").agg(F.count(F.lit(1)).alias("queries"), F.sum(F.col("certified").cast("long")).alias("certified"), F.sum(right.cast("long")).alias("right"), F.sum((F.col("certified") & ~right).cast("long")).alias("certified_wrong"))


def certified_share_sql(name: str, alpha: float) -> str:
    m = metric_of(name)
    return f"WITH {oneshot_lists_sql(name, alpha)}, ps AS (SELECT pivot_id, max(owner_dist) AS psi FROM ol GROUP BY ALL), near AS (SELECT q.id AS query_id, q.v AS qv, r.id AS pivot_id, {m.sql('q.v', 'r.v')} AS dist_qr FROM q, r QUALIFY row_number() OVER (PARTITION BY q.id ORDER BY {m.sql('q.v', 'r.v')}, r.id) = 1), f AS (SELECT query_id, any_value(dist_qr) AS dist_qr, any_value(psi) AS psi, min({m.sql('near.qv', 'ol.v')}) AS d FROM near JOIN ol USING (pivot_id) JOIN ps USING (pivot_id) GROUP BY query_id), b AS (SELECT q.id AS query_id, min({m.sql('q.v', 'x.v')}) AS best FROM q, x GROUP BY 1), t AS (SELECT (dist_qr + d) * (1 + 1e-9) < psi AS c, d <= best + 1e-9 AS r FROM f JOIN b USING (query_id)) SELECT count(*) AS queries, sum(c::BIGINT)::BIGINT AS certified, sum(r::BIGINT)::BIGINT AS right, sum((c AND NOT r)::BIGINT)::BIGINT AS certified_wrong FROM t"


# theory


def ball_mean_by_seed(spark: SparkSession, d: str) -> DataFrame:
    """The mean size of the closed ball up to the nearest pivot, for several draws, beside n / n_r."""
    asked, q, x = by_value(spark, d, "orders2")
    x = storage.at_rest(x)
    n, rows = x.df.agg(F.sum("copies")).first()[0] or 0, []
    n_r = n_pivots(n, ALPHA)
    for seed in SEEDS:
        pivots = drawn(spark, d, "orders2", ALPHA, seed, n)
        balls = byvalue.everyone(asked, evaluate.ball_at_gamma(q, x, cv.around(x, pivots))).agg(F.round(F.avg("closed_ball"), 6).alias("mean_ball"))
        rows.append(balls.select(F.lit(seed).alias("seed"), "mean_ball", F.lit(round(n / n_r, 6)).alias("predicted")))
    return _stacked(rows)


def _ball_mean_sql(seed: int) -> str:
    m = metric_of("orders2")
    head = f"WITH {sets_sql('orders2')}, {pivots_sql(ALPHA, seed=seed)}, g AS (SELECT q.id, any_value(q.v) AS v, min({m.sql('q.v', 'r.v')}) AS gamma FROM q, r GROUP BY q.id), b AS (SELECT g.id, count(*) AS n FROM g, x WHERE {m.sql('g.v', 'x.v')} <= gamma + 1e-9 GROUP BY 1), n AS (SELECT count(*) AS n FROM x)"
    return f"({head} SELECT {seed} AS seed, round(avg(b.n), 6) AS mean_ball, any_value(round(n.n::DOUBLE / greatest(1, least(floor({ALPHA} * sqrt(n.n))::BIGINT, n.n // 2)), 6)) AS predicted FROM b, n)"


def success_by_seed(spark: SparkSession, d: str) -> DataFrame:
    """The share of exact one-shot answers over several draws, beside the bound for the measured growth of balls."""
    q, x = held_out(spark, d, "cust2")
    n, rows = x.df.count(), []
    n_r = n_pivots(n, 2.0)
    for seed in SEEDS:
        cover = storage.settled(cv.build_oneshot(x, n_r, n_r, seed, n))
        found = evaluate.rank_summary(evaluate.rank_errors(oneshot.search(q, cover), q, x))
        rows.append(found.select(F.lit(seed).alias("seed"), "queries", F.col("exact_share").alias("success"), F.lit(round(1 - theory.oneshot_failure(n, n_r, n_r, 2.0), 6)).alias("bound")))
    return _stacked(rows)


def _success_sql(seed: int) -> str:
    name, alpha = "cust2", 2.0
    ranks = rank_sql(name, alpha).replace(f":{SEED}'", f":{seed}'")
    n = f"(SELECT count(*) FROM ({features.SQL[name]}) WHERE {key_sql(name)} % {EVERY} <> 0)"
    n_r = f"greatest(1, least(floor({alpha} * sqrt({n}))::BIGINT, {n} // 2))"
    return f"(SELECT {seed} AS seed, count(*) AS queries, round(avg((closer = 0)::INTEGER), 6) AS success, any_value(round(1 - exp(-({n_r})::DOUBLE * ({n_r}) / (4.0 * {n})), 6)) AS bound FROM ({ranks}))"


def work_against_prediction(spark: SparkSession, d: str) -> DataFrame:
    """Points examined with the paper's window against c^3 n / n_r, c measured over sampled balls, by the number of pivots."""
    q, x = held_out(spark, d, "events3")
    n, rows = x.df.count(), []
    c = theory.sampled_expansion_rate(x, 20, [0.05, 0.1, 0.2], SEED).first().rate
    for alpha in (1.0, 2.0, 4.0):
        seen = evaluate.work(q, _cover(x, alpha), rules=("triple",), window="paper", seeds=False).agg(F.round(F.avg("examined"), 6).alias("examined"), F.max("stage1").alias("n_r"))
        rows.append(seen.select(F.lit(alpha).alias("alpha"), "n_r", "examined", F.round(F.pow(F.lit(float(c)), F.lit(3.0)) * n / F.col("n_r"), 3).alias("predicted")))
    return _stacked(rows)


def _prediction_sql(alpha: float) -> str:
    m = metric_of("events3")
    c = f"(WITH s AS MATERIALIZED (SELECT * FROM ({features.SQL['events3']}) WHERE id % {EVERY} <> 0), c AS MATERIALIZED (SELECT * FROM s ORDER BY substr(md5(id||':{SEED}'),1,8), id LIMIT 20), p AS (SELECT c.id AS i, {m.sql('c.v', 's.v')} AS d FROM c, s), b AS (SELECT i, r, count(*) FILTER (WHERE d <= r) AS few, count(*) FILTER (WHERE d <= 2 * r) AS many FROM p, (VALUES (0.05::DOUBLE), (0.1), (0.2)) v(r) GROUP BY ALL) SELECT round(max(many::DOUBLE / few), 6) FROM b WHERE few > 0)"
    return f"(WITH {rules_sql('events3', ('triple',), 'paper', alpha=alpha)}, e AS (SELECT query_id, count(l.point_id) AS examined FROM kept LEFT JOIN l ON kept.pivot_id = l.pivot_id AND owner_dist BETWEEN lo AND hi GROUP BY 1) SELECT {alpha}::DOUBLE AS alpha, (SELECT count(*) FROM r) AS n_r, round(avg(examined), 6) AS examined, round(pow({c}, 3.0) * (SELECT count(*) FROM x) / (SELECT count(*) FROM r), 3) AS predicted FROM e)"


# the method that is chosen


def auto_nn(name: str) -> Query:
    return lambda spark, d: rounded(workloads.auto_search(*held_out(spark, d, name)))


def explain_search(spark: SparkSession, d: str) -> DataFrame:
    """What a sample of the queries would examine of each set, and the method that follows."""
    rows = [(name, *workloads.explain_search(*held_out(spark, d, name))) for name in ("orders2", "events3", "emb64")]
    return spark.createDataFrame(rows, "set_name string, n long, n_r long, examined double, method string").select("set_name", "n", "method")


EXPLAIN_SQL = f"SELECT 'orders2' AS set_name, count(*) AS n, CASE WHEN count(*) < 1000 THEN 'brute' ELSE 'exact' END AS method FROM orders WHERE o_orderkey % {EVERY} <> 0 UNION ALL SELECT 'events3', count(*), CASE WHEN count(*) < 1000 THEN 'brute' ELSE 'exact' END FROM events WHERE event_id % {EVERY} <> 0 UNION ALL SELECT 'emb64', count(*), 'brute' FROM embeddings WHERE vec_id % {EVERY} <> 0"


def edit_urls(spark: SparkSession, d: str) -> DataFrame:
    u = table(spark, d, "pages").select("page_id", F.regexp_extract("url", "://([^/]+)", 1).alias("host"), "url")
    return u.select("page_id", F.levenshtein("url", "host").alias("edits"), F.substring(F.md5("url"), 1, 8).alias("digest"), F.translate("host", ".-", "_").alias("plain"))


QUERIES: dict[str, tuple[Query, str | None]] = {
    "exact_linf_part": exact_by("part2", lambda: metrics.linf(2)),
    "exact_l3_part": exact_by("part2", lambda: metrics.lp(2, 3.0)),
    "exact_weighted_part": exact_by("part2", lambda: metrics.weighted_l2([4.0, 1.0])),
    "exact_hamming_part": exact_by("part2", lambda: metrics.hamming(2)),
    "exact_haversine_cust2": exact_by("cust2", metrics.haversine),
    "exact_jaccard_docs": exact_by("doc_tokens", metrics.jaccard, 1.0),
    "exact_grid_l1": (exact_grid_l1, GRID_L1_SQL),
    "approx_nn_line4": (approx_nn_line4, approx_sql("line4", RATIO)),
    "recall_oneshot_orders2": (recall_oneshot, recall_sql("orders2", 1.0, 5)),
    "certified_share_events3": (certified_share, certified_share_sql("events3", 2.0)),
    "ball_mean_by_seed": (ball_mean_by_seed, " UNION ALL ".join(map(_ball_mean_sql, SEEDS))),
    "success_by_seed": (success_by_seed, " UNION ALL ".join(map(_success_sql, SEEDS))),
    "work_against_prediction": (work_against_prediction, " UNION ALL ".join(map(_prediction_sql, (1.0, 2.0, 4.0)))),
    "auto_nn_orders2": (auto_nn("orders2"), nearest_sql("orders2")),
    "auto_nn_emb64": (auto_nn("emb64"), nearest_sql("emb64")),
    "explain_search": (explain_search, EXPLAIN_SQL),
    "fn_levenshtein_urls": (edit_urls, "SELECT page_id, levenshtein(url, regexp_extract(url, '://([^/]+)', 1))::INTEGER AS edits, substr(md5(url), 1, 8) AS digest, replace(replace(regexp_extract(url, '://([^/]+)', 1), '.', '_'), '-', '') AS plain FROM pages"),
}
