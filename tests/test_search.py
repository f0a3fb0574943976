"""Bounds, invariants and edge cases of the search engine, held against brute force."""

from __future__ import annotations

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from nearfield.functions import metrics
from nearfield.operators import bruteforce as bf
from nearfield.operators import cover as cv
from nearfield.operators import byvalue, exact, oneshot, storage, trees
from nearfield.plans import evaluate, planner, theory
from nearfield.sources.points import PointSet


def points(spark, rows, metric=None):
    """Rows of (id, numbers) as a PointSet."""
    df = spark.createDataFrame([(i, [float(x) for x in v]) for i, v in rows], "point_id long, value array<double>")
    return PointSet(df, metric or metrics.l2(len(rows[0][1]) if rows else 1))


def answers(df):
    return {r.query_id: (r.neighbor_id, round(r.dist, 9)) for r in df.collect()}


def cover_of(spark, rows, pivots):
    x = points(spark, rows)
    return x, cv.from_pivots(x, x.where(F.col("point_id").isin(pivots)))


LINE = [(i, [v]) for i, v in enumerate([0, 1, 2, 10, 11, 12])]


def test_line_fixture_prunes_the_far_pivot(spark):
    _, c = cover_of(spark, LINE, [1, 4])
    q = points(spark, [(99, [2.4])])
    for rules in (("radius",), ("triple",)):
        kept = {r.pivot_id for r in exact.survivors(q, c, rules=rules).where("hi >= lo").collect()}
        assert kept == {1}
    assert answers(exact.search(q, c)) == {99: (2, 0.4)}


def test_list_of_one_point_is_not_lost(spark):
    _, c = cover_of(spark, [(0, [0]), (1, [5]), (2, [6])], [0, 1])
    assert answers(exact.search(points(spark, [(9, [1])]), c)) == {9: (0, 1.0)}


def test_tie_across_lists_goes_to_the_smaller_id(spark):
    _, c = cover_of(spark, [(0, [-1]), (1, [1])], [0, 1])
    assert answers(exact.search(points(spark, [(9, [0])]), c)) == {9: (0, 1.0)}


def test_oneshot_hits_and_misses(spark):
    x = points(spark, [(0, [0]), (1, [3]), (2, [4]), (3, [10])])
    pivots = x.where(F.col("point_id").isin(0, 3))
    c = cv._covered(x, pivots, cv.nearest_points(pivots, x, 2, 4), "oneshot")
    found = answers(oneshot.search(points(spark, [(8, [5.4]), (9, [4.9])]), c))
    assert found == {8: (2, 1.4), 9: (1, 1.9)}
    errors = {r.query_id: r.closer for r in evaluate.rank_errors(oneshot.search(points(spark, [(8, [5.4]), (9, [4.9])]), c), points(spark, [(8, [5.4]), (9, [4.9])]), x).collect()}
    assert errors == {8: 0, 9: 1}


def test_equal_points_and_more_neighbours_than_points(spark):
    x, c = cover_of(spark, [(i, [1, 1]) for i in range(5)], [0])
    q = points(spark, [(9, [1, 1])])
    assert answers(exact.search(q, c)) == {9: (0, 0.0)}
    assert [r.neighbor_id for r in exact.search(q, c, k=9).orderBy("rank_no").collect()] == [0, 1, 2, 3, 4]
    assert [r.neighbor_id for r in bf.nearest(q, x, k=9).orderBy("rank_no").collect()] == [0, 1, 2, 3, 4]


def test_empty_queries_and_empty_sample(spark):
    x, c = cover_of(spark, LINE, [1, 4])
    empty = PointSet(x.df.where("false"), x.metric)
    assert exact.search(empty, c).count() == 0 and bf.nearest(empty, x).count() == 0
    built = cv.build_exact(x, 1e-9, 1, 6)
    assert built.pivots.count() == 1
    assert answers(exact.search(points(spark, [(9, [10.2])]), built)) == {9: (3, 0.2)}


def test_invalid_points_are_refused(spark):
    bad = spark.createDataFrame([(1, [0.0, float("nan")]), (2, [1.0, 2.0])], "point_id long, value array<double>")
    with pytest.raises(ValueError):
        PointSet(bad, metrics.l2(2)).validate()
    assert PointSet(bad.where("point_id = 2"), metrics.l2(2)).validate()


def cloud(seed, n, d):
    rng = np.random.default_rng(seed)
    centres = rng.normal(0, 3, (4, d))
    return [(i, (centres[i % 4] + rng.normal(0, 0.5, d)).round(3).tolist()) for i in range(n)]


@pytest.mark.parametrize("k", [1, 5, 10])
@pytest.mark.parametrize("window,ring", [(None, False), ("paper", False), ("tight", False), ("tight", True)])
def test_every_rule_set_is_exact(spark, k, window, ring):
    rows = cloud(k, 300, 3)
    x = points(spark, rows[30:])
    q = points(spark, rows[:30])
    want = {(r.query_id, r.rank_no): (r.neighbor_id, round(r.dist, 9)) for r in bf.nearest(q, x, k).collect()}
    c = cv.build_exact(x, 25, 3, 270)
    for rules in (("radius",), ("triple",), ("radius", "triple")):
        got = {(r.query_id, r.rank_no): (r.neighbor_id, round(r.dist, 9)) for r in exact.search(q, c, k, rules, window, ring).collect()}
        assert got == want


def test_owned_lists_partition_the_set_and_answers_do_not_depend_on_partitions(spark):
    rows = cloud(5, 200, 2)
    x, q = points(spark, rows[20:]), points(spark, rows[:20])
    c = cv.build_exact(x, 20, 3, 180)
    assert sorted(r.point_id for r in c.lists.collect()) == sorted(i for i, _ in rows[20:])
    own = c.lists.join(c.pivots.select("pivot_id"), "pivot_id").where("pivot_id = point_id")
    assert own.count() == c.pivots.count()
    again = cv.build_exact(PointSet(x.df.repartition(7), x.metric), 20, 3, 180)
    assert answers(exact.search(q, c)) == answers(exact.search(PointSet(q.df.repartition(5), q.metric), again))


def test_oneshot_lists_have_s_entries_and_certified_answers_are_exact(spark):
    rows = cloud(6, 400, 2)
    x, q = points(spark, rows[40:]), points(spark, rows[:40])
    c = cv.build_oneshot(x, 30, 40, 3, 360)
    assert {r["count"] for r in c.lists.groupBy("pivot_id").count().collect()} == {40}
    truth = answers(bf.nearest(q, x))
    for r in oneshot.certified(q, c).where("certified").collect():
        assert round(r.dist, 9) == truth[r.query_id][1]
    full = cv.build_exact(x, 30, 3, 360)
    assert {i: d for i, (_, d) in answers(oneshot.then_exact(q, c, full)).items()} == {i: d for i, (_, d) in truth.items()}


def test_range_search_and_approximation(spark):
    rows = cloud(7, 300, 2)
    x, q = points(spark, rows[20:]), points(spark, rows[:20])
    c = cv.build_exact(x, 25, 3, 280)
    pairs = lambda df: {(r.query_id, r.neighbor_id) for r in df.collect()}
    assert pairs(exact.within(q, c, 0.7)) == pairs(bf.within(q, x, 0.7))
    best, got = answers(bf.nearest(q, x)), answers(exact.search(q, c, approx=0.5))
    assert all(got[i][1] <= 1.5 * best[i][1] + 1e-9 for i in best)


def test_containment_and_recursion(spark):
    rows = cloud(8, 300, 2)
    x, q = points(spark, rows[20:]), points(spark, rows[:20])
    row = evaluate.containment(q, cv.build_exact(x, 25, 3, 280)).first()
    assert row.pivots_outside == 0 and row.points_outside == 0 and row.points_read > 0
    assert answers(exact.search(q, cv.build_exact(x, 25, 3, 280, levels=2))) == answers(bf.nearest(q, x))


def test_append_and_delete(spark):
    rows = cloud(9, 200, 2)
    x, more, q = points(spark, rows[20:150]), points(spark, rows[150:]), points(spark, rows[:20])
    grown = cv.append(cv.build_exact(x, 20, 3, 130), more)
    assert answers(exact.search(q, grown)) == answers(bf.nearest(q, points(spark, rows[20:])))
    gone = cv.delete(grown, spark.createDataFrame([(25,), (26,)], "point_id long"))
    assert gone.lists.where("point_id in (25, 26)").count() == 0


@pytest.mark.parametrize("kind", [trees.NetTree, trees.BallTree, trees.KdTree])
@pytest.mark.parametrize("chunks", [1, 3])
def test_trees_equal_brute_force(spark, kind, chunks):
    rows = cloud(10, 300, 3) + [(1000 + i, [1.0, 1.0, 1.0]) for i in range(40)]
    x, q = points(spark, rows[20:]), points(spark, rows[:20])
    want = {(r.query_id, r.rank_no): round(r.dist, 9) for r in bf.nearest(q, x, 3).collect()}
    got = {(r.query_id, r.rank_no): round(r.dist, 9) for r in trees.search(kind, q, x, 3, chunks).collect()}
    assert got == want


def test_block_grid_equals_the_kernel(spark):
    rows = cloud(11, 150, 2)
    x, q = points(spark, rows[30:]), points(spark, rows[:30])
    assert answers(bf.reduce_rows(bf.blocks(q, x, 1, rows=40), 1)) == answers(bf.nearest(q, x))


def test_edit_and_jaccard_search(spark):
    words = ["kitten", "sitting", "mitten", "bitten", "flask", "flash", "clash", "class", "glass", "grass"]
    df = spark.createDataFrame(list(enumerate(words)), "point_id long, value string")
    x = PointSet(df.where("point_id % 3 <> 0"), metrics.edit())
    q = PointSet(df.where("point_id % 3 = 0"), metrics.edit())
    c = cv.build_exact(x, 3, 2, 6)
    assert answers(exact.search(q, c)) == answers(bf.nearest(q, x))
    sets = spark.createDataFrame([(1, ["a", "b"]), (2, ["b", "c"]), (3, [])], "point_id long, value array<string>")
    got = {(r.query_id, r.neighbor_id): r.dist for r in bf._nested(PointSet(sets, metrics.jaccard()), PointSet(sets, metrics.jaccard()), "q", False).collect()}
    assert got[1, 1] == 0 and round(got[1, 2], 6) == round(2 / 3, 6) and got[3, 3] == 0 and got[1, 3] == 1


@settings(max_examples=30, deadline=None)
@given(st.lists(st.tuples(st.integers(-20, 20), st.integers(-20, 20)), min_size=3, max_size=40), st.integers(1, 4))
def test_pruning_bounds_in_numpy(rows, k):
    """No k-th neighbour lies on a list, or at an owner distance, that the bounds exclude."""
    x = np.array(rows, float)
    rng = np.random.default_rng(len(rows))
    r = np.flatnonzero(rng.random(len(x)) < 0.4)
    r = r if len(r) >= k else np.arange(min(k, len(x)))
    q = rng.uniform(-25, 25, 2)
    d = lambda a, b: np.sqrt(((a - b) ** 2).sum(axis=-1))
    owner = np.array([r[d(x[r], p).argmin()] for p in x])
    dr = np.sort(d(x[r], q))
    if len(dr) < k:
        return
    g1, gk = dr[0], dr[k - 1]
    for i in np.argsort(d(x, q), kind="stable")[:k]:
        to_owner, back = d(x[owner[i]], q), d(x[owner[i]], x[i])
        assert to_owner <= 2 * gk + g1 + 1e-9
        assert back <= gk + g1 + 1e-9
        assert abs(to_owner - back) <= gk + 1e-9


def test_theory_and_planner(spark):
    assert theory.exact_params(10_000, 2.0) == 282 and theory.exact_params(10, 50.0) == 5
    n_r, s = theory.oneshot_params(10_000, 2.0, 0.01)
    assert n_r == s and theory.oneshot_failure(10_000, n_r, s, 2.0) <= 0.01 + 1e-9
    ps = PointSet(spark.range(1), metrics.l2(64))
    assert planner.choose_pairing(ps, ps, 10, 10**9).kind == "kernel"
    assert planner.choose_pairing(ps, ps, 10**9, 10**9).kind == "grid"


def test_ball_mean_is_near_n_over_n_r(spark):
    """The mean closed ball of radius gamma, over seeds, against n / n_r (fixed seeds, wide margin)."""
    rows = cloud(12, 1000, 2)
    x, q = points(spark, rows[50:]), points(spark, rows[:50])
    means = [evaluate.ball_at_gamma(q, x, cv.build_exact(x, 50, seed, 950)).agg(F.avg("closed_ball")).first()[0] for seed in (1, 2, 3)]
    assert 0.5 * 950 / 50 < np.mean(means) < 2 * 950 / 50


def test_metric_axioms_and_shapes(spark):
    rows = cloud(13, 12, 3)
    for m in (metrics.l1(3), metrics.l2(3), metrics.linf(3), metrics.lp(3, 3), metrics.weighted_l2([1, 2, 3]), metrics.hamming(3), metrics.angular(3)):
        p = points(spark, rows, m)
        assert {r.violations for r in metrics.axiom_violations(p.df, m, 1e-6).collect()} == {0}
        a = np.array([v for _, v in rows])
        col = {(r.query_id, r.neighbor_id): r.dist for r in bf._nested(p, p, "q", False).collect()}
        block = m.block(a, a)
        assert all(abs(col[i, j] - block[i, j]) < 1e-6 for i in range(12) for j in range(12))


def test_oneshot_lists_are_full_where_a_radius_holds_too_few(spark, monkeypatch):
    x = points(spark, [(i, [i % 17, i % 23]) for i in range(300)])
    want = {(r.pivot_id, r.point_id) for r in cv.build_oneshot(x, 20, 15, 3, 300).lists.collect()}
    monkeypatch.setattr(cv, "_cutoffs", lambda x, r_vals, s, n: np.where(np.arange(len(r_vals)) % 2, 0.5, 100.0))
    assert {(r.pivot_id, r.point_id) for r in cv.build_oneshot(x, 20, 15, 3, 300).lists.collect()} == want


def test_deleted_pivots_route_but_answer_nothing(spark):
    x, c = cover_of(spark, LINE, [1, 4])
    left = cv.delete(c, spark.createDataFrame([(1,)], "point_id long"))
    assert answers(exact.search(points(spark, [(99, [1.1])]), left)) == {99: (2, 0.9)}
    rows = cloud(12, 240, 2)
    x, q = points(spark, rows[40:]), points(spark, rows[:40])
    c = cv.build_exact(x, 20, 3, 200)
    gone = c.pivots.select(F.col("pivot_id").alias("point_id")).where("point_id % 3 > 0").union(x.df.select("point_id").where("point_id % 5 = 0"))
    left = cv.delete(c, gone)
    rest = PointSet(x.df.join(gone, "point_id", "left_anti"), x.metric)
    for k in (1, 4):
        want = {(r.query_id, r.rank_no): (r.neighbor_id, round(r.dist, 9)) for r in bf.nearest(q, rest, k).collect()}
        assert {(r.query_id, r.rank_no): (r.neighbor_id, round(r.dist, 9)) for r in exact.search(q, left, k).collect()} == want
    grown = cv.append(left, x.where(F.col("point_id") % 5 == 0))
    back = PointSet(rest.df.union(x.df.where("point_id % 5 = 0")).dropDuplicates(["point_id"]), x.metric)
    assert answers(exact.search(q, grown)) == answers(bf.nearest(q, back))


@pytest.mark.parametrize("ring", [False, True])
def test_kernels_measure_what_the_spans_hold(spark, ring):
    rows = cloud(13, 400, 3)
    x, q = points(spark, rows[50:]), points(spark, rows[:50])
    c = cv.build_exact(x, 20, 3, 350)
    counted = {r.query_id: r.examined for r in evaluate.work(q, c, ring=ring, seeds=False).collect()}
    seen = {r.query_id: r.examined for r in exact.measured(q, c, ring=ring).collect()}
    assert seen == {i: n for i, n in counted.items() if n}
    assert sum(seen.values()) < 50 * 350 / 2


def test_sent_and_met_searches_agree_also_with_hot_lists(spark, monkeypatch):
    rows = [*cloud(14, 300, 2), *[(1000 + i, [0.5, 0.5]) for i in range(200)]]
    x, q = points(spark, rows[40:]), points(spark, rows[:40])
    c = cv.build_exact(x, 12, 3, 460)
    kept = exact.survivors(q, c, 3)
    sent = bf.reduce_rows(exact._answers(exact.scan_lists(q, kept, c, 3, True)), 3)
    monkeypatch.setattr(exact, "SLAB", 64)
    monkeypatch.setattr(exact, "ASKED", 16)
    met = bf.reduce_rows(exact._answers(exact.scan_lists(q, kept, c, 3, True, limit=0)), 3)
    plain = lambda df: {(r.query_id, r.rank_no): (r.neighbor_id, round(r.dist, 9)) for r in df.collect()}
    assert plain(sent) == plain(met) == plain(bf.nearest(q, x, 3))


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 9), st.integers(1, 40), st.integers(1, 6), st.integers(0, 2**32 - 1), st.sampled_from([1.0, 1e-6, 1e6]))
def test_near_equals_a_sort_of_all_distances(width, n, k, seed, scale):
    from nearfield.operators.kernels import Near

    rng = np.random.default_rng(seed)
    b = rng.integers(0, 4, (n, width)) * scale + 1e3
    a = rng.integers(0, 4, (7, width)) * scale + 1e3
    metric = metrics.l2(width)
    every = metric.cells(a[:, None, :], b[None, :, :])
    want = np.argsort(every, axis=1, kind="stable")[:, :k]
    places, dist = Near(metric, b).least(a, k)
    assert (places == want).all() and (dist == np.take_along_axis(every, want, axis=1)).all()


def test_a_set_over_the_limit_is_not_sent(spark):
    with pytest.raises(ValueError):
        bf.collected(points(spark, LINE), limit=10)
    x, q = points(spark, cloud(1, 60, 2)), points(spark, cloud(2, 9, 2))
    pairs = {(r.query_id, r.neighbor_id): round(r.dist, 9) for r in bf._nested(q, x, None, False).collect()}
    assert pairs == {(r.query_id, r.neighbor_id): round(r.dist, 9) for r in bf._nested(q, x, "q", False).collect()} and len(pairs) == 540


def test_a_batch_that_runs_again_leaves_its_rows_once(spark, tmp_path, monkeypatch):
    from nearfield.streaming import search

    spark.range(20).write.parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema("id long").parquet(f"{tmp_path}/in")
    wrote = []

    def twice(batch, number):
        wrote.append(number)
        return batch

    real = search.finish
    out = real(stream, "once", each=twice)
    assert sorted(r.id for r in out.collect()) == list(range(20)) and wrote


def test_axioms_count_copies_and_violations(spark):
    squared = metrics.Metric("squared", lambda a, b: (a[0] - b[0]) * (a[0] - b[0]), lambda a, b: "", lambda a, b: (a[..., 0] - b[..., 0]) ** 2, 1)
    rows = [(i, [v]) for i, v in enumerate([0, 1, 2] * 500)]
    got = {r.axiom: r.violations for r in metrics.axiom_violations(points(spark, rows, squared).df, squared).collect()}
    # 0 - 1 - 2 and 2 - 1 - 0 break the inequality: a cube of 1,500 rows holds 2 * 500^3 such triples.
    assert got == {"identity": 0, "symmetry": 0, "sign": 0, "triangle": 2 * 500**3}
    empty = metrics.axiom_violations(points(spark, rows, squared).df.limit(0), squared).collect()
    assert {r.violations for r in empty} == {0}


def test_nearest_targets_keep_few_rows_a_node_and_ties(spark):
    from nearfield.functions import graphdist

    leaves = [(f"c{i}", "n0" if i % 2 else "n1", 1.0 + (i % 5) / 10) for i in range(40)]
    edges = spark.createDataFrame([*leaves, ("n0", "r", 1.0), ("n1", "r", 1.0), ("s0", "n0", 1.5), ("s1", "r", 1.5)], "src string, dst string, weight double")
    targets = spark.createDataFrame([(a,) for a, _, _ in leaves], "node string")
    found = graphdist.nearest_targets(edges, targets, 9)
    assert found.count() < 3 * 45
    near = {r.node: (r.target, round(r.dist, 9)) for r in found.orderBy("node", "dist", "target").collect() if r.node in ("s0", "s1", "c3")}
    assert near == {"s0": ("c15", 2.5), "s1": ("c0", 3.5), "c3": ("c3", 0.0)}


def test_token_blocks_equal_the_column(spark):
    from nearfield.operators import tokens
    from pyspark.sql import DataFrame

    rng = np.random.default_rng(5)
    rows = [(i, [f"w{w}" for w in sorted(set(rng.integers(0, 12, rng.integers(0, 9)).tolist()))]) for i in range(120)]
    x = PointSet(spark.createDataFrame(rows, "point_id long, value array<string>").repartition(3), metrics.jaccard())
    q = x.where(F.col("point_id") % 6 == 0)
    plain = lambda df: sorted((r.query_id, r.neighbor_id, round(r.dist, 9), r.rank_no) for r in df.collect())
    for a, b in ((q, x), (x, q)):
        for k in (1, 3):
            assert isinstance(tokens.nearest(a, b, k, "q"), DataFrame)
            assert plain(bf.nearest(a, b, k)) == plain(bf.reduce_top_k(bf._nested(a, b, "q", False), k))
    c = cv.from_pivots(x, x.where(F.col("point_id") % 10 == 0))
    assert plain(exact.search(q, c, 3)) == plain(bf.reduce_top_k(bf._nested(q, x, "q", False), 3))


@pytest.mark.parametrize("kind", ["long", "string"])
def test_heads_stand_for_all_rows_of_a_value(spark, kind):
    from nearfield.operators import byvalue

    rows = [(i, [float(i % 7), float(i % 3) - 0.0]) for i in range(300)]
    df = spark.createDataFrame(rows, "point_id long, value array<double>").withColumn("point_id", F.col("point_id").cast(kind)).repartition(5)
    x = PointSet(df, metrics.l2(2))
    h = byvalue.heads(x)
    got = {(tuple(r.value), r.point_id, r.copies) for r in h.df.collect()}
    least = min if kind == "long" else (lambda ids: min(map(str, ids)))
    groups = {}
    for i, v in rows:
        groups.setdefault(tuple(v), []).append(i)
    assert got == {(v, least(ids), len(ids)) for v, ids in groups.items()}
    q = x.where(F.col("point_id").cast("long") % 2 == 0)
    own = byvalue.heads(q)
    plain = lambda df: sorted((r.query_id, r.neighbor_id, r.dist) for r in df.collect())
    assert plain(byvalue.everyone(byvalue.members(q, own), bf.nearest(own, h))) == plain(bf.nearest(q, x))


def test_balls_and_rates_weigh_a_value_by_its_copies(spark):
    from nearfield.operators import byvalue

    x = points(spark, [(i, [float(i % 6)]) for i in range(60)])
    q, own = x.where(F.col("point_id") < 6), byvalue.heads(x)
    pivots = own.where(F.col("value")[0] == 3.0)
    plain = lambda df: sorted(map(tuple, df.collect()))
    got = evaluate.ball_at_gamma(q, own, cv.around(own, pivots))
    assert got.columns == ["query_id", "closed_ball", "strictly_closer"]
    assert plain(got) == [(0, 40, 30), (1, 40, 30), (2, 30, 10), (3, 10, 0), (4, 30, 10), (5, 30, 20)]
    rates = plain(theory.exact_expansion_rate(x))
    assert len(rates) == 60 and rates[0] == (0, 2.0) and rates[3] == (3, 3.0)


def test_oneshot_lists_by_value_end_where_those_of_all_rows_do(spark):
    """Copies, and values that share the distance at which a list ends: the least ids of rows decide."""
    rng = np.random.default_rng(4)
    rows = [(int(i), [int(v)]) for i, v in enumerate(rng.integers(-12, 13, 400))]
    x = points(spark, rows)
    heads = storage.at_rest(byvalue.heads(x))
    pivots = x.where(F.col("point_id").isin(*range(0, 400, 57)))
    own = byvalue.heads(pivots)
    least = {tuple(r.value): r.point_id for r in heads.df.collect()}
    names = {r.point_id: tuple(r.value) for r in pivots.df.collect()}
    for s in (1, 7, 30, 90, 399):
        want = {(names[r.pivot_id], least[tuple(r.value)]) for r in cv.nearest_points(pivots, x, s, 400).collect() if least[tuple(r.value)] == r.point_id}
        found = cv.nearest_values(own, heads, s, 400, x).collect()
        assert {(names[r.pivot_id], r.point_id) for r in found} == want and len(found) == len(want)


@pytest.mark.parametrize("width", [2, 5])
def test_nearest_angles_need_few_measured_pairs(width):
    """The k least angles, ties and rows of one direction by place, are those of all pairs, of which few are measured."""
    from dataclasses import replace

    from nearfield.operators.kernels import Near, _least_of

    r, seen = np.random.default_rng(3), []
    values = r.uniform(0.01, 1, (400, width))
    values[100:120] = 2 * values[:20]
    values[200:220] = values[:20]
    asks, plain = np.vstack((r.uniform(0.01, 1, (50, width)), values[:20] * 3)), metrics.angular(width)
    counted = replace(plain, cells=lambda a, b: seen.append(np.broadcast_shapes(a.shape, b.shape)[:-1]) or plain.cells(a, b))
    for k in (1, 3):
        want, got = _least_of(plain.block(asks, values), k), Near(counted, values).least(asks, k)
        assert (want[0] == got[0]).all() and (want[1] == got[1]).all()
    assert sum(int(np.prod(x)) for x in seen) < 0.05 * len(asks) * len(values)
    apart = np.zeros((len(asks), len(values)), bool)
    apart[:, ::2] = True
    assert (Near(plain, values).least(asks, 1, apart)[0] % 2 == 1).all()
    assert Near(plain, np.vstack((values, np.zeros(width)))).turned is None


@pytest.mark.parametrize("k", [1, 3])
@pytest.mark.parametrize("name", ["l2", "l1"])
def test_many_queries_search_in_rounds_without_rows_of_spans(spark, monkeypatch, k, name):
    """Rounds give the rows of brute force, ties to the smaller id, also in slabs and blocks that cut lists; no spans are made."""
    r = np.random.default_rng(8)
    values = np.round(r.uniform(0, 1, (900, 3)) * 8) / 8
    metric = metrics.l2(3) if name == "l2" else metrics.l1(3)
    x, q = points(spark, list(enumerate(values[:700])), metric), points(spark, list(enumerate(values[700:])), metric)
    c = storage.settled(cv.build_exact(x, 40, 1, 700))
    for at, value in (("MANY", 10), ("ROUND_BYTES", 4096), ("SLAB", 128), ("BLOCK", 64), ("HELD", 512)):
        monkeypatch.setattr(exact, at, value)
    monkeypatch.setattr(exact, "scan_lists", None)
    rows = lambda df: sorted((a.query_id, a.neighbor_id, round(a.dist, 9)) for a in df.collect())
    assert rows(exact.search(q, c, k)) == rows(bf.nearest(q, x, k))
    assert rows(exact.within(q, c, 0.3)) == rows(bf.within(q, x, 0.3))
    got = {(a.query_id, a.rank_no): a.dist for a in exact.search(q, c, k, approx=0.5).collect()}
    want = {(a.query_id, a.rank_no): a.dist for a in bf.nearest(q, x, k).collect()}
    assert got.keys() == want.keys() and all(got[i] <= 1.5 * want[i] * (1 + 1e-9) + 1e-12 for i in want)


def test_edit_search_measures_few_pairs_and_is_exact(spark, monkeypatch):
    """What the bags of characters and the rings leave is measured, and the answers are those of the Column."""
    from nearfield.operators import edits

    rng = np.random.default_rng(5)
    words = ["", *("".join(rng.choice(list("abcdefé\U0001f600"), int(n))) for n in rng.choice([1, 6, 40, 63, 64, 65, 130], 199))]
    frame = spark.createDataFrame(list(enumerate(words)) + [(200, None)], "point_id long, value string")
    x, q = (PointSet(frame.where(c), metrics.edit()) for c in ("point_id % 5 <> 0", "point_id % 5 = 0"))
    pairs = bf._nested(q, x, "q", False)
    for k in (1, 3):
        want = sorted(map(tuple, bf.reduce_top_k(pairs.where("dist IS NOT NULL"), k).select("query_id", "neighbor_id", "dist", "rank_no").collect()))
        cover = cv.build_exact(x, 12.0, 3)
        for found in (exact.search(q, cover, k), exact.search(q, cover, k, ring=False), bf.nearest(q, x, k), bf.nearest(x, q, k)):
            got = sorted(map(tuple, found.select("query_id", "neighbor_id", "dist", "rank_no").collect()))
            if got and got[0][0] % 5:
                assert len(got) == k * 160
            else:
                assert got == want
    assert "levenshtein" not in exact.search(q, cover)._jdf.queryExecution().optimizedPlan().toString()
    # A string's neighbours are found among the few that share most of its characters.
    a, b = edits.Texts(words[:100]), edits.Texts(words[100:])
    seen, plain = [], edits.measured
    monkeypatch.setattr(edits, "measured", lambda *p: (seen.append(len(p[1])), plain(*p))[1])
    list(edits.least(a, b, 1, np.full(100, np.inf)))
    assert sum(seen) < 5000


@pytest.mark.parametrize("metric", [metrics.l1(5), metrics.l2(5), metrics.linf(5), metrics.hamming(5)])
@pytest.mark.parametrize("eps", [0.0, 0.05, 0.4, 30.0])
def test_cells_hold_every_pair_of_a_range(metric, eps):
    from nearfield.operators.kernels import Cells

    rng = np.random.default_rng(3)
    q, x = (np.round(rng.uniform(-1, 1, (n, 5)), 2) * [1, 1, 0.1, 10, 0] for n in (150, 300))
    q[3, 2], x[4, 1], x[5, 0], x[6] = np.nan, np.inf, 1e12, -1e9
    with np.errstate(invalid="ignore"):
        want = set(zip(*(a.tolist() for a in np.nonzero(metric.block(q, x) <= eps)), strict=True))
    if not Cells.fits(metric, q, eps):
        assert eps == 0 or metric.name == "hamming"
        return
    found = list(Cells(metric, q, eps).within(x))
    assert sorted((a, b) for own, row, _ in found for a, b in zip(own.tolist(), row.tolist(), strict=True)) == sorted(want)


def test_range_search_measures_only_cells_beside(monkeypatch):
    from nearfield.operators import kernels

    q, x = (np.random.default_rng(s).uniform(0, 1, (2000, 4)) for s in (1, 2))
    seen, plain = [], kernels.measured
    monkeypatch.setattr(kernels, "measured", lambda m, a, b: (seen.append(len(a)), plain(m, a, b))[1])
    list(kernels.Cells(metrics.l2(4), q, 0.05).within(x))
    assert sum(seen) < 2000 * 2000 / 100


def test_range_search_shuffles_no_rows(spark, tmp_path):
    from nearfield.queries.search import bf_range_line4

    rows = spark.range(400).selectExpr("id % 200 AS l_orderkey", "id AS l_partkey", "id AS l_suppkey", "1 AS l_linenumber", "CAST(id % 7 AS double) AS l_quantity", "CAST(id % 11 * 900 AS double) AS l_extendedprice", "0.1D AS l_discount", "0.02D AS l_tax")
    rows.write.parquet(f"{tmp_path}/lineitem.parquet")
    found = bf_range_line4(spark, str(tmp_path))
    assert "Exchange" not in found._jdf.queryExecution().executedPlan().toString()
    assert found.count() > 0


def test_balls_count_copies_whatever_the_size(spark, monkeypatch):
    rng = np.random.default_rng(8)
    x = spark.createDataFrame([(i, [float(a), float(b)], int(c)) for i, (a, b, c) in enumerate(rng.integers(0, 30, (400, 3)))], "point_id long, value array<double>, copies long")
    x = PointSet(x.where("copies > 0"), metrics.l2(2))
    q = points(spark, [(1000 + i, [float(a), float(b)]) for i, (a, b) in enumerate(rng.uniform(0, 30, (150, 2)))])
    held, asked = x.df.collect(), q.df.collect()
    pivots = [r for r in held if r.point_id % 40 == 0]
    cover = cv.around(x, x.where(F.col("point_id") % 40 == 0))
    apart = lambda a, b: float(np.hypot(a.value[0] - b.value[0], a.value[1] - b.value[1]))
    want = {}
    for a in asked:
        gamma = min(apart(a, p) for p in pivots)
        want[a.point_id] = (sum(r.copies for r in held if apart(a, r) <= gamma + 1e-9), sum(r.copies for r in held if apart(a, r) < gamma - 1e-9))
    for limit in (1 << 28, 1500):
        monkeypatch.setattr(evaluate.bf, "BROADCAST_BYTES", limit)
        assert {r.query_id: (r.closed_ball, r.strictly_closer) for r in evaluate.ball_at_gamma(q, x, cover).collect()} == want


def test_boxes_find_what_all_pairs_hold(monkeypatch):
    from nearfield.operators.kernels import Boxes

    rng = np.random.default_rng(9)
    for width, n, m in ((1, 1, 1), (2, 900, 300), (4, 700, 129), (12, 500, 140)):
        x, a = (np.round(rng.normal(size=(rows, width)), 1) for rows in (n, m))
        dist = metrics.l2(width).cells(a[:, None, :], x[None, :, :])
        boxes, limit = Boxes(metrics.l2(width), x), dist.min(axis=1) * (np.arange(m) % 3)
        place, near = boxes.nearest(a)
        assert (place == dist.argmin(axis=1)).all() and (near == dist.min(axis=1)).all()
        assert (np.isfinite(boxes.nearest(a, limit)[1]) == (dist.min(axis=1) <= limit)).all()
        radius = np.where(np.arange(m) % 4, 0.8, -1.0)
        pairs = [p for row, col, _ in boxes.within(a, radius) for p in zip(row, col, strict=True)]
        assert len(pairs) == len(set(pairs)) and set(pairs) == set(zip(*np.nonzero(dist <= radius[:, None]), strict=True))


def test_nearest_of_slabs_sends_on_only_what_may_be_nearest(spark, monkeypatch):
    from nearfield.operators.kernels import Boxes

    rng = np.random.default_rng(10)
    x = points(spark, [(i, [float(v) for v in row]) for i, row in enumerate(rng.integers(0, 40, (3000, 2)))])
    q = points(spark, [(9000 + i, [float(v) for v in row]) for i, row in enumerate(rng.uniform(0, 40, (400, 2)))])
    monkeypatch.setattr(Boxes, "ROWS", 32)
    monkeypatch.setattr(bf, "PAID", 1)
    monkeypatch.setattr(bf, "SAMPLED", 1500)
    want = {r.query_id: (r.neighbor_id, r.dist) for r in bf.nearest_in(q, x, x.df, 2).where("rank_no = 1").collect()}
    sent = bf.candidates(q, PointSet(x.df.repartition(8), x.metric), 1)
    # Every task used to send a row for every query.
    assert sent.count() < 4 * 400
    assert {r.query_id: (r.neighbor_id, r.dist) for r in bf.reduce_rows(sent, 1).collect()} == want


def test_sides_of_lineitem_are_chosen_by_the_first_part_of_an_id(spark, tmp_path):
    from nearfield.queries import common
    from nearfield.sources import features

    rows = [(k, 1, 2, 3, 1.0, 2.0, 0.1, 0.02) for k in (0, 1, 100, 199, 200, None)]
    spark.createDataFrame(rows, "l_orderkey long, l_linenumber int, l_partkey long, l_suppkey long, l_quantity double, l_extendedprice double, l_discount double, l_tax double").write.parquet(f"{tmp_path}/lineitem.parquet")
    asks = F.substring_index("point_id", "-", 1).cast("long") % 100 == 0
    every = features.line4(spark, str(tmp_path))
    for part, want in zip(common.split(spark, str(tmp_path), "line4"), (every.where(asks), every.where(~asks)), strict=True):
        assert {r.point_id for r in part.df.collect()} == {r.point_id for r in want.df.collect()}
        assert "l_orderkey" in part.df._jdf.queryExecution().optimizedPlan().toString()


def test_hashed_search_finds_the_nearest_of_all_shared_buckets(spark, monkeypatch):
    from nearfield.operators import lsh

    rng = np.random.default_rng(11)
    x = points(spark, [(i, [float(v) / 10 for v in row]) for i, row in enumerate(rng.integers(0, 60, (1500, 2)))])
    q = points(spark, [(9000 + i, [float(v) / 10 for v in row]) for i, row in enumerate(rng.integers(0, 60, (200, 2)))])
    x = PointSet(x.df.repartition(3), x.metric)
    got = {r.query_id: (r.neighbor_id, round(r.dist, 9)) for r in lsh.search(q, x, 0.1, 0.07).collect()}
    monkeypatch.setattr(lsh, "_in_buckets", None)
    monkeypatch.setattr(lsh.bf, "BROADCAST_BYTES", 0)
    assert got == {r.query_id: (r.neighbor_id, round(r.dist, 9)) for r in lsh.search(q, x, 0.1, 0.07).collect()}


def test_oneshot_text_takes_the_least_ids_without_windows_over_pairs(spark):
    from nearfield.functions import udfs
    from nearfield.queries import relational

    udfs.register(spark)
    spark.createDataFrame([(1, 0.0, 0.0), (2, 5.0, 0.0)], "query_id long, x double, y double").createOrReplaceTempView("queries_in")
    spark.createDataFrame([(8, 1.0, 0.0), (7, -1.0, 0.0), (9, 5.0, 1.0)], "pivot_id long, x double, y double").createOrReplaceTempView("pivots")
    lists = [(7, 30, 0.0, 2.0), (7, 20, 2.0, 0.0), (7, 40, 0.0, 3.0), (8, 10, 0.0, 0.0), (9, 50, 5.0, 0.5)]
    spark.createDataFrame(lists, "pivot_id long, point_id long, x double, y double").createOrReplaceTempView("owned_lists")
    near = spark.sql(relational.NEAREST_TEXT)
    near.createOrReplaceTempView("nearest_in")
    found = spark.sql(relational.ONESHOT_TEXT)
    assert {(r.query_id, r.neighbor_id, r.dist) for r in found.collect()} == {(1, 20, 2.0), (2, 50, 0.5)}
    assert not any("Window" in p._jdf.queryExecution().optimizedPlan().toString() for p in (near, found))
