"""Pages, vectors, mixing and the pipeline on small fixtures."""

from __future__ import annotations

import random
import time

import numpy as np
from pyspark.sql import types as T

from nearfield.llm import curves, html, kdtree, mixing
from nearfield.llm.components import components

# pages


def test_main_text_of_markup():
    page = (
        "<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var a='</p>';</script></head><body><nav><a href=x>menu</a></nav><header>top</header>"
        "<!-- c --><div class='ad box'>buy</div><main><article><h1>A &amp; B</h1><p>One<b>two</b> <i>three</i><br>four<p>five &lt;six&gt;<ul><li>x<li>y</ul>"
        "<aside>side</aside><form><input>q</form><div class=comments><p>reader</p></div></article></main><footer>end</footer></body></html>"
    )
    assert html.main_text(page) == "A & B Onetwo three four five <six> x y"
    assert html.main_text(None) == "" and html.main_text("") == "" and html.main_text("plain & text") == "plain & text"
    assert html.main_text("<article><p>cut <a href='x") == "cut" and html.main_text("<article>a &am") == "a &am"
    assert html.main_text("<p>" * 3000 + "deep" + "<div>" * 3000 + "er") == "deep er"


def test_recurring_subtrees_of_a_host_go_and_articles_stay(spark):
    schema = T.StructType([T.StructField("page_id", T.LongType()), T.StructField("url", T.StringType()), T.StructField("html", T.StringType()), T.StructField("text", T.StringType())])
    box = "<div><span>Visit our other pages</span></div>"
    rows = [(i, f"http://a.example/{i}", f"<body>{box}<section><p>story {i}</p></section></body>", "old") for i in range(20)]
    rows += [(100 + i, "http://b.example/x", f"<body>{box}<p>other {i}</p></body>", "old") for i in range(3)]
    rows += [(200 + i, "http://c.example/y", "<body><article><p>same article</p></article></body>", None) for i in range(20)]
    rows += [(300, None, None, None), (None, "http://a.example/z", f"{box}<p>no id</p>", None), (301, "nonsense", "<p>kept</p>", None)]
    got = {r.page_id: (r.text, r.n_chars) for r in html.extract(spark.createDataFrame(rows, schema)).collect()}
    assert got[4] == ("story 4", 7) and got[101] == ("Visit our other pages other 1", 29)
    assert got[205] == ("same article", 12) and got[300] == ("", 0) and got[301] == ("kept", 4)
    assert got[None] == ("Visit our other pages no id", 27)
    assert html.extract(spark.createDataFrame([], schema)).count() == 0


def test_template_of_a_part_of_a_large_host_goes_and_copies_stay(spark):
    note = "<div><p>Read this notice of one section</p></div>"
    rows = [(i, f"http://a.example/{i}", f"<body>{note if i < 12 else ''}<section><p>story {i}</p></section></body>") for i in range(200)]
    copy = "<body><section><p>told again</p><p>and again</p></section><div>on <i>every</i> copy</div></body>"
    rows += [(300 + i, "http://a.example/x", copy) for i in range(30)]
    got = {r.page_id: r.text for r in html.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert [got[i] for i in range(200)] == [f"story {i}" for i in range(200)]
    assert {got[300 + i] for i in range(30)} == {"told again and again on every copy"}


def test_deep_pages_take_linear_time():
    for page in ("<div>" * 100_000 + "x", "<b>" * 50_000 + "<hr>" * 50_000 + "x", "<p>" + "<i>" * 50_000 + "x" + "<p>y" * 50_000):
        began = time.perf_counter()
        parsed = html.Page(page)
        parsed.hashes(), parsed.remainders(), parsed.weights()
        assert html.main_text(page, {1}).split()[0] == "x"
        assert time.perf_counter() - began < 8


def template_by_brute_force(rows, min_pages):
    """Texts of pages made of plain div blocks: blocks that stand on a host's pages beside min_pages different rests go."""
    rests = {}
    for _, host, blocks in rows:
        for x in set(blocks):
            rests.setdefault((host, x), set()).add(tuple(sorted(y for y in blocks if y != x)))
    return {i: " ".join(x for x in blocks if len(rests[host, x]) < min_pages) for i, host, blocks in rows}


def test_templates_without_helpful_markup_by_brute_force(spark):
    rng = random.Random(11)
    menus = [f"menu {i}" for i in range(6)]
    rows = [(i, f"h{i % 3}.example", [f"own {i}", *rng.sample(menus, rng.randrange(0, 4)), f"tale {rng.randrange(1000)}"]) for i in range(240)]
    pages = [(i, f"https://{host}/{i}", "".join(f"<div>{x}</div>" for x in blocks)) for i, host, blocks in rows]
    df = spark.createDataFrame(pages, "page_id long, url string, html string")
    assert {r.page_id: r.text for r in html.extract(df).collect()} == template_by_brute_force(rows, html.MIN_PAGES)
    without = {r.page_id: r.text for r in html.extract(df, 10**9).collect()}
    assert without == {i: " ".join(blocks) for i, _, blocks in rows}


# vectors

VEC = T.StructType([T.StructField("vec_id", T.LongType()), T.StructField("embedding", T.ArrayType(T.FloatType())), T.StructField("rank", T.StringType())])


def vectors(spark, rows):
    return spark.createDataFrame([(i, None if v is None else [None if x is None else float(x) for x in v], "r") for i, v in rows], VEC)


def odd_rows():
    return [(10_000, None), (10_020, [0.1, None, 0.2]), (10_040, [float("nan")] * 3), (10_060, [float("inf"), 0, 0]), (10_080, [0.1]), (None, [0.1, 0.2, 0.3])]


def test_top_k_by_brute_force(spark):
    rng = np.random.default_rng(0)
    data = {i: rng.normal(0, 0.3, 3).round(2).astype(np.float32) for i in range(700)} | {900: np.zeros(3, np.float32), 901: np.zeros(3, np.float32)}
    df = vectors(spark, [(i, v.tolist()) for i, v in data.items()] + odd_rows())
    got = {}
    for r in kdtree.top_k(df, shard=150, block=10).collect():
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id, r.score))
    ints = {i: np.floor(64 * v.astype(np.float64)).astype(np.int64) for i, v in data.items()}
    want = {q: [(n + 1, i, s) for n, (s, i) in enumerate(sorted(((int(ints[q] @ ints[i]), i) for i in ints if i != q), key=lambda x: (-x[0], x[1]))[:20])] for q in ints if q % 20 == 0}
    assert {q: sorted(v) for q, v in got.items()} == want


def test_top_k_few_rows_and_none(spark):
    got = kdtree.top_k(vectors(spark, [(0, [1, 0, 0]), (1, [0.5, 0, 0]), *odd_rows()])).collect()
    assert [(r.query_id, r.rank, r.vec_id, r.score) for r in got] == [(0, 1, 1, 2048)]
    assert kdtree.top_k(vectors(spark, [])).count() == 0


def test_tree_boxes_bound_every_score():
    rng = np.random.default_rng(2)
    x, q = rng.integers(-50, 50, (500, 4)).astype(float), rng.integers(-50, 50, (9, 4)).astype(float)
    tree = kdtree.Tree(np.arange(500), x, leaf=16)
    bound = tree.bounds(q)
    for node, (a, b) in enumerate(tree.rows):
        assert (q @ tree.points[a:b].T <= bound[:, node : node + 1]).all()
    assert sorted(tree.ids.tolist()) == list(range(500))


def test_hilbert_neighbours_are_one_step_apart():
    side = np.arange(8)
    cells = np.stack(np.meshgrid(side, side, side, indexing="ij"), -1).reshape(-1, 3)
    keys = curves.hilbert_keys(cells, 3)
    assert sorted(keys.tolist()) == list(range(512))
    walk = cells[np.argsort(keys)]
    assert (np.abs(np.diff(walk, axis=0)).sum(axis=1) == 1).all()


def recall_of(spark, points, k=10, every=20, block=256):
    got = {}
    for r in curves.nearest(vectors(spark, [*points.items(), *odd_rows(), (10_100, [0] * len(points[0]))]), every=every, k=k, block=block).collect():
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id, r.score))
    x = {i: np.array(v, np.float32).astype(np.float64) for i, v in points.items()}
    hits = total = 0
    for q in (i for i in x if i % every == 0):
        want = sorted((float(np.sqrt(((x[q] - v) ** 2).sum())), i) for i, v in x.items() if i != q)[:k]
        rows = sorted(got[q])
        assert [r[0] for r in rows] == list(range(1, len(rows) + 1))
        assert all(abs(s - np.sqrt(((x[q] - x[i]) ** 2).sum())) < 1e-12 for _, i, s in rows)
        hits += len({i for _, i in want} & {r[1] for r in rows})
        total += len(want)
    return hits / total


def test_nearest_recall_on_clusters_and_on_noise(spark):
    rng = np.random.default_rng(3)
    centres = rng.normal(0, 1, (40, 16))
    clustered = {i: (centres[i % 40] + rng.normal(0, 0.1, 16)).tolist() for i in range(4000)}
    noise = {i: rng.normal(0, 1, 16).tolist() for i in range(4000)}
    assert recall_of(spark, clustered) >= 0.9
    assert recall_of(spark, noise) >= 0.9
    few = {i: noise[i] for i in range(600)}
    assert recall_of(spark, few, block=4096) == 1


def test_nearest_block_keeps_ties_by_id_among_copies():
    rng = np.random.default_rng(7)
    for copies in (60, 100, 1365):
        points = rng.normal(0, 1, (4096, 16))
        points[:copies] = points[0]
        ids = rng.permutation(4096)
        asked = np.arange(0, copies, 7)
        got = curves.exact_nearest(points, ids, points[asked], ids[asked], 10)
        for q in ids[asked]:
            assert got[got.query_id == q].vec_id.tolist() == [i for i in sorted(ids[:copies]) if i != q][:10]
    got = curves.exact_nearest(np.array([[0.0], [0.0], [1.0], [2.0], [3.0]]), np.array([5, 5, 5, 6, 7]), np.array([[0.1]]), np.array([9]), 2)
    assert got.vec_id.tolist() == [5, 6]


def test_nearest_recall_with_more_copies_than_a_window(spark):
    rng = np.random.default_rng(8)
    points = {int(i): [1.0, 2.0, 3.0, 4.0] if n < 2000 else rng.normal(0, 1, 4).tolist() for n, i in enumerate(rng.permutation(3000))}
    assert recall_of(spark, points) >= 0.99


def test_nearest_in_groups_of_queries_and_with_copies_that_ask(spark, monkeypatch):
    rng = np.random.default_rng(10)
    points = {i: rng.normal(0, 1, 6).round(2).tolist() for i in range(900)} | {2000 + i: [1.0] * 6 for i in range(300)}
    whole = sorted(curves.nearest(vectors(spark, list(points.items())), every=10, block=128).collect())
    monkeypatch.setattr(curves, "ASKED", 7)
    assert sorted(curves.nearest(vectors(spark, list(points.items())), every=10, block=128).collect()) == whole
    assert [r.vec_id for r in whole if r.query_id == 2000] == list(range(2001, 2011)) and [r.vec_id for r in whole if r.query_id == 2290] == list(range(2000, 2010))


def test_nearest_on_nothing(spark):
    assert curves.nearest(vectors(spark, [])).count() == 0
    assert curves.nearest(vectors(spark, odd_rows())).count() == 0


# components


def test_components_by_union(spark):
    rng = random.Random(4)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(i, i + 1) for i in range(400, 460)] + [(7, 7)]
    parent = {}

    def root(x):
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    for a, b in edges:
        ra, rb = root(a), root(b)
        parent[max(ra, rb)] = min(ra, rb)
    found = {r.node: r.component for r in components(spark.createDataFrame(edges, "u long, v long")).collect()}
    for node in parent:
        assert found.get(node, node) == root(node)


def test_components_of_few_edges_take_few_jobs_and_equal_the_rounds_by_jobs(spark):
    rng = random.Random(3)
    ids = list({rng.randrange(-(2**62), 2**62) for _ in range(90)})
    edges = spark.createDataFrame([(ids[i], ids[i + 1]) for i in range(60)] + [(ids[i], ids[70]) for i in range(71, 90)] + [(ids[65], ids[65])], "u long, v long")
    spark.sparkContext.setJobGroup("few-edges", "components")
    found = {(r.node, r.component) for r in components(edges).collect()}
    spark.sparkContext.setJobGroup("other", "other")
    assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("few-edges")) <= 10
    assert found == {(i, min(part)) for part in (ids[:61], ids[70:]) for i in part if i != min(part)}
    assert found == {(r.node, r.component) for r in components(edges, local=0).collect()}


# mixing


def test_mixing_meets_reachable_targets_and_separates(spark, documents):
    rng = random.Random(5)
    plain, rude, poor = [f"p{i}" for i in range(60)], ["vile", "foul"], ["zzz", "qqq"]
    rows, labels = [], []
    for i in range(600):
        kind = ("high", "high", "high", "low", "toxic")[i % 5]
        words = [rng.choice(plain) for _ in range(rng.randrange(20, 80))]
        words += [rng.choice({"high": plain, "low": poor, "toxic": rude}[kind]) for _ in range(5)]
        rows.append((i, " ".join(words)))
        if i % 2:
            labels.append((i, {"high": 1, "low": 0, "toxic": 1}[kind], int(kind == "toxic")))
    rows += [(900, None), (901, ""), (None, "p1 p2")]
    labels += [(5000, 1, 0), (None, 1, 1), (1, None, None)]
    marked = mixing.domains_of_labels(spark.createDataFrame(labels, "doc_id long, quality int, toxic int"))
    targets = {"high": 0.8, "low": 0.19, "toxic": 0.01}
    out = mixing.mix(documents(rows), marked, targets, max_rate=3.0).collect()
    assert len(out) == len(rows)
    total = sum(r.n_words for r in out)
    for d, share in targets.items():
        assert abs(sum(r.n_words * r.rate * r[f"p_{d}"] for r in out) / total - share) < 1e-4
    assert {r.misfit for r in out} == {out[0].misfit} and out[0].misfit < 1e-5
    by = {r.doc_id: r for r in out}
    right = [max(targets, key=lambda d: by[i][f"p_{d}"]) == ("high", "high", "high", "low", "toxic")[i % 5] for i in range(600)]
    assert sum(right) > 560 and all(0 <= r.rate <= 3 for r in out)
    assert all(abs(sum(r[f"p_{d}"] for d in targets) - 1) < 1e-6 for r in out)


def bounded_least_squares(n, p, wanted, max_rate, rounds=200_000):
    """Plain accelerated projected gradient in numpy: the loss at the bounded optimum."""
    a = (n[:, None] * p / n.sum()).T
    rate = ahead = np.ones(len(n))
    length, t = 1 / np.linalg.eigvalsh(a @ a.T)[-1], 1.0
    for _ in range(rounds):
        new = np.clip(ahead - length * (a.T @ (a @ ahead - wanted)), 0, max_rate)
        after = (1 + (1 + 4 * t * t) ** 0.5) / 2
        ahead, rate, t = new + (t - 1) / after * (new - rate), new, after
        loss = ((a @ rate - wanted) ** 2).sum()
        if loss < 1e-15:
            break
    return loss


def test_rates_against_bounded_least_squares(spark):
    rng = np.random.default_rng(9)
    n, p = rng.integers(1, 500, 400).astype(float), np.round(rng.dirichlet([0.3, 0.6, 0.2], 400), 9)
    members = spark.createDataFrame([(i, int(n[i]), *map(float, p[i])) for i in range(400)], "doc_id long, n_words long, p0 double, p1 double, p2 double").repartition(4)
    for wanted, reachable in (((0.8, 0.15, 0.05), None), ((0.2, 0.2, 0.6), None), ((0.01, 0.01, 0.98), False), ((0.3, 0.5, 0.2), True)):
        rate, misfits = mixing.fitted(members, list(wanted), 2.0)
        out = members.orderBy("doc_id").withColumn("rate", rate).collect()
        rate = np.array([r.rate for r in out])
        off = (n * rate) @ p / n.sum() - np.array(wanted)
        best = bounded_least_squares(n, p, np.array(wanted), 2.0, 20_000)
        assert (rate >= 0).all() and (rate <= 2).all() and abs(np.abs(off).max() - misfits[-1]) < 1e-8
        assert (off**2).sum() <= best * 1.01 + 1e-10, wanted
        assert reachable is None or (misfits[-1] < 1e-6) == reachable


def test_mixing_without_labels_or_rows(spark, documents):
    none = mixing.domains_of_labels(spark.createDataFrame([], "doc_id long, quality int, toxic int"))
    out = mixing.mix(documents([(1, "a b"), (1, "a b"), (2, None)]), none).collect()
    assert sorted((r.doc_id, r.n_words) for r in out) == [(1, 2), (2, 0)]
    clash = documents([(1, "a b"), (2, "c " * 50_000)]).withColumnRenamed("n_chars", "n_words").withColumnRenamed("lang", "rate")
    assert sorted((r.doc_id, r.n_words) for r in mixing.mix(clash, none).collect()) == [(1, 2), (2, 50_000)]
    assert mixing.mix(documents([]), none).count() == 0


def test_draws_follow_rates(spark, documents):
    docs = documents([(i, "x") for i in range(400)])
    rated = spark.createDataFrame([(i, r) for i, r in zip(range(400), [0.0, 1.0, 2.0, 0.5] * 100, strict=True)], "doc_id long, rate double")
    times = {}
    for r in mixing.drawn(docs, rated).collect():
        times[r.doc_id] = times.get(r.doc_id, 0) + 1
    assert all(times.get(i, 0) == i % 4 for i in range(400) if i % 4 < 3)
    assert 20 < sum(times.get(i, 0) for i in range(3, 400, 4)) < 80


# pipeline


def test_pipeline_stages_by_brute_force(spark, documents, tmp_path):
    import corpus_pipeline

    rng = random.Random(6)
    words = [f"word{chr(97 + i % 26)}{chr(97 + i // 26)}" for i in range(300)]
    text = lambda n: " ".join(rng.choice(words) for _ in range(n))
    rows = [(i, f"{text(60)}\nShared footer line\n{text(20)}", "en", f"s{i % 3}") for i in range(40)]
    rows += [(100 + i, rows[i][1], "en", "s9") for i in range(5)] + [(200, "12345 !!!", "en", "s1"), (201, None, "en", "s1")]
    docs = documents(rows)
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, 1, 0) for i in range(0, 40, 2)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    columns, step = docs.columns, docs
    kept = {}
    for name, stage in corpus_pipeline.STAGES:
        step = stage(spark, step, str(tmp_path))
        kept[name] = step.collect()
        if name != "packing":
            assert step.columns == columns
    assert {r.doc_id for r in kept["language"]} == {r[0] for r in rows} - {200, 201}
    assert all("Shared footer line" not in r.text and r.n_chars == len(r.text) for r in kept["lines"])
    assert {r.doc_id for r in kept["near_duplicates"]} == set(range(40))
    assert sum(r.n_words for r in kept["packing"]) == sum(len(r.text.split()) for r in kept["mixing"])
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == len(kept["packing"])
