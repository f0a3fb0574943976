"""The operators, sources, sinks and functions around the methods: what feeds a search and what inspects it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from nearfield.functions import udfs
from nearfield.operators import bruteforce as bf
from nearfield.operators import cover as cv
from nearfield.operators import byvalue, exact, oneshot, storage
from nearfield.queries.common import by_value, held_out, metric_of, nearest_sql, oneshot_by_value, rounded, sets_sql
from nearfield.queries.search import ALPHA, COVER, _cover, _oneshot, oneshot_lists_sql, oneshot_sql, rules_sql
from nearfield.sources import features, pointset
from nearfield.sources.features import table
from nearfield.sources.points import PointSet
from nearfield.streaming.search import scratch

#: The exact lists of orders, as SQL CTEs.
LISTS = COVER("orders2")


def _orders(spark: SparkSession, d: str) -> tuple:
    q, x = held_out(spark, d, "orders2")
    return q, x, _cover(x)


# sources and sinks


def scan_embeddings(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "embeddings").select("vec_id", F.size("embedding").alias("width"), F.round(F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x), 4).alias("squared_length"))


def scan_roundtrip(kind: str):
    """Customers written in another format and read back by an explicit schema."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        rows = table(spark, d, "customer").select("c_custkey", "c_name", "c_acctbal", "c_nationkey")
        path = scratch(spark, f"roundtrip-{kind}")
        writer = rows.write.mode("overwrite")
        if kind == "csv":
            writer.option("header", True).csv(path)
            return spark.read.option("header", True).schema(rows.schema).csv(path)
        getattr(writer, kind)(path)
        return getattr(spark.read.schema(rows.schema), kind)(path)

    return run


def scan_text_pages(spark: SparkSession, d: str) -> DataFrame:
    """URLs through a text file: lines, and their lengths."""
    path = scratch(spark, "text")
    table(spark, d, "pages").select("url").write.mode("overwrite").text(path)
    return spark.read.text(path).select(F.col("value").alias("url"), F.length("value").alias("n"))


def sink_cover_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    """Lists written clustered by pivot and distance, and read back."""
    _, x, cover = _orders(spark, d)
    path = scratch(spark, "cover")
    storage.write_cover(cover, path, files=4)
    back = storage.read_cover(spark, path, x)
    return back.lists.select("pivot_id", "point_id", F.round("owner_dist", 6).alias("owner_dist"))


def cover_roundtrip_search(spark: SparkSession, d: str) -> DataFrame:
    q, x, cover = _orders(spark, d)
    path = scratch(spark, "cover")
    storage.write_cover(cover, path, files=4)
    return rounded(exact.search(q, storage.read_cover(spark, path, x)))


def list_chunks(spark: SparkSession, d: str) -> DataFrame:
    """Long lists cut into chunks by distance; no entry is lost."""
    _, _, cover = _orders(spark, d)
    return storage.chunked(cover.lists, 40).groupBy("pivot_id").agg(F.count(F.lit(1)).alias("entries"))


def scan_pointset(spark: SparkSession, d: str) -> DataFrame:
    """Rows of lineitem on a cube of integer points, which the made source numbers, by the first coordinate."""
    pointset.register(spark)
    cube = spark.read.format("pointset").option("side", 12).option("width", 3).load()
    axes = [F.col("l_linenumber") - 1, F.round(F.col("l_discount") * 100.0), F.round(F.col("l_tax") * 100.0)]
    cells = byvalue.heads(PointSet.from_table(table(spark, d, "lineitem"), F.col("l_orderkey"), axes)).df.select("value", "copies")
    return cells.join(cube, "value").groupBy(F.col("value")[0].alias("x")).agg(F.sum("copies").alias("n"), F.sum(F.col("point_id") * F.col("copies")).alias("ids"))


# projection and filter


def filter_within_box(spark: SparkSession, d: str) -> DataFrame:
    keep = F.col("l_quantity").between(10, 20) & F.col("l_returnflag").isin("A", "R") & (F.col("l_discount") <= 0.05) & ~F.col("l_linestatus").like("X%")
    return table(spark, d, "lineitem").where(keep).groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum(F.col("l_extendedprice").cast("decimal(20,4)")), 2).cast("double").alias("price"))


def project_features(spark: SparkSession, d: str) -> DataFrame:
    return features.orders2(spark, d).df.select("point_id", F.round(F.col("value")[0], 9).alias("x"), F.round(F.col("value")[1], 9).alias("y"))


def case_coalesce(spark: SparkSession, d: str) -> DataFrame:
    kind = F.when(F.col("o_totalprice") > 300000, "large").when(F.col("o_totalprice") > 100000, "middle").otherwise("small")
    return table(spark, d, "orders").select(kind.alias("kind"), F.coalesce(F.nullif("o_orderstatus", F.lit("P")), F.lit("?")).alias("status")).groupBy("kind", "status").agg(F.count(F.lit(1)).alias("n"))


# joins


def join_lists_merge(spark: SparkSession, d: str) -> DataFrame:
    """Lists with their pivots by a sort-merge join."""
    _, _, cover = _orders(spark, d)
    met = cover.lists.hint("merge").join(cover.pivots.select("pivot_id", "psi"), "pivot_id")
    return met.groupBy("pivot_id").agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("owner_dist") == F.col("psi")).cast("long")).alias("on_edge"))


def join_semi_ids(spark: SparkSession, d: str) -> DataFrame:
    rich = table(spark, d, "customer").where("c_acctbal > 5000").select(F.col("c_custkey").alias("o_custkey"))
    return table(spark, d, "orders").join(rich, "o_custkey", "left_semi").groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


def join_anti_uncovered(spark: SparkSession, d: str) -> DataFrame:
    """Points that no one-shot list holds."""
    _, x = held_out(spark, d, "cust2")
    cover = _oneshot(x, 1.0)
    return x.df.join(cover.lists.select("point_id").distinct(), "point_id", "left_anti").select("point_id")


def join_range_window(spark: SparkSession, d: str) -> DataFrame:
    """Each pivot's points in rings of a tenth of its radius: a range join."""
    _, _, cover = _orders(spark, d)
    rings = spark.range(10).select(F.col("id").cast("int").alias("ring"))
    spans = cover.pivots.where("psi > 0").join(F.broadcast(rings), F.lit(True)).select("pivot_id", "ring", (F.col("psi") * F.col("ring") / 10).alias("lo"), (F.col("psi") * (F.col("ring") + 1) / 10).alias("hi"))
    met = cover.lists.join(spans, "pivot_id").where((F.col("owner_dist") >= F.col("lo")) & (F.col("owner_dist") < F.col("hi")))
    return met.groupBy("ring").agg(F.count(F.lit(1)).alias("n"))


def join_asof_events(spark: SparkSession, d: str) -> DataFrame:
    """For each purchase the user's last earlier event of another type: a union and a running last."""
    events = table(spark, d, "events").select("event_id", "user_id", "event_type", "ts")
    own = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    before = F.last(F.when(F.col("event_type") != "purchase", F.col("event_id")), ignorenulls=True).over(own)
    return events.withColumn("earlier_id", before).where("event_type = 'purchase'").select("event_id", "earlier_id")


def join_lateral_topk(spark: SparkSession, d: str) -> DataFrame:
    """The two dearest orders of each customer, as a correlated lateral subquery."""
    table(spark, d, "customer").createOrReplaceTempView("lateral_customer")
    table(spark, d, "orders").createOrReplaceTempView("lateral_orders")
    return spark.sql("SELECT c_custkey, t.o_orderkey, t.o_totalprice FROM lateral_customer, LATERAL (SELECT o_orderkey, o_totalprice FROM lateral_orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2) t")


def join_full_ranks(spark: SparkSession, d: str) -> DataFrame:
    """Exact and one-shot answers side by side."""
    q, x, cover = _orders(spark, d)
    a = exact.search(q, cover).select("query_id", F.col("neighbor_id").alias("exact_id"))
    b = oneshot.search(q, _oneshot(x, 0.5)).select("query_id", F.col("neighbor_id").alias("oneshot_id"))
    return a.join(b, "query_id", "full").select("query_id", "exact_id", "oneshot_id")


# aggregation


def agg_radii(spark: SparkSession, d: str) -> DataFrame:
    _, _, cover = _orders(spark, d)
    return cover.lists.groupBy("pivot_id").agg(F.round(F.max("owner_dist"), 6).alias("psi"), F.count(F.lit(1)).alias("n"), F.round(F.avg("owner_dist"), 6).alias("mean"), F.max_by("point_id", F.struct("owner_dist", "point_id")).alias("edge_id"))


def agg_list_skew(spark: SparkSession, d: str) -> DataFrame:
    _, _, cover = _orders(spark, d)
    return cover.pivots.agg(F.max("list_size").alias("largest"), F.min("list_size").alias("smallest"), F.round(F.avg("list_size"), 6).alias("mean"), F.round(F.stddev_samp("list_size"), 6).alias("deviation"))


def _graded(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").select("l_returnflag", "l_linestatus", "l_quantity")


def agg_cube(spark: SparkSession, d: str) -> DataFrame:
    return _graded(spark, d).cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("quantity"))


def agg_rollup(spark: SparkSession, d: str) -> DataFrame:
    return _graded(spark, d).rollup("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("quantity"))


def agg_grouping_sets(spark: SparkSession, d: str) -> DataFrame:
    _graded(spark, d).createOrReplaceTempView("graded")
    return spark.sql("SELECT l_returnflag, l_linestatus, count(*) AS n FROM graded GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")


def agg_pivot(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).select("o_orderpriority", *[F.coalesce(c, F.lit(0)).alias(f"n_{c}") for c in ("F", "O", "P")])


def agg_filter_having(spark: SparkSession, d: str) -> DataFrame:
    table(spark, d, "orders").createOrReplaceTempView("having_orders")
    return spark.sql("SELECT o_custkey, count(*) AS n, count(*) FILTER (WHERE o_totalprice > 200000) AS dear FROM having_orders GROUP BY o_custkey HAVING count(*) > 12")


def agg_quantile_gamma(spark: SparkSession, d: str) -> DataFrame:
    """Approximate quantiles of the distance to the nearest pivot, and an approximate count of owners."""
    _, _, cover = _orders(spark, d)
    return cover.lists.agg(F.percentile_approx("owner_dist", F.array(F.lit(0.5), F.lit(0.99))).alias("quantiles"), F.approx_count_distinct("pivot_id").alias("owners"))


def agg_histogram(spark: SparkSession, d: str) -> DataFrame:
    _, _, cover = _orders(spark, d)
    return cover.pivots.select(F.floor(F.col("list_size") / 10).alias("bin")).groupBy("bin").agg(F.count(F.lit(1)).alias("n"))


def agg_collect(spark: SparkSession, d: str) -> DataFrame:
    """Nation names of each region, collected and sorted."""
    n = table(spark, d, "nation").join(F.broadcast(table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return n.groupBy("r_name").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names"))


# windows


def win_rank_neighbors(spark: SparkSession, d: str) -> DataFrame:
    _, _, cover = _orders(spark, d)
    own = Window.partitionBy("pivot_id").orderBy("owner_dist", "point_id")
    return cover.lists.select("pivot_id", "point_id", F.row_number().over(own).alias("place"), F.round(F.percent_rank().over(own), 6).alias("part")).where("place <= 3")


def win_list_prefix(spark: SparkSession, d: str) -> DataFrame:
    """How many entries each list has up to each of its distances."""
    _, _, cover = _orders(spark, d)
    own = Window.partitionBy("pivot_id").orderBy("owner_dist").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    return cover.lists.select("pivot_id", "point_id", F.count(F.lit(1)).over(own).alias("prefix"))


def win_lag_gap(spark: SparkSession, d: str) -> DataFrame:
    own = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    days = F.datediff("o_orderdate", F.lag("o_orderdate").over(own))
    return table(spark, d, "orders").select("o_orderkey", days.alias("gap"), F.lead("o_orderkey").over(own).alias("next_key"))


def win_ntile(spark: SparkSession, d: str) -> DataFrame:
    order = Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")
    return table(spark, d, "customer").select("c_custkey", F.ntile(4).over(order).alias("quarter"), F.dense_rank().over(order).alias("place"), F.first("c_custkey").over(order).alias("least_id"))


def win_moving_sum(spark: SparkSession, d: str) -> DataFrame:
    near = Window.partitionBy("c_nationkey").orderBy("c_custkey").rowsBetween(-2, 2)
    return table(spark, d, "customer").select("c_custkey", F.round(F.sum(F.col("c_acctbal").cast("decimal(20,4)")).over(near), 2).cast("double").alias("around"))


# sort, limit, sets


def topk_global(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select("o_orderkey", "o_totalprice")


def limit_offset(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").orderBy("o_orderkey").offset(100).limit(10).select("o_orderkey")


def topk_per_query(spark: SparkSession, d: str) -> DataFrame:
    own = Window.partitionBy("p_type").orderBy(F.desc("p_retailprice"), "p_partkey")
    return table(spark, d, "part").withColumn("place", F.row_number().over(own)).where("place <= 5").select("p_type", "p_partkey", "place")


def _answers(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    q, x = held_out(spark, d, "cust2")
    a = bf.nearest(q, x).select("query_id", "neighbor_id")
    b = oneshot.search(q, _oneshot(x, 0.5)).select("query_id", "neighbor_id")
    return a, b


def set_union(spark: SparkSession, d: str) -> DataFrame:
    a, b = _answers(spark, d)
    return a.union(b).distinct()


def set_intersect(spark: SparkSession, d: str) -> DataFrame:
    a, b = _answers(spark, d)
    return a.intersect(b)


def set_except(spark: SparkSession, d: str) -> DataFrame:
    """Answers that one-shot search missed."""
    a, b = _answers(spark, d)
    return a.exceptAll(b)


# scalar functions


def fn_edit_urls(spark: SparkSession, d: str) -> DataFrame:
    u = table(spark, d, "pages").select("page_id", F.regexp_extract("url", "://([^/]+)", 1).alias("host"), "url")
    return u.select("page_id", "host", F.levenshtein("url", "host").alias("edits"), F.substring(F.md5("url"), 1, 8).alias("digest"), F.soundex(F.element_at(F.split("host", r"\."), 1)).alias("sound"))


def fn_array_distance(spark: SparkSession, d: str) -> DataFrame:
    """Each embedding's distance to its own reverse, by array functions."""
    e = F.col("embedding").cast("array<double>")
    dist = F.sqrt(F.aggregate(F.zip_with(e, F.reverse(e), lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))
    return table(spark, d, "embeddings").select("vec_id", F.round(dist, 6).alias("dist"), F.round(F.array_max(e), 6).alias("largest"), F.size(F.filter(e, lambda x: x > 0)).alias("positive"))


def fn_json_feature(spark: SparkSession, d: str) -> DataFrame:
    k = F.from_json("props", "k INT")["k"]
    return table(spark, d, "events").select(k.alias("k"), F.get_json_object("props", "$.k").cast("int").alias("again")).groupBy("k", "again").agg(F.count(F.lit(1)).alias("n"))


def fn_date_features(spark: SparkSession, d: str) -> DataFrame:
    month = F.date_format("o_orderdate", "yyyy-MM")
    return table(spark, d, "orders").select(month.alias("month"), F.dayofweek("o_orderdate").alias("day")).groupBy("month", "day").agg(F.count(F.lit(1)).alias("n"))


def fn_map_sparse(spark: SparkSession, d: str) -> DataFrame:
    """Letter counts of the passages as a map, and its squared length."""
    letters = F.filter(F.split(F.lower("text"), ""), lambda x: x.rlike("^[a-z]$"))
    kinds = F.array_sort(F.array_distinct(letters))
    pairs = F.transform(kinds, lambda k: F.size(F.filter(letters, lambda x: x == k)))
    m = F.map_from_arrays(kinds, pairs)
    squared = F.aggregate(F.map_values(F.transform_values(m, lambda k, v: v * v)), F.lit(0), lambda s, x: s + x)
    return table(spark, d, "benchmark").select("item_id", F.size(m).alias("kinds"), squared.alias("squared"), F.coalesce(m["e"], F.lit(0)).alias("e"))


# functions and SQL surface


def udf_distance(spark: SparkSession, d: str) -> DataFrame:
    points = features.orders2(spark, d).df
    return points.select("point_id", F.round(udfs.distance(F.col("value"), F.reverse("value")), 6).alias("dist"))


def udaf_spread(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "part").groupBy("p_type").agg(F.round(udfs.spread("p_retailprice"), 6).alias("spread"))


def udtf_neighbors(spark: SparkSession, d: str) -> DataFrame:
    """The five customers with balances nearest to 1000, by a table function."""
    udfs.register(spark)
    table(spark, d, "customer").createOrReplaceTempView("udtf_customer")
    return spark.sql("SELECT item, round(dist, 6) AS dist, rank_no FROM ms_neighbors(TABLE(SELECT c_custkey, abs(c_acctbal - 1000) FROM udtf_customer) WITH SINGLE PARTITION, 5)")


def sqlfn_l2(spark: SparkSession, d: str) -> DataFrame:
    udfs.register(spark)
    table(spark, d, "part").createOrReplaceTempView("sqlfn_part")
    return spark.sql("SELECT p_partkey, round(ms_l2(p_size, p_retailprice, 25, 950), 6) AS dist FROM sqlfn_part")


#: Exact search as SQL over the views queries_in, pivots and owned_lists (two columns a point).
#: Both sides of a query's minimum are aggregates, so pairs are summed in their task and are never shuffled for a window.
EXACT_TEXT = """
WITH g AS (SELECT q.query_id, q.x, q.y, min(ms_l2(q.x, q.y, p.x, p.y)) AS gamma FROM queries_in q, pivots p GROUP BY q.query_id, q.x, q.y),
d AS (SELECT g.*, p.pivot_id, p.psi, ms_l2(g.x, g.y, p.x, p.y) AS dist_qr FROM g, pivots p),
kept AS (SELECT * FROM d WHERE dist_qr <= (gamma + psi) * (1 + 1e-9) + 1e-12 AND dist_qr <= 3 * gamma * (1 + 1e-9) + 1e-12),
met AS (SELECT k.query_id, k.gamma, l.point_id, ms_l2(k.x, k.y, l.x, l.y) AS dist FROM kept k JOIN owned_lists l ON k.pivot_id = l.pivot_id AND l.owner_dist BETWEEN k.dist_qr - k.gamma * (1 + 1e-9) - 1e-12 AND k.dist_qr + k.gamma * (1 + 1e-9) + 1e-12),
found AS (SELECT query_id, point_id, dist FROM met WHERE dist <= gamma UNION ALL SELECT query_id, pivot_id, dist_qr FROM kept WHERE dist_qr = gamma),
best AS (SELECT query_id, min(named_struct('dist', dist, 'point_id', point_id)) AS first FROM found GROUP BY query_id)
SELECT query_id, first.point_id AS neighbor_id, round(first.dist, 6) AS dist FROM best
"""

#: The same for one-shot lists, in two steps: each query's nearest pivot, then the view nearest_in of these and its list.
NEAREST_TEXT = """
WITH g AS (SELECT /*+ BROADCAST(p) */ q.query_id, q.x, q.y, min(ms_l2(q.x, q.y, p.x, p.y)) AS gamma FROM queries_in q, pivots p GROUP BY q.query_id, q.x, q.y)
SELECT /*+ BROADCAST(p) */ g.query_id, g.x, g.y, min(p.pivot_id) AS pivot_id FROM g JOIN pivots p ON ms_l2(g.x, g.y, p.x, p.y) = g.gamma GROUP BY g.query_id, g.x, g.y
"""

ONESHOT_TEXT = """
WITH d AS (SELECT n.query_id, l.point_id, ms_l2(n.x, n.y, l.x, l.y) AS dist FROM nearest_in n JOIN owned_lists l ON n.pivot_id = l.pivot_id),
least AS (SELECT query_id, min(dist) AS dist FROM d GROUP BY query_id)
SELECT d.query_id, min(d.point_id) AS neighbor_id, round(d.dist, 6) AS dist FROM d JOIN least ON d.query_id = least.query_id AND d.dist = least.dist GROUP BY d.query_id, d.dist
"""


def _views(spark: SparkSession, q: PointSet, cover: cv.Cover) -> None:
    two = [F.col("value")[0].alias("x"), F.col("value")[1].alias("y")]
    q.df.select(F.col("point_id").alias("query_id"), *two).createOrReplaceTempView("queries_in")
    cover.pivots.select("pivot_id", "psi", *two).createOrReplaceTempView("pivots")
    cover.lists.select("pivot_id", "owner_dist", "point_id", *two).createOrReplaceTempView("owned_lists")
    udfs.register(spark)


def sql_exact_search(spark: SparkSession, d: str) -> DataFrame:
    asked, q, x = by_value(spark, d, "orders2")
    _views(spark, q, _cover(x))
    return byvalue.everyone(asked, spark.sql(EXACT_TEXT))


def sql_oneshot_search(spark: SparkSession, d: str) -> DataFrame:
    asked, q, x = by_value(spark, d, "orders2")
    _views(spark, q, oneshot_by_value(spark, d, "orders2", x, ALPHA))
    storage.at_rest(PointSet(spark.sql(NEAREST_TEXT), q.metric)).df.createOrReplaceTempView("nearest_in")
    return byvalue.everyone(asked, spark.sql(ONESHOT_TEXT))


def answers_attach(spark: SparkSession, d: str) -> DataFrame:
    """Payload joined back after a search: the order behind each nearest neighbour."""
    q, x, cover = _orders(spark, d)
    found = exact.search(q, cover).select("query_id", "neighbor_id")
    return found.join(table(spark, d, "orders").select(F.col("o_orderkey").alias("neighbor_id"), "o_custkey", "o_orderstatus"), "neighbor_id").select("query_id", "neighbor_id", "o_custkey", "o_orderstatus")


_A, _B = nearest_sql("cust2"), oneshot_sql("cust2", 0.5)
_PAIR = f"a AS (SELECT query_id, neighbor_id FROM ({_A})), b AS (SELECT query_id, neighbor_id FROM ({_B}))"
_MOVING = "SELECT c_custkey, round(sum(c_acctbal::DECIMAL(20,4)) OVER (PARTITION BY c_nationkey ORDER BY c_custkey ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING), 2)::DOUBLE AS around FROM customer"

QUERIES = {
    "scan_embeddings": (scan_embeddings, "SELECT vec_id, len(embedding)::INTEGER AS width, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4) AS squared_length FROM embeddings"),
    **{f"scan_roundtrip_{k}": (scan_roundtrip(k), "SELECT c_custkey, c_name, c_acctbal, c_nationkey FROM customer") for k in ("csv", "json", "orc")},
    "scan_pointset": (scan_pointset, "SELECT (l_linenumber - 1)::DOUBLE AS x, count(*) AS n, sum(l_linenumber - 1 + 12 * round(l_discount * 100)::BIGINT + 144 * round(l_tax * 100)::BIGINT)::BIGINT AS ids FROM lineitem GROUP BY 1"),
    "scan_text_pages": (scan_text_pages, "SELECT url, length(url)::INTEGER AS n FROM pages"),
    "sink_cover_roundtrip": (sink_cover_roundtrip, f"WITH {LISTS} SELECT pivot_id, point_id, round(owner_dist, 6) AS owner_dist FROM l"),
    "cover_roundtrip": (cover_roundtrip_search, nearest_sql("orders2")),
    "list_chunks": (list_chunks, f"WITH {LISTS} SELECT pivot_id, count(*) AS entries FROM l GROUP BY 1"),
    "filter_within_box": (filter_within_box, "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_extendedprice::DECIMAL(20,4)), 2)::DOUBLE AS price FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_discount <= 0.05 AND l_linestatus NOT LIKE 'X%' GROUP BY ALL"),
    "project_features": (project_features, f"SELECT id AS point_id, round(v[1], 9) AS x, round(v[2], 9) AS y FROM ({features.SQL['orders2']})"),
    "case_coalesce": (case_coalesce, "SELECT CASE WHEN o_totalprice > 300000 THEN 'large' WHEN o_totalprice > 100000 THEN 'middle' ELSE 'small' END AS kind, coalesce(nullif(o_orderstatus, 'P'), '?') AS status, count(*) AS n FROM orders GROUP BY ALL"),
    "join_lists_merge": (join_lists_merge, f"WITH {LISTS} SELECT l.pivot_id, count(*) AS n, count(*) FILTER (WHERE owner_dist = psi) AS on_edge FROM l JOIN pv USING (pivot_id) GROUP BY 1"),
    "join_semi_ids": (join_semi_ids, "SELECT o_orderstatus, count(*) AS n FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_acctbal > 5000) GROUP BY 1"),
    "join_anti_uncovered": (join_anti_uncovered, f"WITH {oneshot_lists_sql('cust2', 1.0)} SELECT id AS point_id FROM x WHERE id NOT IN (SELECT point_id FROM ol)"),
    "join_range_window": (join_range_window, f"WITH {LISTS} SELECT r.ring::INTEGER AS ring, count(*) AS n FROM l JOIN pv USING (pivot_id), range(10) r(ring) WHERE psi > 0 AND owner_dist >= psi * ring / 10 AND owner_dist < psi * (ring + 1) / 10 GROUP BY 1"),
    "join_asof_events": (join_asof_events, "SELECT event_id, earlier_id FROM (SELECT *, last_value(CASE WHEN event_type <> 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS earlier_id FROM events) WHERE event_type = 'purchase'"),
    "join_lateral_topk": (join_lateral_topk, "SELECT o_custkey AS c_custkey, o_orderkey, o_totalprice FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer) QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 2"),
    "join_full_ranks": (join_full_ranks, f"SELECT query_id, a.neighbor_id AS exact_id, b.neighbor_id AS oneshot_id FROM ({nearest_sql('orders2')}) a FULL JOIN ({oneshot_sql('orders2', 0.5)}) b USING (query_id)"),
    "agg_radii": (agg_radii, f"WITH {LISTS} SELECT pivot_id, round(max(owner_dist), 6) AS psi, count(*) AS n, round(avg(owner_dist), 6) AS mean, max(struct_pack(d := owner_dist, i := point_id)).i AS edge_id FROM l GROUP BY 1"),
    "agg_list_skew": (agg_list_skew, f"WITH {LISTS} SELECT max(list_size) AS largest, min(list_size) AS smallest, round(avg(list_size), 6) AS mean, round(stddev_samp(list_size), 6) AS deviation FROM pv"),
    "agg_cube_work": (agg_cube, "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity::BIGINT)::BIGINT AS quantity FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)"),
    "agg_rollup_rank": (agg_rollup, "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity::BIGINT)::BIGINT AS quantity FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)"),
    "agg_grouping_sets_work": (agg_grouping_sets, "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())"),
    "agg_pivot_status": (agg_pivot, "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS \"n_F\", count(*) FILTER (WHERE o_orderstatus = 'O') AS \"n_O\", count(*) FILTER (WHERE o_orderstatus = 'P') AS \"n_P\" FROM orders GROUP BY 1"),
    "agg_filter_having": (agg_filter_having, "SELECT o_custkey, count(*) AS n, count(*) FILTER (WHERE o_totalprice > 200000) AS dear FROM orders GROUP BY 1 HAVING count(*) > 12"),
    "agg_quantile_gamma": (agg_quantile_gamma, None),
    "agg_histogram": (agg_histogram, f"WITH {LISTS} SELECT list_size // 10 AS bin, count(*) AS n FROM pv GROUP BY 1"),
    "agg_collect": (agg_collect, "SELECT r_name, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY 1"),
    "win_rank_neighbors": (win_rank_neighbors, f"WITH {LISTS} SELECT pivot_id, point_id, (row_number() OVER w)::INTEGER AS place, round(percent_rank() OVER w, 6) AS part FROM l WINDOW w AS (PARTITION BY pivot_id ORDER BY owner_dist, point_id) QUALIFY place <= 3"),
    "win_list_prefix": (win_list_prefix, f"WITH {LISTS} SELECT pivot_id, point_id, count(*) OVER (PARTITION BY pivot_id ORDER BY owner_dist) AS prefix FROM l"),
    "win_lag_owner_gap": (win_lag_gap, "SELECT o_orderkey, date_diff('day', lag(o_orderdate) OVER w, o_orderdate)::INTEGER AS gap, lead(o_orderkey) OVER w AS next_key FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)"),
    "win_ntile_radius": (win_ntile, "SELECT c_custkey, (ntile(4) OVER w)::INTEGER AS quarter, (dense_rank() OVER w)::INTEGER AS place, first_value(c_custkey) OVER w AS least_id FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)"),
    "win_moving_sum": (win_moving_sum, _MOVING),
    "topk_global": (topk_global, "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25"),
    "limit_offset": (limit_offset, "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 10 OFFSET 100"),
    "topk_per_query": (topk_per_query, "SELECT p_type, p_partkey, (row_number() OVER (PARTITION BY p_type ORDER BY p_retailprice DESC, p_partkey))::INTEGER AS place FROM part QUALIFY place <= 5"),
    "set_union_lists": (set_union, f"WITH {_PAIR} SELECT * FROM a UNION SELECT * FROM b"),
    "set_intersect_answers": (set_intersect, f"WITH {_PAIR} SELECT * FROM a INTERSECT SELECT * FROM b"),
    "set_except_missed": (set_except, f"WITH {_PAIR} SELECT * FROM a EXCEPT SELECT * FROM b"),
    "fn_edit_urls": (fn_edit_urls, None),
    "fn_array_distance": (fn_array_distance, "WITH e AS (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings) SELECT vec_id, round(sqrt(list_sum(list_transform(range(1, 65), lambda i: (v[i] - v[65 - i]) * (v[i] - v[65 - i])))), 6) AS dist, round(list_max(v), 6) AS largest, len(list_filter(v, lambda x: x > 0))::INTEGER AS positive FROM e"),
    "fn_json_feature": (fn_json_feature, "SELECT (props->>'$.k')::INTEGER AS k, (props->>'$.k')::INTEGER AS again, count(*) AS n FROM events GROUP BY ALL"),
    "fn_date_features": (fn_date_features, "SELECT strftime(o_orderdate, '%Y-%m') AS month, (dayofweek(o_orderdate) + 1)::INTEGER AS day, count(*) AS n FROM orders GROUP BY ALL"),
    "fn_map_sparse": (fn_map_sparse, "WITH c AS (SELECT item_id, x, count(*) AS n FROM (SELECT item_id, unnest(regexp_extract_all(lower(text), '[a-z]')) AS x FROM benchmark) GROUP BY ALL) SELECT item_id, count(*)::INTEGER AS kinds, sum(n * n)::INTEGER AS squared, coalesce(max(n) FILTER (WHERE x = 'e'), 0)::INTEGER AS e FROM c GROUP BY item_id"),
    "udf_distance": (udf_distance, f"SELECT id AS point_id, round(sqrt((v[1]-v[2])*(v[1]-v[2]) + (v[2]-v[1])*(v[2]-v[1])), 6) AS dist FROM ({features.SQL['orders2']})"),
    "udaf_medoid": (udaf_spread, "SELECT p_type, round(avg(abs(p_retailprice - m)), 6) AS spread FROM part JOIN (SELECT p_type, median(p_retailprice) AS m FROM part GROUP BY 1) USING (p_type) GROUP BY 1"),
    "udtf_neighbors": (udtf_neighbors, "SELECT c_custkey AS item, round(abs(c_acctbal - 1000), 6) AS dist, (row_number() OVER (ORDER BY abs(c_acctbal - 1000), c_custkey))::INTEGER AS rank_no FROM customer QUALIFY rank_no <= 5"),
    "sqlfn_l2": (sqlfn_l2, "SELECT p_partkey, round(sqrt((p_size - 25.0) * (p_size - 25.0) + (p_retailprice - 950.0) * (p_retailprice - 950.0)), 6) AS dist FROM part"),
    "sql_exact_search": (sql_exact_search, nearest_sql("orders2")),
    "sql_oneshot_search": (sql_oneshot_search, oneshot_sql("orders2", ALPHA)),
    "answers_attach": (answers_attach, f"SELECT query_id, neighbor_id, o_custkey, o_orderstatus FROM ({nearest_sql('orders2')}) JOIN orders ON o_orderkey = neighbor_id"),
}

__all__ = ["QUERIES", "metric_of", "rules_sql", "sets_sql"]
