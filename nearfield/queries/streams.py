"""Streaming queries over the events table; each drains what is there and returns the sink's rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nearfield.operators import cover as cv
from nearfield.queries.common import EVERY, SEED, Query, n_pivots, nearest_sql, rounded
from nearfield.queries.search import oneshot_sql
from nearfield.sources import features
from nearfield.sources.features import table
from nearfield.sources.points import PointSet, spread
from nearfield.streaming import search as st


def _vectors(events: DataFrame, spark: SparkSession, d: str) -> DataFrame:
    users = float(table(spark, d, "customer").count()) / 10.0
    vec = F.array((F.hour("ts") * 60 + F.minute("ts")) / F.lit(1440.0), F.col("value") / 500.0, F.col("user_id") / F.lit(users))
    return events.select(F.col("event_id").alias("point_id"), vec.alias("value"))


def _searched(mode: str, alpha: float) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        points = features.events3(spark, d)
        x = spread(points.where(F.col("point_id") % EVERY != 0))
        n = x.df.count()
        n_r = n_pivots(n, alpha)
        cover = cv.build_exact(x, n_r, SEED, n) if mode == "exact" else cv.build_oneshot(x, n_r, n_r, SEED, n)
        asked = st.read_events(spark, d).where(F.col("event_id") % EVERY == 0)
        return rounded(st.search_stream(PointSet(_vectors(asked, spark, d), points.metric), cover, mode))

    return run


def _text(c: str):
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss").alias(c)


def stream_tumbling(spark: SparkSession, d: str) -> DataFrame:
    """Windows that the watermark has closed by the end of the stream."""
    return st.finish(st.tumbling(st.read_events(spark, d)), "tumbling").select(_text("start"), "event_type", "events", F.round("total", 2).alias("total"))


def stream_sliding(spark: SparkSession, d: str) -> DataFrame:
    return st.finish(st.sliding(st.read_events(spark, d)), "sliding").select(_text("start"), "events")


def stream_sessions(spark: SparkSession, d: str) -> DataFrame:
    return st.finish(st.sessions(st.read_events(spark, d)), "sessions").select("user_id", _text("start"), _text("end"), "events")


def stream_complete_counts(spark: SparkSession, d: str) -> DataFrame:
    """Complete mode: all totals by type, rewritten with each batch."""
    events = st.read_events(spark, d)
    return st.finish(events.groupBy("event_type").agg(F.count(F.lit(1)).alias("events")), "complete", mode="complete")


def stream_interval_join(spark: SparkSession, d: str) -> DataFrame:
    events = st.read_events(spark, d)
    later, earlier = events.where("event_type = 'purchase'"), st.read_events(spark, d).where("event_type <> 'purchase'")
    return st.finish(st.pairs_within(later, earlier, 720), "interval")


def stream_dedup(spark: SparkSession, d: str) -> DataFrame:
    """One event for each user and type; how many stay, as which one is first may depend on the order."""
    kept = st.finish(st.deduplicated(st.read_events(spark, d), ["user_id", "event_type"]), "dedup")
    return kept.groupBy("event_type").agg(F.count(F.lit(1)).alias("users"))


def stream_late_drop(spark: SparkSession, d: str) -> DataFrame:
    """Daily counts when the first half of the month arrives after the second: those rows are late and go."""
    path = st.scratch(spark, "late")
    events = table(spark, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "event_type", "value", "user_id")
    half = F.date_format("ts", "dd").cast("int") >= 16
    events.where(half).coalesce(1).write.parquet(f"{path}/day=1")
    events.where(~half).coalesce(1).write.parquet(f"{path}/day=2")
    kept = None
    marks, out = st.scratch(spark, "late-marks"), st.scratch(spark, "late-out")
    for day in (1, 2):
        # The same query goes on from its checkpoint with the files that came meanwhile.
        stream = spark.readStream.schema(events.schema).parquet(f"{path}/day={{{','.join(map(str, range(1, day + 1)))}}}")
        st.tumbling(stream).writeStream.format("parquet").option("path", out).option("checkpointLocation", marks).trigger(availableNow=True).start().awaitTermination()
        kept = spark.read.parquet(out)
    return kept.select(_text("start"), "event_type", "events", F.round("total", 2).alias("total"))


def stream_standing_top_k(spark: SparkSession, d: str) -> DataFrame:
    points = _vectors(st.read_events(spark, d), spark, d)
    found = st.finish(st.standing_top_k(points, {"noon": [0.5, 0.1, 0.5], "night": [0.0, 0.2, 0.1]}, 5), "standing", mode="update")
    return found.select("anchor", "rank_no", "point_id", F.round("dist", 6).alias("dist"))


_DAYS = "SELECT time_bucket(INTERVAL 1 DAY, ts) AS s, event_type, value FROM events"
_L2 = "sqrt((v[1]-a[1])*(v[1]-a[1]) + (v[2]-a[2])*(v[2]-a[2]) + (v[3]-a[3])*(v[3]-a[3]))"

QUERIES = {
    "stream_exact": (_searched("exact", 4.0), nearest_sql("events3")),
    "stream_oneshot": (_searched("oneshot", 2.0), oneshot_sql("events3", 2.0)),
    # A window is closed once the watermark, an hour behind the last event, has passed its end.
    "stream_tumbling_nn": (stream_tumbling, f"SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS events, round(sum(value::DECIMAL(20,6))::DOUBLE, 2) AS total FROM ({_DAYS}) WHERE s + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR GROUP BY s, event_type"),
    "stream_sliding_density": (stream_sliding, "WITH w AS (SELECT time_bucket(INTERVAL 3 HOUR, ts) - i * INTERVAL 3 HOUR AS s FROM events, (VALUES (0), (1)) v(i)) SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS events FROM w WHERE s + INTERVAL 6 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR GROUP BY s"),
    "stream_session_users": (stream_sessions, "WITH g AS (SELECT *, ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) > INTERVAL 12 HOUR AS fresh FROM events), n AS (SELECT *, sum(coalesce(fresh, true)::INTEGER) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS run FROM g), s AS (SELECT user_id, min(ts) AS a, max(ts) + INTERVAL 12 HOUR AS b, count(*) AS events FROM n GROUP BY user_id, run) SELECT user_id, strftime(a, '%Y-%m-%d %H:%M:%S') AS start, strftime(b, '%Y-%m-%d %H:%M:%S') AS \"end\", events FROM s WHERE b <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR"),
    "stream_late_drop": (stream_late_drop, f"SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS events, round(sum(value::DECIMAL(20,6))::DOUBLE, 2) AS total FROM ({_DAYS}) WHERE day(s) >= 16 AND s + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR GROUP BY s, event_type"),
    "stream_complete_counts": (stream_complete_counts, "SELECT event_type, count(*) AS events FROM events GROUP BY event_type"),
    "stream_interval_join": (stream_interval_join, "SELECT a.event_id AS later_id, b.event_id AS earlier_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts - INTERVAL 720 MINUTE AND b.ts < a.ts WHERE a.event_type = 'purchase' AND b.event_type <> 'purchase'"),
    "stream_dedup": (stream_dedup, "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type"),
    "stream_standing_topk": (stream_standing_top_k, f"WITH p AS ({features.SQL['events3']}), a AS (SELECT * FROM (VALUES ('noon', [0.5, 0.1, 0.5]::DOUBLE[]), ('night', [0.0, 0.2, 0.1]::DOUBLE[])) t(anchor, a)), d AS (SELECT anchor, id, {_L2} AS d FROM p, a) SELECT anchor, row_number() OVER (PARTITION BY anchor ORDER BY d, id)::INTEGER AS rank_no, id AS point_id, round(d, 6) AS dist FROM d QUALIFY rank_no <= 5"),
}
