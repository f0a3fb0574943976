"""Streams of queries against a static cover, standing queries, and windows over events.

A stream is searched micro-batch by micro-batch with the batch operators, so its
answers are the batch answers; only deduplication, windows and standing queries
keep state.
"""

from __future__ import annotations

import os
import re
import uuid
from collections.abc import Callable, Iterator
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from nearfield.operators import exact, oneshot
from nearfield.operators.cover import Cover
from nearfield.sources.points import PointSet
from nearfield.sources.scratch import shared_dir


def scratch(spark: SparkSession, name: str) -> str:
    """A fresh folder for checkpoints and sinks in the session's shared folder."""
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def read_events(spark: SparkSession, sf_dir: str, files_per_batch: int = 1) -> DataFrame:
    """The events table as a stream of files; its zone-less times become times, as watermarks need."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    source = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch)
    if re.match(r"^[a-z][a-z0-9+.-]*://", sf_dir) or os.path.isdir(f"{sf_dir}/events.parquet"):
        stream = source.parquet(f"{sf_dir}/events.parquet")
    else:
        stream = source.option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def finish(stream: DataFrame, name: str, mode: str = "append", each: Callable[[DataFrame, int], None] | None = None) -> DataFrame:
    """Run a stream over what is there, and read what it wrote.

    Complete and update results go through ``foreachBatch``: each batch rewrites
    all rows, or the folder of its own number, so a batch that is run again
    leaves its rows once.
    """
    spark = stream.sparkSession
    out, marks = scratch(spark, f"{name}-out"), scratch(spark, f"{name}-marks")
    writer = stream.writeStream.option("checkpointLocation", marks).trigger(availableNow=True).outputMode(mode)
    if each is not None or mode != "append":
        def put(batch: DataFrame, number: int) -> None:
            if each is not None:
                batch = each(batch, number)
            batch.write.mode("overwrite").parquet(out if mode == "complete" else f"{out}/batch={number}")

        writer.foreachBatch(put).start().awaitTermination()
        return spark.read.parquet(out).drop("batch")
    writer.format("parquet").option("path", out).start().awaitTermination()
    return spark.read.parquet(out)


def search_stream(stream: PointSet, cover: Cover, mode: str = "exact", k: int = 1, name: str = "search") -> DataFrame:
    """Answers to a stream of queries: ``query_id, neighbor_id, dist, rank_no``.

    Each micro-batch is searched against the cover, which is read once for the
    whole run; nothing of a batch outlives it.
    """

    def each(batch: DataFrame, number: int) -> DataFrame:
        q = PointSet(batch, stream.metric)
        return exact.search(q, cover, k) if mode == "exact" else oneshot.search(q, cover, k)

    return finish(stream.df, name, each=each)


def tumbling(events: DataFrame, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Closed windows: events and the mean of their values by type."""
    return (
        events.withWatermark("ts", late)
        .groupBy(F.window("ts", width).alias("w"), "event_type")
        .agg(F.count(F.lit(1)).alias("events"), F.sum(F.col("value").cast("decimal(20,6)")).alias("total"))
        .select(F.col("w.start").alias("start"), "event_type", "events", F.col("total").cast("double").alias("total"))
    )


def sliding(events: DataFrame, width: str = "6 hours", step: str = "3 hours", late: str = "1 hour") -> DataFrame:
    """How dense events are in overlapping windows."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", width, step).alias("w")).agg(F.count(F.lit(1)).alias("events")).select(F.col("w.start").alias("start"), "events")


def sessions(events: DataFrame, gap: str = "12 hours", late: str = "1 hour") -> DataFrame:
    """Each user's runs of events without a pause longer than the gap."""
    return (
        events.withWatermark("ts", late)
        .groupBy(F.session_window("ts", gap).alias("w"), "user_id")
        .agg(F.count(F.lit(1)).alias("events"))
        .select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "events")
    )


def pairs_within(left: DataFrame, right: DataFrame, minutes: int, late: str = "1 hour") -> DataFrame:
    """A user's purchases with the views up to ``minutes`` before: an interval join of two streams."""
    a = left.withWatermark("ts", late).select(F.col("event_id").alias("later_id"), F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts"))
    b = right.withWatermark("ts", late).select(F.col("event_id").alias("earlier_id"), F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts"))
    met = (F.col("a_user") == F.col("b_user")) & (F.col("b_ts") >= F.col("a_ts") - F.expr(f"INTERVAL {minutes} MINUTES")) & (F.col("b_ts") < F.col("a_ts"))
    return a.join(b, met).select("later_id", "earlier_id")


def deduplicated(events: DataFrame, columns: list[str], late: str = "40 days") -> DataFrame:
    """The first of the events that agree in ``columns`` within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(columns)


def standing_top_k(points: DataFrame, anchors: dict[str, list[float]], k: int) -> DataFrame:
    """Standing queries: the k nearest of all points seen so far, for a few fixed anchors; state is k rows each.

    ``points`` is a stream of (point_id, value).
    """
    literal = F.map_from_arrays(F.array(*[F.lit(a) for a in anchors]), F.array(*[F.array(*[F.lit(float(v)) for v in vec]) for vec in anchors.values()]))
    width = len(next(iter(anchors.values())))
    asked = points.select("point_id", "value", F.explode(literal).alias("anchor", "at"))
    from nearfield.functions.metrics import l2

    scored = asked.select("anchor", "point_id", l2(width).column(F.col("value"), F.col("at")).alias("dist"))

    def update(key: tuple[Any, ...], rows: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = list(zip(*state.get, strict=True)) if state.exists else []
        for frame in rows:
            held = sorted({*held, *zip(frame["dist"].tolist(), frame["point_id"].tolist(), strict=True)})[:k]
        state.update(([d for d, _ in held], [i for _, i in held]))
        yield pd.DataFrame({"anchor": key[0], "rank_no": range(1, len(held) + 1), "point_id": [i for _, i in held], "dist": [d for d, _ in held]})

    return scored.groupBy("anchor").applyInPandasWithState(update, "anchor string, rank_no int, point_id long, dist double", "dists array<double>, ids array<long>", "update", GroupStateTimeout.NoTimeout)
