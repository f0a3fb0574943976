"""Shortest-path distances from a few sources by rounds of relaxation."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from nearfield.sources.scratch import shared_dir


def shortest_paths(edges: DataFrame, sources: DataFrame, max_rounds: int = 50, every: int = 3) -> DataFrame:
    """``source, node, dist`` over edges (src, dst, weight), both ways.

    Each round extends the best distances by one edge and keeps the least; the
    lineage is cut every few rounds, and rounds end when nothing improves.
    """
    both = edges.select("src", "dst", "weight").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight"))
    best = sources.select(F.col("node").alias("source"), "node", F.lit(0.0).alias("dist"))
    before = None
    for turn in range(1, max_rounds + 1):
        step = best.join(both, best["node"] == both["src"]).select("source", F.col("dst").alias("node"), (F.col("dist") + F.col("weight")).alias("dist"))
        best = best.unionByName(step).groupBy("source", "node").agg(F.min("dist").alias("dist"))
        if turn % every == 0:
            best = _cut(best)
            now = best.agg(F.count(F.lit(1)), F.sum(F.round("dist", 9).cast("decimal(38,9)"))).first()
            if now == before:
                break
            before = now
    return best


#: Paths whose lengths differ by less than this may be equal once they are rounded to nine places.
TIE = 4e-9


def nearest_targets(edges: DataFrame, targets: DataFrame, max_rounds: int = 50, every: int = 3) -> DataFrame:
    """``node, target, dist``: the nearest of ``targets`` (node) of every node over edges (src, dst, weight), both ways.

    Each round sends what a node knows of its nearest targets one edge on, so a
    node has a few rows however many sources and targets there are.  Of targets at
    one distance the least name stays; rows within ``TIE`` of the least distance
    stay too, for callers that round it.
    """
    both = edges.select("src", "dst", "weight").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight"))
    best = targets.select("node", F.col("node").alias("target"), F.lit(0.0).alias("dist"))
    before = None
    for turn in range(1, max_rounds + 1):
        step = best.join(both, best["node"] == both["src"]).select(F.col("dst").alias("node"), "target", (F.col("dist") + F.col("weight")).alias("dist"))
        known = best.unionByName(step)
        least = F.min("dist").over(Window.partitionBy("node"))
        best = known.groupBy("node", "dist").agg(F.min("target").alias("target")).withColumn("least", least).where(F.col("dist") <= F.col("least") + TIE).select("node", "target", "dist")
        if turn % every == 0:
            best = _cut(best)
            now = best.agg(F.count(F.lit(1)), F.sum(F.round("dist", 9).cast("decimal(38,9)")), F.sum(F.crc32("target"))).first()
            if now == before:
                break
            before = now
    return best


def _cut(df: DataFrame) -> DataFrame:
    """checkpoint() into the session's shared folder."""
    shared_dir(df.sparkSession)
    return df.checkpoint()


def geography(region: DataFrame, nation: DataFrame, customer: DataFrame, supplier: DataFrame) -> DataFrame:
    """Edges of the tree region - nation - customer or supplier, under one root: weight 1 + |balance| / 10000 (1 without a balance)."""
    plain = F.lit(1.0).alias("weight")
    leaf = lambda key, nation_key, balance, kind: [F.concat(F.lit(kind), F.col(key).cast("string")).alias("src"), F.concat(F.lit("n"), F.col(nation_key).cast("string")).alias("dst"), (F.lit(1.0) + F.abs(balance) / 10000.0).alias("weight")]
    return (
        region.select(F.concat(F.lit("r"), F.col("r_regionkey").cast("string")).alias("src"), F.lit("root").alias("dst"), plain)
        .unionByName(nation.select(F.concat(F.lit("n"), F.col("n_nationkey").cast("string")).alias("src"), F.concat(F.lit("r"), F.col("n_regionkey").cast("string")).alias("dst"), plain))
        .unionByName(customer.select(*leaf("c_custkey", "c_nationkey", "c_acctbal", "c")))
        .unionByName(supplier.select(*leaf("s_suppkey", "s_nationkey", "s_acctbal", "s")))
    )
