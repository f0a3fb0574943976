"""Connected components by alternating large-star and small-star rounds."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nearfield.llm.common import keep

#: So many edges at most go through their rounds in one task, whose size this bounds; more take a job for each half round.
LOCAL = 1 << 19


def _large_star(edges: DataFrame) -> DataFrame:
    """Each node's larger neighbours move to the least node around it."""
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = keep(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m")))
    return both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _small_star(edges: DataFrame) -> DataFrame:
    """Each node and its smaller neighbours move to the least of those."""
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = keep(down.groupBy("u").agg(F.min("v").alias("m")))
    moved = down.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionByName(least.select("u", F.col("m").alias("v"))).where("u <> v")


def _is_stars(edges: DataFrame) -> bool:
    """Whether every node points to one node, and none of those points on."""
    if not edges.groupBy("u").agg(F.count(F.lit(1)).alias("n")).where("n > 1").isEmpty():
        return False
    return edges.select("v").distinct().join(edges.select(F.col("u").alias("v")), "v", "left_semi").isEmpty()


def _once(u: np.ndarray, v: np.ndarray, nodes: int) -> tuple[np.ndarray, np.ndarray]:
    apart = u != v
    return np.divmod(np.unique(u[apart] * nodes + v[apart]), nodes)


def stars(u: np.ndarray, v: np.ndarray, nodes: int) -> tuple[np.ndarray, np.ndarray]:
    """The rounds of ``components`` on edges in memory; nodes are numbered in their order."""
    u, v = _once(u, v, nodes)
    while True:
        least = np.arange(nodes)
        np.minimum.at(least, u, v)
        np.minimum.at(least, v, u)
        low, high = np.minimum(u, v), np.maximum(u, v)
        large = _once(high, least[low], nodes)
        u, v = np.maximum(*large), np.minimum(*large)
        least = np.arange(nodes)
        np.minimum.at(least, u, v)
        small = _once(np.concatenate((v, u)), least[np.concatenate((u, u))], nodes)
        # Stars: each node has one edge, and no centre has any.
        u, v = small
        if len(np.unique(u)) == len(u) and not np.isin(v, u).any():
            return u, v


def _in_one_task(edges: DataFrame) -> DataFrame:
    def settle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if held:
            table = pa.Table.from_batches(held)
            names, code = np.unique(np.concatenate([table.column(c).to_numpy() for c in ("u", "v")]), return_inverse=True)
            u, v = stars(code[: table.num_rows], code[table.num_rows :], len(names))
            yield pa.RecordBatch.from_arrays([pa.array(names[u], table.schema.field("u").type), pa.array(names[v], table.schema.field("v").type)], ["node", "component"])

    kind = edges.schema["u"].dataType
    return edges.coalesce(1).mapInArrow(settle, T.StructType([T.StructField("node", kind), T.StructField("component", kind)]))


def components(edges: DataFrame, max_rounds: int = 50, local: int = LOCAL) -> DataFrame:
    """``node, component`` for every node of ``edges`` (u, v) but the least of each component.

    Each round writes its edges, so no lineage grows; a star's centre is summed
    on the map side, and its least node meets the edges by a join that Spark can
    broadcast or split.  Rounds end when only stars are left: then the centre of
    a star is its least node.  Edges from a node to itself say nothing and go.

    Up to ``local`` edges take the same rounds within one task: some hundred
    stages of almost no rows cost far more than the rows.
    """
    edges = keep(edges.where("u <> v").select("u", "v").distinct())
    if edges.count() <= local:
        return keep(_in_one_task(edges))
    for _ in range(max_rounds):
        edges = keep(_large_star(edges).where("u <> v").distinct())
        edges = keep(_small_star(edges).distinct())
        if _is_stars(edges):
            found = edges.select(F.col("u").alias("node"), F.col("v").alias("component"))
            found._kept_at = edges._kept_at
            return found
    raise RuntimeError(f"components: no fixed point after {max_rounds} rounds")
