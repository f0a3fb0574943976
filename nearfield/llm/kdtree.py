"""Exact top-k inner products with KD-trees, one for each shard.

Vectors are dealt at random to shards of a mean size; each shard becomes one
tree: median splits of the widest side, a tight box around every node.  The most
that a query can score in a box follows from its corners, so a best-first walk
opens the boxes in order of that bound and ends when it falls below the k-th
score so far.

Queries go in blocks.  First every block searches one shard; the k-th scores it
finds are passed on as the bounds with which it enters all other shards, where
most boxes then fall at once or never yield a row.  Blocks and shards meet by
shard number; a block's rows repeat once a shard, a shard's never.

Scores are integers: the arithmetic is the narrowest that is exact for the
values at hand (float32, float64 or int64).

Defined results: rows without id, or whose vector is null, empty, of an unusual
width or holds what is null or not finite, take no part; of rows that repeat a
query's id the least vector asks, and none of them is its candidate; repeated
candidates each count; fewer than k candidates give all; no query or an empty
table gives an empty table; ties go to the smaller id.
"""

from __future__ import annotations

import heapq
import pickle
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from nearfield.llm.common import keep
from nearfield.llm.vectors import matrix, usable

#: Mean vectors of a shard, most vectors of a leaf, mean queries of a block.
SHARD, LEAF, BLOCK = 16_384, 256, 1024
#: Blocks of queries that a tree is sent to a task for.
GROUP = 8
SCALE = 64
_PAIRS = "query_id long, vec_id long, score long"


class Tree:
    def __init__(self, ids: np.ndarray, points: np.ndarray, leaf: int = LEAF):
        order = np.lexsort((ids,))
        #: For each node: first and last row, children (or -1).
        rows, kids, lows, highs = [], [], [], []
        todo = [(order, -1, 0)]
        placed, at = [], 0
        while todo:
            own, parent, side = todo.pop()
            box = points[own]
            low, high = box.min(axis=0), box.max(axis=0)
            node = len(rows)
            if parent >= 0:
                kids[parent][side] = node
            rows.append([at, at + len(own)])
            kids.append([-1, -1])
            lows.append(low)
            highs.append(high)
            wide = int((high - low).argmax())
            if len(own) <= leaf or high[wide] == low[wide]:
                placed.append(own)
                at += len(own)
                continue
            half = len(own) // 2
            cut = np.argpartition(box[:, wide], half)
            # The right half is left for later, so rows of a subtree stay together.
            todo.append((own[cut[half:]], node, 1))
            todo.append((own[cut[:half]], node, 0))
        order = np.concatenate(placed)
        self.ids, self.points = ids[order], points[order]
        self.rows, self.kids = np.array(rows), np.array(kids)
        self.low, self.high = np.array(lows), np.array(highs)

    def bounds(self, queries: np.ndarray) -> np.ndarray:
        """The most each query can score in each node's box."""
        return np.maximum(queries, 0) @ self.high.T + np.minimum(queries, 0) @ self.low.T

    def top(self, queries: np.ndarray, ids: np.ndarray, k: int, least: np.ndarray) -> list[list[tuple[int, int]]]:
        """The (score, -id) of each query's k best rows that reach ``least``, best first."""
        bound = self.bounds(queries)
        kids, rows = self.kids.tolist(), self.rows.tolist()
        out = []
        for q, own, floor, most in zip(queries, ids, least.tolist(), bound, strict=True):
            most = most.tolist()
            heap, best, kth = [(-most[0], 0)], [], floor
            while heap and -heap[0][0] >= kth:
                node = heapq.heappop(heap)[1]
                left, right = kids[node]
                if left >= 0:
                    if most[left] >= kth:
                        heapq.heappush(heap, (-most[left], left))
                    if most[right] >= kth:
                        heapq.heappush(heap, (-most[right], right))
                    continue
                a, b = rows[node]
                scores = self.points[a:b] @ q
                for i in np.flatnonzero(scores >= kth):
                    candidate = int(self.ids[a + i])
                    if candidate == own:
                        continue
                    entry = (int(scores[i]), -candidate)
                    if len(best) < k:
                        heapq.heappush(best, entry)
                    elif entry > best[0]:
                        heapq.heapreplace(best, entry)
                if len(best) == k:
                    kth = max(floor, best[0][0])
            out.append(sorted(best, reverse=True))
        return out


def _exact_type(a: np.ndarray, b: np.ndarray) -> type:
    """The narrowest type whose sums of products are exact for these values."""
    most = float(np.abs(a).max(initial=0)) * float(np.abs(b).max(initial=0)) * max(1, a.shape[-1])
    return np.float32 if most < 2**24 else np.float64 if most < 2**53 else np.int64


def _grown(found: pd.DataFrame) -> pd.DataFrame:
    tree = Tree(found["vec_id"].to_numpy(), np.stack(found["vec"].to_numpy()))
    return pd.DataFrame({"shard": [int(found["shard"].iloc[0])], "tree": [pickle.dumps(tree, protocol=5)]})


def _searched(trees: DataFrame, blocks: DataFrame, parts: int, k: int) -> DataFrame:
    """What the trees of the blocks' shards give to their queries.

    A tree goes to each part of the blocks of its shard once and stands before
    them in their partition, so a task holds one tree and one block at a time.
    """
    placed = blocks.withColumn("part", F.floor(F.col("block") / GROUP).cast("int"))
    copies = trees.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))).join(placed.select("shard", "part").distinct(), ["shard", "part"], "left_semi")
    none = F.lit(None).cast(placed.schema["asked"].dataType)
    both = copies.select("shard", "part", F.lit(-1).alias("block"), "tree", none.alias("asked")).unionByName(placed.select("shard", "part", "block", F.lit(None).cast("binary").alias("tree"), "asked"))
    ordered = both.repartition("shard", "part").sortWithinPartitions("shard", "part", "block")

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tree = None
        for batch in batches:
            for i in range(batch.num_rows):
                if batch.column("tree")[i].is_valid:
                    tree = pickle.loads(batch.column("tree")[i].as_buffer())
                    continue
                block = batch.column("asked")[i].values
                ids = block.field("query_id").to_numpy()
                least = block.field("least").to_numpy()
                queries = matrix(block.field("vec"))
                kind = _exact_type(tree.points, queries)
                if tree.points.dtype != kind:
                    tree.points, tree.low, tree.high = (x.astype(kind) for x in (tree.points, tree.low, tree.high))
                found = tree.top(queries.astype(kind), ids, k, least)
                n = [len(x) for x in found]
                flat = np.array([e for x in found for e in x], np.int64).reshape(-1, 2)
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(ids, n)), pa.array(-flat[:, 1]), pa.array(flat[:, 0])], ["query_id", "vec_id", "score"])

    return ordered.select("tree", "asked").mapInArrow(search, _PAIRS)


def top_k(df: DataFrame, every: int = 20, k: int = 20, scale: int = SCALE, shard: int = SHARD, block: int = BLOCK) -> DataFrame:
    """``query_id, rank, vec_id, score``: the k highest integer inner products of each query.

    Queries are the rows whose id is divisible by ``every``; components become
    ``floor(scale * x)``.
    """
    scaled = usable(df).select(F.col("vec_id").cast("long").alias("vec_id"), F.transform("vec", lambda x: F.floor(F.lit(float(scale)) * x).cast("long")).alias("vec"))
    n = scaled.count()
    shards = max(1, -(-n // shard))
    # The deal is random, not by id, so repeated rows spread; it is written, so it stays.
    dealt = keep(scaled.withColumn("shard", F.floor(F.rand(11) * shards).cast("int")))
    trees = keep(dealt.groupBy("shard").applyInPandas(_grown, "shard int, tree binary"))
    queries = dealt.where(F.col("vec_id") % every == 0).groupBy(F.col("vec_id").alias("query_id")).agg(F.min("vec").alias("vec"))
    blocks = max(1, -(-n // every // block))
    lowest = F.lit(-(2**62)).cast("long")

    def asked(rows: DataFrame, least) -> DataFrame:
        return rows.groupBy("block").agg(F.collect_list(F.struct("query_id", "vec", least.alias("least"))).alias("asked"))

    placed = keep(queries.withColumn("block", F.pmod(F.xxhash64("query_id"), F.lit(blocks)).cast("int")))
    home = F.pmod(F.col("block"), F.lit(shards))
    parts = -(-blocks // GROUP)
    first = keep(_searched(trees, asked(placed, lowest).withColumn("shard", home), parts, k))
    kth = first.groupBy("query_id").agg(F.when(F.count(F.lit(1)) == k, F.min("score")).otherwise(lowest).alias("least"))
    bounded = placed.join(kth, "query_id", "left")
    away = asked(bounded, F.coalesce("least", lowest)).withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(shards - 1)))).where(F.col("shard") != home)
    found = first.unionByName(_searched(trees, away, parts, k)) if shards > 1 else first
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


#: The same rows in DuckDB SQL.
TOP_SQL = """
WITH vecs AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(64 * x::DOUBLE)::BIGINT) AS v FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), scored AS (
  SELECT q.vec_id AS query_id, c.vec_id, list_sum(list_transform(list_zip(q.v, c.v), lambda p: p[1] * p[2]))::BIGINT AS score
  FROM vecs q JOIN vecs c ON q.vec_id % 20 = 0 AND c.vec_id <> q.vec_id
)
SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank, vec_id, score
FROM scored QUALIFY rank <= 20
"""
