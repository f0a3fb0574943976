"""Approximate nearest neighbours along shifted space-filling curves.

Vectors are projected to a few random directions, shifted and cut to a grid; the
Hilbert curve through the grid puts them in order.  Several such orderings, each
with its own directions and shift, are range-partitioned by Spark, and every row
gets its rank in each.  A query looks at the rows whose rank is within a window
of its own, in every ordering; what the windows hold is merged and ranked by true
distance in the full space.

The window is fitted, not guessed: for a bounded sample of rows the true
neighbours are found by brute force over all rows, and the window is the rank
distance that catches the wanted share of them in their best ordering.  On
clustered data it stays narrow; on data without structure, where no ordering can
help, it widens until the recall holds.

Copies of one vector tie for every query, so only the k + 1 of least id are
candidates, and any other copy asks from the place of the first: no window has to
span a run of copies, and ties by id hold however many there are.

Rows are cut into blocks of ranks; a query goes to the blocks its window meets,
and the queries of a block to groups, so a task holds one block and about ASKED
queries, whatever the table's size and however wide the window.  Queries with one
vector ask once.

Defined results: rows without id, or whose vector is null, empty, zero, of an
unusual width or holds what is null or not finite, take no part; rows that
repeat an id count as one candidate at its nearest vector, and of those that
repeat a query's id the least vector asks; fewer candidates than k give all that
are found; an empty table gives an empty table; ties go to the smaller id.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from nearfield.llm.common import discard, keep, temporaries
from nearfield.llm.vectors import matrix, usable

ORDERINGS, DIRECTIONS, BITS = 4, 8, 7
#: Rows that fit the grid; of them, rows whose true neighbours fit the window.
GRID_SAMPLE, WINDOW_SAMPLE = 2048, 128
#: The share of true neighbours that the window must catch, and the least window.
WANTED, LEAST_WINDOW = 0.97, 512
BLOCK = 4096
#: Queries that meet a block in one task, about.
ASKED = 2048
#: Pairs that are measured at once.
MEASURED = 1 << 15


def hilbert_keys(cells: np.ndarray, bits: int = BITS) -> np.ndarray:
    """Places on the Hilbert curve of grid cells (rows by axes), for all rows at once.

    The published bit-transposition form: undo the excess work from the highest
    bit down, take Gray codes across the axes, and interleave the bits.
    """
    axes = [cells[:, i].astype(np.int64) for i in range(cells.shape[1])]
    n = len(axes)
    bit = 1 << (bits - 1)
    while bit > 1:
        low = bit - 1
        for i in range(n):
            on = (axes[i] & bit) != 0
            swap = np.where(on, 0, (axes[0] ^ axes[i]) & low)
            axes[0] ^= np.where(on, low, swap)
            if i:
                axes[i] ^= swap
        bit >>= 1
    for i in range(1, n):
        axes[i] ^= axes[i - 1]
    flip = np.zeros_like(axes[0])
    bit = 1 << (bits - 1)
    while bit > 1:
        flip ^= np.where((axes[n - 1] & bit) != 0, bit - 1, 0)
        bit >>= 1
    key = np.zeros_like(axes[0])
    for b in range(bits - 1, -1, -1):
        for i in range(n):
            key = (key << 1) | (((axes[i] ^ flip) >> b) & 1)
    return key


class Grid:
    """Directions, centres, spreads and shifts of all orderings, from a sample of rows."""

    def __init__(self, sample: np.ndarray, orderings: int = ORDERINGS, directions: int = DIRECTIONS):
        rng = np.random.default_rng(5)
        width = sample.shape[1]
        directions = min(directions, width)
        self.turns = []
        for _ in range(orderings):
            basis = np.linalg.qr(rng.standard_normal((width, width)))[0][:, :directions]
            seen = sample @ basis
            self.turns.append((basis, seen.mean(axis=0), seen.std(axis=0) + 1e-12, rng.uniform(0, 1, directions)))

    def keys(self, points: np.ndarray) -> list[np.ndarray]:
        cells = 1 << BITS
        out = []
        for basis, centre, spread, shift in self.turns:
            # Six standard deviations fill half of the grid; the shift moves them within it.
            place = ((points @ basis - centre) / spread + 3) / 12 * cells + shift * cells / 2
            out.append(hilbert_keys(np.clip(place, 0, cells - 1).astype(np.int64)))
        return out


def exact_nearest(points: np.ndarray, ids: np.ndarray, queries: np.ndarray, query_ids: np.ndarray, k: int, apart: bool = True) -> pd.DataFrame:
    """Each query's k nearest ids of these points: by true distance, then the smaller id; ``apart`` leaves out its own.

    Products give the squared distances up to rounding.  Every row that rounding
    could place among the k nearest, however many tie there, is measured anew.
    """
    by_id = np.argsort(ids, kind="stable")
    points, ids = points[by_id], ids[by_id]
    own = query_ids[:, None] == ids[None, :] if apart else np.zeros((len(query_ids), len(ids)), bool)
    norms = (points**2).sum(axis=1)
    squared = norms[None, :] - 2 * queries @ points.T
    squared[own] = np.inf
    # An id that repeats is one candidate.
    starts = np.flatnonzero(np.r_[True, ids[1:] != ids[:-1]])
    each = squared if len(starts) == len(ids) else np.minimum.reduceat(squared, starts, axis=1)
    last = min(k, each.shape[1]) - 1
    slack = 8 * (points.shape[1] + 8) * np.finfo(float).eps * (norms.max() + (queries**2).sum(axis=1))
    limit = np.partition(each, last, axis=1)[:, last] + slack
    # Written so that what overflowed is measured too.
    asked, near = np.nonzero(~own & ~(squared > limit[:, None]))
    true = np.empty(len(near))
    for at in range(0, len(near), MEASURED):
        part = slice(at, at + MEASURED)
        true[part] = np.sqrt(((points[near[part]] - queries[asked[part]]) ** 2).sum(axis=1))
    order = np.lexsort((ids[near], true, asked))
    out = pd.DataFrame({"query_id": query_ids[asked], "vec_id": ids[near], "score": true}).iloc[order]
    out = out[np.isfinite(out["score"])]
    if len(starts) < len(ids):
        out = out.drop_duplicates(["query_id", "vec_id"])
    return out.groupby("query_id", sort=False).head(k)


_FOUND = "query_id long, vec_id long, score double"


def _ranked(points: DataFrame, grid: Grid) -> DataFrame:
    """``turn, rank, vec_id, vec``: every row once in each ordering."""

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                for turn, keys in enumerate(grid.keys(matrix(batch.column("vec")))):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(keys), turn, np.int32)), pa.array(keys), batch.column("vec_id"), batch.column("vec")], ["turn", "key", "vec_id", "vec"])

    rows = points.select("vec_id", "vec").mapInArrow(keyed, "turn int, key long, vec_id long, vec array<double>")
    ordered = rows.repartitionByRange("turn", "key", "vec_id").sortWithinPartitions("turn", "key", "vec_id")
    # Partition and place in it are written with the rows: they must not be drawn again.
    placed = keep(ordered.select("turn", "vec_id", "vec", F.spark_partition_id().alias("part"), F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)).alias("place")))
    sizes = placed.groupBy("part").agg(F.count(F.lit(1)).alias("n")).orderBy("part").collect()
    starts, at = [], 0
    for r in sizes:
        starts.append((r.part, at))
        at += r.n
    offsets = points.sparkSession.createDataFrame(starts or [(0, 0)], "part int, start long")
    # One row for each partition of the shuffle.  Every ordering has all rows, so its ranks start where it does.
    rank = F.col("start") + F.col("place") - F.col("turn") * F.lit(at // len(grid.turns))
    return placed.join(F.broadcast(offsets), "part").select("turn", rank.alias("rank"), "vec_id", "vec")


def _fitted_window(points: DataFrame, ranked: DataFrame, sample: list, k: int, wanted: float) -> int:
    ids, asked = np.array([r.vec_id for r in sample]), np.array([r.vec for r in sample])

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = None
        for batch in batches:
            if batch.num_rows:
                found = exact_nearest(matrix(batch.column("vec")), batch.column("vec_id").to_numpy(), asked, ids, k)
                best = found if best is None else pd.concat((best, found)).sort_values(["query_id", "score", "vec_id"]).drop_duplicates(["query_id", "vec_id"]).groupby("query_id").head(k)
        if best is not None:
            yield pa.RecordBatch.from_pandas(best, preserve_index=False)

    found = points.select("vec_id", "vec").mapInArrow(local, _FOUND).groupBy("query_id", "vec_id").agg(F.min("score").alias("score"))
    near = found.withColumn("r", F.row_number().over(Window.partitionBy("query_id").orderBy("score", "vec_id"))).where(F.col("r") <= k)
    pairs = [(r.query_id, r.vec_id) for r in near.select("query_id", "vec_id").collect()]
    if not pairs:
        return LEAST_WINDOW
    named = points.sparkSession.createDataFrame([(i,) for i in sorted({x for p in pairs for x in p})], "vec_id long")
    rank: dict[tuple[int, int], int] = {(r.vec_id, r.turn): r.rank for r in ranked.select("vec_id", "turn", "rank").join(F.broadcast(named), "vec_id", "left_semi").collect()}
    turns = sorted({t for _, t in rank})
    best = [min(abs(rank[q, t] - rank[x, t]) for t in turns) for q, x in pairs]
    return max(LEAST_WINDOW, int(np.quantile(best, wanted)) + 1)


def nearest(df: DataFrame, every: int = 100, k: int = 10, wanted: float = WANTED, block: int = BLOCK) -> DataFrame:
    """``query_id, rank, vec_id, score``: the k nearest rows found for each query, by true distance."""
    spark = df.sparkSession
    given = usable(df, nonzero=True).select(F.col("vec_id").cast("long").alias("vec_id"), "vec", F.xxhash64("vec").alias("same"))
    # Copies are equally far from any query, so those of the k + 1 least ids (one may ask) are all that can be an answer.
    copies = Window.partitionBy("same", "vec").orderBy("vec_id")
    points = keep(given.withColumn("copy", F.dense_rank().over(copies)).where(F.col("copy") <= k + 1))
    sample = points.orderBy(F.xxhash64("vec_id"), "vec_id").limit(GRID_SAMPLE).collect()
    if not sample:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    grid = Grid(np.array([r.vec for r in sample]))
    with temporaries() as spared:
        ranked = keep(_ranked(points, grid))
        spared.append(ranked)
    window = _fitted_window(points, ranked, list({r.vec_id: r for r in sample[:WINDOW_SAMPLE]}.values()), k, wanted)
    # Every query asks, also one that is no candidate; those with one vector ask once, at the place of its first copy.
    queries = given.where(F.col("vec_id") % every == 0).groupBy(F.col("vec_id").alias("query_id")).agg(F.min(F.struct("vec", "same")).alias("x")).select("query_id", "x.*")
    first = points.where(F.col("copy") == 1).select("same", "vec", F.col("vec_id").alias("first"))
    queries = keep(queries.join(first, ["same", "vec"]))
    discard(points)

    # A block is part of one ordering, so no row is in it twice.
    rows = ranked.select("turn", F.floor(F.col("rank") / block).alias("block"), "vec_id", "vec")
    places = ranked.select("turn", "rank", F.col("vec_id").alias("first"), F.xxhash64("vec").alias("same"))
    once = queries.groupBy("first").agg(F.min("same").alias("same"), F.min("vec").alias("vec"))
    asking = once.join(places, ["first", "same"]).groupBy("first", "turn").agg(F.min(F.struct("rank", "vec")).alias("x"))
    reach = F.sequence(F.floor(F.greatest(F.col("x.rank") - window, F.lit(0)) / block), F.floor((F.col("x.rank") + window) / block))
    sent = keep(asking.select("turn", F.explode(reach).alias("block"), "first", F.col("x.vec").alias("vec")))
    # Where many queries reach one block they are dealt to groups, each of which meets the block in a task of its own.
    most = sent.groupBy("turn", "block").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0
    groups = max(1, -(-most // ASKED))
    rows = rows.withColumn("part", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(groups - 1).cast("long"))))
    asked = sent.withColumn("part", F.pmod(F.xxhash64("first"), F.lit(groups)))

    def meet(own: pa.Table, queries: pa.Table) -> pa.Table:
        if not own.num_rows or not queries.num_rows:
            return schema.empty_table()
        points_, ids = matrix(own.column("vec")), own.column("vec_id").to_numpy()
        parts = []
        for at in range(0, queries.num_rows, 256):
            some = queries.slice(at, 256)
            parts.append(exact_nearest(points_, ids, matrix(some.column("vec")), some.column("first").to_numpy(), k + 1, False))
        return pa.Table.from_pandas(pd.concat(parts), schema=schema, preserve_index=False)

    schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.float64())])
    found = rows.groupBy("turn", "block", "part").cogroup(asked.groupBy("turn", "block", "part")).applyInArrow(meet, _FOUND)
    merged = found.groupBy(F.col("query_id").alias("first"), "vec_id").agg(F.min("score").alias("score"))
    best = merged.withColumn("place", F.row_number().over(Window.partitionBy("first").orderBy("score", "vec_id"))).where(F.col("place") <= k + 1)
    # One of the k + 1 may be the query itself.
    told = queries.select("query_id", "first").join(best, "first").where(F.col("vec_id") != F.col("query_id"))
    order = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return told.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
