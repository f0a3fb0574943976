"""Edit distances in blocks: what two strings share as bags of characters bounds their distance, and only what the bound leaves is measured."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nearfield.operators import bruteforce as bf
from nearfield.operators.cover import Cover
from nearfield.operators.kernels import first_of
from nearfield.sources.points import PointSet

#: Cells of a block of bounds, pairs that are measured at once, and code points that a part of a batch may take.
BLOCK, PAIRS, POINTS = 1 << 20, 1 << 12, 1 << 22
#: Characters are counted in this many classes, each up to this count; the rest of a string counts as shared.
CLASSES, LEVELS = 64, 8
#: Bits of a word of a column, and characters that are placed by a table.
WORD, TABLE = 64, 1 << 16


class Texts:
    """Strings as code points, padded to the longest, with the bag of each."""

    def __init__(self, values: list[str]):
        self.sizes = np.array([len(v) for v in values], np.int64)
        width = max(1, int(self.sizes.max(initial=0)))
        self.codes = np.array(values, f"<U{width}").view(np.uint32).reshape(len(values), width)
        at = np.repeat(np.arange(len(values)), self.sizes) * CLASSES + self.codes[np.arange(width)[None, :] < self.sizes[:, None]] % CLASSES
        counts = np.bincount(at, minlength=len(values) * CLASSES).reshape(len(values), CLASSES)
        self.counts = np.minimum(counts, LEVELS).astype(np.uint8)
        self.rest = (counts - self.counts).sum(axis=1)
        self.letters = np.unique(self.codes)
        self.table = np.zeros(TABLE, np.int64)
        self.table[self.letters[self.letters < TABLE]] = 1 + np.arange(int((self.letters < TABLE).sum()))

    def places(self, codes: np.ndarray) -> np.ndarray:
        """Places of characters among the letters of these strings, from 1; 0 for others."""
        if codes.max(initial=0) < TABLE:
            return self.table[codes]
        at = np.minimum(np.searchsorted(self.letters, codes), len(self.letters) - 1)
        return np.where(self.letters[at] == codes, at + 1, 0) if len(self.letters) else np.zeros(codes.shape, np.int64)

    def steps(self, part: slice = slice(None)) -> np.ndarray:
        """A bag as zeros and ones, so that the product of two counts what they share."""
        own = self.counts[part]
        return (own[:, :, None] > np.arange(LEVELS)).reshape(len(own), -1).astype(np.float32)


def bounds(a: Texts, part: slice, b: Texts, steps: np.ndarray) -> np.ndarray:
    """At most the distances of a part of ``a`` to all of ``b`` (``steps``: b's): each edit changes one character of the longer bag."""
    own = a.steps(part)
    used = np.flatnonzero(own.any(axis=0))
    shared = own[:, used] @ steps[:, used].T
    if a.rest[part].any() and b.rest.any():
        shared += np.minimum(a.rest[part][:, None], b.rest[None, :])
    return np.maximum(a.sizes[part][:, None], b.sizes[None, :]).astype(np.float32) - shared


def measured(a: Texts, row: np.ndarray, b: Texts, col: np.ndarray) -> np.ndarray:
    """The distances of pairs: a column of the table of prefixes at a time as the bits of its steps up and down, for many pairs at once."""
    one, top = np.uint64(1), np.uint64(WORD - 1)
    words = max(1, -(-int(a.sizes[row].max(initial=0)) // WORD))
    out, order, step = np.empty(len(row)), np.argsort(b.sizes[col], kind="stable"), max(1, PAIRS // words)
    for at in range(0, len(row), step):
        some = order[at : at + step]
        own, place = np.unique(row[some], return_inverse=True)
        sizes, codes, letters = a.sizes[own], a.places(a.codes[own]), len(a.letters) + 1
        # Where each letter stands in a left string; what it doesn't have stands nowhere.
        stands = np.zeros((words, len(own), letters), np.uint64)
        for i in range(int(sizes.max())):
            there = np.flatnonzero(sizes > i)
            stands[i // WORD, there, codes[there, i]] |= one << np.uint64(i % WORD)
        stands = stands.reshape(words, -1)
        n, m = sizes[place], b.sizes[col[some]]
        asked = place[None, :] * letters + a.places(b.codes[col[some], : m.max()]).T
        last, bit = (np.maximum(n, 1) - 1) // WORD, ((np.maximum(n, 1) - 1) % WORD).astype(np.uint64)
        up, down = np.full((words, len(some)), ~np.uint64(0)), np.zeros((words, len(some)), np.uint64)
        score = n.astype(np.int64)
        for j in range(int(m.max())):
            # A step to the right along the edge of the table costs one; shorter right strings are done.
            plus, minus, begun = one, np.uint64(0), int(np.searchsorted(m, j, "right"))
            for w in range(words):
                p, q, same = up[w], down[w], stands[w][asked[j]]
                across = same | q
                same = same | minus
                along = (((same & p) + p) ^ p) | same
                rise, fall = q | ~(along | p), p & along
                move = ((rise >> bit) & one).astype(np.int64) - ((fall >> bit) & one).astype(np.int64)
                score[begun:] += (move if words == 1 else np.where(last == w, move, 0))[begun:]
                out_plus, out_minus = rise >> top, fall >> top
                rise, fall = (rise << one) | plus, (fall << one) | minus
                up[w], down[w] = fall | ~(across | rise), rise & across
                plus, minus = out_plus, out_minus
        out[some] = np.where(n > 0, score, m)
    return out


def least(a: Texts, b: Texts, k: int, kth: np.ndarray, floor: Callable[[slice], np.ndarray] | None = None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Pairs (row of a, row of b, distance) that hold each row's k least, ties with the k-th included.

    ``kth`` is the most that they may be, and falls to the k-th of what is measured.
    ``floor`` gives bounds of another kind for some rows of a; pairs of infinite ones don't count.
    """
    steps, step, few = b.steps(), max(1, BLOCK // max(1, len(b.sizes))), min(k, len(b.sizes))
    for at in range(0, len(a.sizes) if len(b.sizes) else 0, step):
        part = slice(at, at + step)
        low = bounds(a, part, b, steps)
        if floor is not None:
            low = np.maximum(low, floor(part))
        # The most promising ones first: what they are bounds the rest.
        near = low.argmin(axis=1)[:, None] if few == 1 else np.argpartition(low, few - 1, axis=1)[:, :few]
        row, place = np.nonzero(np.take_along_axis(low, near, axis=1) <= np.minimum(kth[part], np.finfo(np.float32).max)[:, None])
        col = near[row, place]
        dist = measured(a, at + row, b, col)
        yield at + row, col, dist
        if few == k:
            found = np.full(near.shape, np.inf)
            found[row, place] = dist
            kth[part] = np.minimum(kth[part], found.max(axis=1))
        low[row, col] = np.inf
        row, col = np.nonzero(low <= np.minimum(kth[part], np.finfo(np.float32).max)[:, None])
        dist = measured(a, at + row, b, col)
        fine = dist <= kth[at + row]
        yield at + row[fine], col[fine], dist[fine]


def sent(points: PointSet, limit: int = bf.BROADCAST_BYTES) -> tuple[np.ndarray, Texts] | None:
    """The strings in the order of their ids, if they may be sent to every task, padded as they are."""
    known = points.df.where(F.col("value").isNotNull()).select("point_id", "value")
    rows, longest = known.agg(F.count(F.lit(1)), F.max(F.length("value"))).first()
    if rows * (4 * (longest or 0) + CLASSES + 24) > limit:
        return None
    table = known.toArrow()
    ids = bf.ids_of(table.column("point_id"))
    order = np.argsort(ids, kind="stable")
    return ids[order], Texts(table.column("value").combine_chunks().take(pa.array(order)).to_pylist())


def _parts(ids: pa.Array, texts: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray, Texts]]:
    """Places, ids and strings of a batch in the order of the ids, in parts that long ones don't make large."""
    ids, values = bf.ids_of(ids), texts.to_pylist()
    order = np.argsort(ids, kind="stable")
    step = max(1, POINTS // max(1, max(map(len, values), default=1)))
    for at in range(0, len(ids), step):
        some = order[at : at + step]
        yield some, ids[some], Texts([values[i] for i in some])


class _Best:
    """The k least of each of ``n`` strings so far, over all batches of a task; ties to the smaller id."""

    def __init__(self, n: int, k: int, kth: np.ndarray | None = None):
        self.n, self.k, self.kth, self.held = n, k, np.full(n, np.inf) if kth is None else kth.copy(), None

    def add(self, ids: np.ndarray, found: list[tuple]) -> None:
        for row, col, dist in found:
            near = ids[col]
            if self.held is not None:
                row, near, dist = (np.concatenate(c) for c in zip(self.held, (row, near, dist), strict=True))
            names, code = np.unique(near, return_inverse=True)
            places, dists = first_of(row, code, dist, self.n, self.k)
            row, rank = np.nonzero(np.isfinite(dists))
            self.held = row, names[places[row, rank]], dists[row, rank]

    def rows(self, schema: T.StructType, ids: np.ndarray) -> Iterator[pa.RecordBatch]:
        if self.held is not None:
            row, near, dist = self.held
            yield bf._batch(schema, ids[row], near, dist)


def nearest(q: PointSet, x: PointSet, k: int, small: str, not_self: bool = False) -> DataFrame | None:
    """k rows for each query and task: ``query_id, neighbor_id, dist``; None if the small side may not be sent. Nulls take no part."""
    fixed = sent(q if small == "q" else x)
    if fixed is None:
        return None
    s_ids, texts = fixed
    schema = bf.schema_of(q, x)

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = _Best(len(s_ids), k)
        for batch in batches:
            for _, ids, own in _parts(batch.column(0), batch.column(1)) if len(s_ids) else ():
                a, b, a_ids, b_ids = (texts, own, s_ids, ids) if small == "q" else (own, texts, ids, s_ids)
                to = best if small == "q" else _Best(len(ids), k)
                apart = lambda part: np.where(a_ids[part][:, None] == b_ids[None, :], np.float32(np.inf), np.float32(0))  # noqa: B023, E731
                to.add(b_ids, [_joined(least(a, b, k, to.kth, apart if not_self else None))])
                if small == "x":
                    yield from to.rows(schema, ids)
        yield from best.rows(schema, s_ids)

    big = (x if small == "q" else q).df.where(F.col("value").isNotNull())
    return big.select("point_id", "value").mapInArrow(search, schema)


def _joined(found: Iterator[tuple]) -> tuple:
    parts = list(found)
    return tuple(np.concatenate(c) for c in zip(*parts, strict=True)) if parts else (np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0))


def _routed(q: PointSet, texts: Texts) -> DataFrame:
    """``point_id, value, dists``: each query with its distances to all pivots, four bytes each."""
    schema = T.StructType([*q.df.select("point_id", "value").schema.fields, T.StructField("dists", T.BinaryType())])

    def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = len(texts.sizes)
        for batch in batches:
            step = max(1, min(PAIRS, POINTS // max(1, n)))
            for at in range(0, batch.num_rows, step):
                some = batch.slice(at, step)
                own = Texts(some.column(1).to_pylist())
                row, col = np.divmod(np.arange(some.num_rows * n), max(1, n))
                dists = measured(own, row, texts, col).astype(np.int32).reshape(some.num_rows, n)
                yield pa.RecordBatch.from_arrays([some.column(0), some.column(1), pa.array([d.tobytes() for d in dists], pa.binary())], schema.names)

    return q.df.where(F.col("value").isNotNull()).select("point_id", "value").mapInArrow(route, schema)


def search(q: PointSet, cover: Cover, k: int, rules: tuple[str, ...], ring: bool, limit: int = bf.BROADCAST_BYTES) -> DataFrame | None:
    """What an exact search finds: ``query_id, neighbor_id, dist``, k rows for each query and task and the k nearest pivots.

    A list's row is measured only if neither the rules, nor its ring, nor its bag
    of characters rule it out.  None if pivots, queries and the distances between
    them may not be sent to every task.
    """
    p = cover.pivots.where(F.col("value").isNotNull()).select(F.col("pivot_id").alias("point_id"), "value")
    pivots = sent(PointSet(p, q.metric))
    if pivots is None:
        return None
    names, texts = pivots
    known = q.df.where(F.col("value").isNotNull())
    m, longest = known.agg(F.count(F.lit(1)), F.max(F.length("value"))).first()
    if m * (4 * len(names) + 4 * (longest or 0) + CLASSES + 24) > limit:
        return None
    told = cover.pivots.where(F.col("value").isNotNull()).select("pivot_id", "psi", "alive").toArrow()
    order = np.argsort(bf.ids_of(told.column("pivot_id")), kind="stable")
    psi, alive = told.column("psi").to_numpy()[order], told.column("alive").to_numpy()[order]
    asked = _routed(q, texts).toArrow()
    q_ids = bf.ids_of(asked.column("point_id"))
    order = np.argsort(q_ids, kind="stable")
    q_ids, asks = q_ids[order], Texts(asked.column("value").combine_chunks().take(pa.array(order)).to_pylist())
    far = np.frombuffer(b"".join(asked.column("dists").take(pa.array(order)).to_pylist()), np.int32).reshape(len(q_ids), len(names))
    living = np.flatnonzero(alive)
    own = np.argsort(far[:, living], axis=1, kind="stable")[:, :k]
    near = np.take_along_axis(far[:, living], own, axis=1)
    kth = near[:, k - 1].astype(float) if len(living) >= k else np.full(len(q_ids), np.inf)
    first = far.min(axis=1, initial=1 << 30)
    schema = bf.schema_of(q, cover.points)

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = _Best(len(q_ids), k, kth)
        for batch in batches:
            for some, ids, values in _parts(batch.column(2), batch.column(3)) if len(q_ids) and len(names) else ():
                at = np.searchsorted(names, bf.ids_of(batch.column(0))[some])
                owner = batch.column(1).to_numpy()[some]

                def floor(part: slice) -> np.ndarray:
                    d, b = far[part][:, at], kth[part, None]  # noqa: B023
                    out = np.abs(d - owner[None, :]).astype(np.float32) if ring else np.zeros(d.shape, np.float32)  # noqa: B023
                    if "radius" in rules:
                        out[d > b + psi[at][None, :]] = np.inf  # noqa: B023
                    if "triple" in rules:
                        out[d > 2 * b + first[part, None]] = np.inf
                    return out

                best.add(ids, [_joined(least(asks, values, k, best.kth, floor))])
        yield from best.rows(schema, q_ids)

    spark = q.df.sparkSession
    row, place = np.divmod(np.arange(own.size), max(1, own.shape[1]))
    seeds = pa.Table.from_batches([bf._batch(schema, q_ids[row], names[living[own[row, place]]], near[row, place].astype(float))])
    lists = cover.lists.where(F.col("value").isNotNull()).select("pivot_id", "owner_dist", "point_id", "value")
    return lists.mapInArrow(scan, schema).unionByName(spark.createDataFrame(seeds, schema))
