"""Near-duplicate groups: universal minima, banding, signature check, full check, components.

* Every whole text becomes its set of word shingles; texts with the same set
  are one node from here on, known by a 64-bit hash of the set, so copies cost
  one row each and no pairs.
* A signature holds the minima of many universal hash functions.  Nodes that
  agree in all rows of a band share a bucket.
* Pairs are never listed bucket by bucket.  The least node of a bucket leads it
  and is compared with the other members; once components are known, only pairs
  across components are still open, and only buckets that span components have
  any.
* In those, two bounds that are exact close most pairs without a look at the
  sets.  A node's lone shingles, which no other open node holds, limit what it can
  share; and two bitmaps of shingle parities differ in no more bits than the sets
  do in shingles, so pairs whose bitmaps differ too much are never made.
* The node with the fewest lone shingles, the one nearest to the original, leads
  its bucket next.  After that only members outside its component have to lead,
  since every open pair has one of them: all at once in buckets of up to GROWTH
  members, by their hash in more and more shares in larger ones.
* A pair whose signatures agree too little goes; the rest are confirmed on the
  full sets, as integers: 100 * intersection >= percent * union.
* Confirmed pairs are joined by large-star and small-star rounds.

Bands and rows follow from the threshold: as many rows as keep the chance that a
pair right at it shares no bucket under one in a million.

Defined results: null and wordless texts have an empty set and stand alone; a
row without doc_id stands alone, its component is null and it is kept; rows that
repeat a doc_id are judged each by its own text; an empty table gives an empty
table.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nearfield.llm.common import folded_words_of, keep, pieces, temporaries
from nearfield.llm.components import components
from nearfield.llm.shingles import shingle_set

#: Hash functions in all, and the chance of missing a pair right at the threshold.
FUNCTIONS, MISS = 200, 1e-6
#: About so many members of a bucket lead in the second turn, and so many times as many in each turn after it.
GROWTH = 2048
#: 64-bit words of a node's parity bitmap.
BITMAP = 16
#: A pair goes if its signatures agree less than the wanted share by this many standard deviations.
DEVIATIONS = 5.5
_BLOCK = 4096


def banding(percent: int, functions: int = FUNCTIONS, miss: float = MISS) -> tuple[int, int]:
    """Bands and rows: the most rows that still find a pair right at the threshold."""
    share = percent / 100
    for rows in range(16, 1, -1):
        bands = functions // rows
        if (1 - share**rows) ** bands <= miss:
            return bands, rows
    return functions, 1


def _functions(n: int) -> tuple[np.ndarray, np.ndarray]:
    drawn = np.random.default_rng(7).integers(0, 2**32, (2, n), dtype=np.uint32)
    return drawn[0] | np.uint32(1), drawn[1]


def signature(shingles: np.ndarray, n: int) -> np.ndarray:
    """The minima of n hash functions x -> a * x + b modulo 2^32, block by block."""
    a, b = _functions(n)
    low = np.full(n, 2**32 - 1, np.uint32)
    short = (shingles >> np.uint64(32)).astype(np.uint32)
    for start in range(0, len(short), _BLOCK):
        block = a[:, None] * short[None, start : start + _BLOCK]
        block += b[:, None]
        np.minimum(low, block.min(axis=1), out=low)
    return low


def _sets(docs: DataFrame, size: int, functions: int) -> DataFrame:
    def describe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            n, nodes, signatures = [], [], []
            for text in batch.column(1).to_pylist():
                found = shingle_set(folded_words_of(text), size)
                n.append(len(found))
                nodes.append(xxhash.xxh3_64_intdigest(found.tobytes()) - 2**63 if len(found) else None)
                signatures.append(signature(found, functions).tobytes() if len(found) else None)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(nodes, pa.int64()), pa.array(signatures, pa.binary())], ["doc_id", "n_shingles", "node", "signature"])

    schema = T.StructType([docs.schema["doc_id"], T.StructField("n_shingles", T.LongType()), T.StructField("node", T.LongType()), T.StructField("signature", T.BinaryType())])
    return docs.select("doc_id", "text").mapInArrow(describe, schema)


def bitmap(shingles: np.ndarray) -> list[int]:
    """One bit for each residue of the shingles: whether an odd number of them has it."""
    odd = np.bincount((shingles & np.uint64(64 * BITMAP - 1)).astype(np.int64), minlength=64 * BITMAP) & 1
    return np.packbits(odd.astype(np.uint8)).view(np.int64).tolist()


def _full_sets(docs: DataFrame, size: int) -> DataFrame:
    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            sets = [shingle_set(folded_words_of(text), size) for text in batch.column(1).to_pylist()]
            found = [xxhash.xxh3_64_intdigest(x.tobytes()) - 2**63 for x in sets]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(found, pa.int64()), pa.array([x.tobytes() for x in sets], pa.binary()), pa.array(list(map(len, sets)), pa.int64()), pa.array(list(map(bitmap, sets)), pa.list_(pa.int64()))],
                ["node", "found", "shingles", "n", "bits"],
            )

    return docs.select("node", "text").mapInArrow(pack, "node long, found long, shingles binary, n long, bits array<long>")


def _lone(full: DataFrame) -> DataFrame:
    """``node, n, bits, lone``: how many of each node's shingles no other of these nodes holds."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            for i in range(batch.num_rows):
                values = np.frombuffer(batch.column(1)[i].as_buffer(), np.int64)
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(np.full(len(values), i, np.int32))), pa.array(values)], ["node", "shingle"])

    listed = full.select("node", "shingles").mapInArrow(rows, T.StructType([full.schema["node"], T.StructField("shingle", T.LongType())]))
    single = listed.groupBy("shingle").agg(F.count(F.lit(1)).alias("held"), F.min("node").alias("node")).where("held = 1")
    return full.select("node", "n", "bits").join(single.groupBy("node").agg(F.count(F.lit(1)).alias("lone")), "node", "left").select("node", "n", "bits", F.coalesce("lone", F.lit(0)).alias("lone"))


def _agreeing(pairs: DataFrame, least: int) -> DataFrame:
    """Pairs whose signatures agree in at least ``least`` places."""

    def filtered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            if batch.num_rows:
                left, right = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint32).reshape(batch.num_rows, -1) for c in ("sa", "sb"))
                yield batch.select(["a", "b"]).filter(pa.array((left == right).sum(axis=1) >= least))

    return pairs.select("a", "b", "sa", "sb").mapInArrow(filtered, pairs.select("a", "b").schema)


def _confirmed(pairs: DataFrame, percent: int) -> DataFrame:
    def filtered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            good = []
            for x, y in zip(batch.column("fa"), batch.column("fb"), strict=True):
                left, right = (np.frombuffer(v.as_buffer(), np.uint64) for v in (x, y))
                both = np.concatenate((left, right))
                both.sort(kind="stable")
                common = int((both[1:] == both[:-1]).sum())
                good.append(100 * common >= percent * (len(both) - common))
            yield batch.select(["a", "b"]).filter(pa.array(good, pa.bool_()))

    return pairs.select("a", "b", "fa", "fb").mapInArrow(filtered, pairs.select("a", "b").schema)


def _spanning(members: DataFrame, of: DataFrame) -> DataFrame:
    """The members of buckets that span components, with their component."""
    placed = keep(members.join(of, "node", "left").withColumn("component", F.coalesce("component", "node")))
    split = keep(placed.groupBy("bucket").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).where("lo < hi").select("bucket"))
    return placed.join(split, "bucket", "left_semi")


def _open_pairs(placed: DataFrame, turn: int, percent: int) -> DataFrame:
    """Pairs across components of one bucket that this turn's leaders make and that the bounds leave open.

    In turn 1 the node with the fewest lone shingles leads.  From turn 2 on the
    members outside its component do: a node's share is its place between 0 and
    1 by its hash, and turn t takes the shares from (G^(t-2) - 1) / size to
    (G^(t-1) - 1) / size with G = GROWTH, so the turns take every one once.
    """
    central = placed.groupBy("bucket").agg(F.min(F.struct((F.col("lone") / F.col("n")).alias("part"), "node", "component")).alias("x"))
    central = central.select("bucket", F.col("x.node").alias("centre"), F.col("x.component").alias("of_centre"))
    led = placed.join(central, "bucket")
    if turn == 1:
        leads, once = F.col("node") == F.col("centre"), F.lit(True)
    else:
        share = (F.pmod(F.xxhash64("node"), F.lit(1 << 30)) + 0.5) / float(1 << 30) * F.col("size")
        leads = (F.col("component") != F.col("of_centre")) & (share >= GROWTH ** (turn - 2) - 1) & (share < GROWTH ** (turn - 1) - 1)
        # A pair that shares several buckets is made in the least of them alone.
        once = F.col("bucket") == F.array_min(F.array_intersect("buckets", "of_buckets"))
    mine = {"node": "leader", "n": "of_n", "lone": "of_lone", "component": "of_leader", "buckets": "of_buckets", "bits": "of_bits"}
    leaders = led.where(leads).select("bucket", *[F.col(a).alias(b) for a, b in mine.items()])
    wanted = percent * (F.col("n") + F.col("of_n"))
    reach = ((100 + percent) * (F.col("n") - F.col("lone")) >= wanted) & ((100 + percent) * (F.col("of_n") - F.col("of_lone")) >= wanted)
    differ = F.bit_count(F.col("bits")[0].bitwiseXOR(F.col("of_bits")[0]))
    for i in range(1, BITMAP):
        differ = differ + F.bit_count(F.col("bits")[i].bitwiseXOR(F.col("of_bits")[i]))
    near = (100 + percent) * differ <= (100 - percent) * (F.col("n") + F.col("of_n"))
    both = placed.join(leaders, "bucket").where((F.col("component") != F.col("of_leader")) & reach & near & once)
    return both.select(F.least("leader", "node").alias("a"), F.greatest("leader", "node").alias("b")).distinct()


def group(docs: DataFrame, size: int = 3, percent: int = 85) -> DataFrame:
    """``doc_id, n_shingles, component_id, kept`` for each row of ``docs``."""
    with temporaries() as spared:
        return _grouped(docs, size, percent, spared)


def _grouped(docs: DataFrame, size: int, percent: int, spared: list[DataFrame]) -> DataFrame:
    bands, rows = banding(percent)
    places, width = bands * rows, 4 * rows
    sets = keep(_sets(docs, size, places))
    named = sets.where(F.col("doc_id").isNotNull() & F.col("node").isNotNull())
    # Any row of a node speaks for it; the one with the least doc_id lends its text.
    nodes = keep(named.groupBy("node").agg(F.min(F.struct("doc_id", "signature")).alias("x")).select("node", F.col("x.doc_id").alias("doc_id"), F.col("x.signature").alias("signature")))

    banded = nodes.select("node", "doc_id", F.explode(F.array(*[F.xxhash64(F.lit(k), F.substring("signature", 1 + k * width, width)) for k in range(bands)])).alias("bucket"))
    shared = keep(banded.groupBy("bucket").agg(F.count(F.lit(1)).alias("size"), F.min("node").alias("leader")).where("size > 1"))
    members = keep(banded.join(shared, "bucket").select("bucket", "size", "leader", "node", "doc_id"))

    taken = members.select("node", "doc_id").distinct()
    texts = docs.select("doc_id", "text").join(taken, "doc_id").select("node", "text")
    full = keep(_full_sets(texts, size).where(F.col("node") == F.col("found")).drop("found").dropDuplicates(["node"]))
    share = percent / 100
    least = int(places * share - DEVIATIONS * (places * share * (1 - share)) ** 0.5)

    def confirmed(pairs: DataFrame) -> DataFrame:
        whole = {side: full.select(F.col("node").alias(side), F.col("shingles").alias(f"f{side}")) for side in "ab"}
        return keep(_confirmed(pairs.join(whole["b"], "b").join(whole["a"], "a"), percent))

    led = members.where("node <> leader").select(F.col("leader").alias("a"), F.col("node").alias("b")).distinct()
    by = {side: nodes.select(F.col("node").alias(side), F.col("signature").alias(f"s{side}")) for side in "ab"}
    edges = confirmed(keep(_agreeing(led.join(by["b"], "b").join(by["a"], "a"), least)))
    of = components(edges.toDF("u", "v"))

    still = _spanning(members.select("bucket", "size", "node"), of).drop("component")
    lone = _lone(full.join(still.select("node").distinct(), "node", "left_semi")).where(F.expr(f"100 * (n - lone) >= {percent} * n"))
    still = keep(still.join(keep(lone), "node"))
    lists = still.groupBy("node").agg(F.collect_set("bucket").alias("buckets"))
    still = keep(still.join(lists, "node"))
    largest = still.agg(F.max("size")).first()[0] or 0
    turn = 1
    while largest and (turn <= 2 or GROWTH ** (turn - 2) - 1 < largest):
        more = confirmed(keep(_open_pairs(_spanning(still, of), turn, percent)))
        if not more.isEmpty():
            edges = edges.unionByName(more)
            of = components(edges.toDF("u", "v"))
        turn += 1

    found = sets.join(of, "node", "left").withColumn("component", F.coalesce("component", "node"))
    least_id = keep(found.where(F.col("doc_id").isNotNull() & F.col("node").isNotNull()).groupBy("component").agg(F.min("doc_id").alias("least_id")))
    spared += [sets, of, least_id]
    met = found.join(least_id, "component", "left")
    id_ = F.when(F.col("node").isNull() | F.col("doc_id").isNull(), F.col("doc_id")).otherwise(F.col("least_id"))
    return met.select("doc_id", "n_shingles", id_.alias("component_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def keep_one(docs: DataFrame, size: int = 5, percent: int = 80) -> DataFrame:
    """``docs`` with the least doc_id of each group; every column stays.

    Of rows that repeat a kept doc_id all stay: they are one document.
    """
    with temporaries() as spared:
        gone = keep(group(docs, size, percent).where(~F.col("kept")).select("doc_id").distinct())
        spared.append(gone)
    return docs.join(gone, "doc_id", "left_anti").select(docs.columns)


#: The same rows in DuckDB SQL: all pairs with a common shingle, then reachability.
NEAR_SQL = r"""
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w
  FROM documents
), sets AS (
  SELECT doc_id, list_distinct(CASE WHEN len(w) = 0 THEN []::VARCHAR[] WHEN len(w) < 3 THEN [array_to_string(w, ' ')]
           ELSE list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2]) END) AS s
  FROM words
), nodes AS (
  SELECT min(doc_id) AS node, list_sort(s) AS s, len(s) AS n FROM sets WHERE len(s) > 0 GROUP BY list_sort(s), len(s)
), posts AS (
  SELECT node, n, unnest(s) AS x FROM nodes
), links AS (
  SELECT a.node AS u, b.node AS v FROM posts a JOIN posts b ON a.x = b.x AND a.node < b.node AND 100 * least(a.n, b.n) >= 85 * greatest(a.n, b.n)
  GROUP BY a.node, b.node, a.n, b.n HAVING 100 * count(*) >= 85 * (a.n + b.n - count(*))
), ways AS (
  SELECT u, v FROM links UNION SELECT v, u FROM links
), reach AS (
  SELECT node AS u, node AS v FROM nodes UNION SELECT reach.u, ways.v FROM reach JOIN ways ON reach.v = ways.u
), least_of AS (
  SELECT u AS node, min(v) AS component FROM reach GROUP BY u
), named AS (
  SELECT sets.doc_id, len(sets.s)::BIGINT AS n_shingles, CASE WHEN len(sets.s) = 0 THEN sets.doc_id ELSE component END AS component_id
  FROM sets LEFT JOIN nodes ON list_sort(sets.s) = nodes.s LEFT JOIN least_of ON nodes.node = least_of.node
)
SELECT doc_id, n_shingles, component_id, doc_id = component_id AS kept FROM named
"""
