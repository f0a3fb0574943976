"""Best-fit packing under conflicts.

Documents become pieces of at most ``capacity`` words and go, longest first, to
the open bin with the least room that still takes them.  A bin carries two
bitmaps: the duplicate clusters in it, and the sources that have reached their
quota.  Open bins are ordered by room; the search starts at the tightest bin and
goes on to the next until the bitmaps allow the piece, so the bin it finds is
the tightest compatible one.

Documents are dealt by hash to shards of a mean size, packed each in one task: a
hot source or a group of copies is spread over all shards, and no shard grows
with the input.

Defined results: a null or wordless text has one row without a bin; each row is
packed for itself, also where doc_ids repeat or are null, and ids of any size stay
as they are; null sources count as one source; pieces of equal length go by
cluster, source and id, nulls last; copies of a text (the pieces of a long text
too) never share a bin;
an empty table gives an empty table; other columns are not read.
"""

from __future__ import annotations

from bisect import bisect_left, insort
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from nearfield.llm.common import folded_words_of, keep, pieces

CAPACITY = 2048
PER_SOURCE = 2
#: Mean number of documents packed in one task.
SHARD = 4096


def best_fit(pieces: list[tuple[int, object, object]], capacity: int, per_source: int) -> list[int]:
    """The bin of each (words, source, cluster), given longest first."""
    repeated = {c for c, n in Counter(c for _, _, c in pieces).items() if n > 1}
    cluster_bit: dict[object, int] = {}
    source_bit: dict[object, int] = {}
    clusters: list[int] = []
    full: list[int] = []
    held: list[Counter] = []
    open_: list[tuple[int, int]] = []
    out = []
    for words, source, cluster in pieces:
        # A cluster of one has no conflict and needs no bit.
        c = 1 << cluster_bit.setdefault(cluster, len(cluster_bit)) if cluster in repeated else 0
        s = 1 << source_bit.setdefault(source, len(source_bit))
        at = bisect_left(open_, (words, -1))
        while at < len(open_) and (clusters[open_[at][1]] & c or full[open_[at][1]] & s):
            at += 1
        if at < len(open_):
            room, chosen = open_.pop(at)
        else:
            room, chosen = capacity, len(clusters)
            clusters.append(0)
            full.append(0)
            held.append(Counter())
        clusters[chosen] |= c
        held[chosen][source] += 1
        if held[chosen][source] >= per_source:
            full[chosen] |= s
        if room > words:
            insort(open_, (room - words, chosen))
        out.append(chosen)
    return out


def _measured(docs: DataFrame) -> DataFrame:
    """Words and cluster (a 64-bit hash of the folded words) of each text; the texts stay where they are."""

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            words = [folded_words_of(t) for t in batch.column(2).to_pylist()]
            n, cluster = [len(w) for w in words], [xxhash.xxh3_64_intdigest(b" ".join(w)) - 2**63 for w in words]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(n, pa.int64()), pa.array(cluster, pa.int64())], ["doc_id", "source", "n_words", "cluster"])

    schema = T.StructType([docs.schema["doc_id"], docs.schema["source"], T.StructField("n_words", T.LongType()), T.StructField("cluster", T.LongType())])
    return docs.select("doc_id", "source", "text").mapInArrow(measure, schema)


def pack(docs: DataFrame, capacity: int = CAPACITY, per_source: int = PER_SOURCE, shard: int = SHARD) -> DataFrame:
    """One row for each piece: where it lies in its text, its bin and its place there."""
    measured = keep(_measured(docs))
    shards = max(1, -(-measured.where("n_words > 0").count() // shard))
    id_type = docs.schema["doc_id"].dataType

    def order(row: tuple) -> tuple:
        """Least words first; nulls after all else."""
        doc_id, source, n_words, cluster = row
        return n_words, cluster, source is None, source or "", doc_id is None, 0 if doc_id is None else doc_id

    def one(found: pa.Table) -> pa.Table:
        columns = [found.column(c).to_pylist() for c in ("doc_id", "source", "n_words", "cluster")]
        rows = [(min(capacity, n - start), source, cluster, doc_id, start // capacity, start) for doc_id, source, n, cluster in sorted(zip(*columns, strict=True), key=order) for start in range(0, n, capacity)]
        rows.sort(key=lambda x: -x[0])
        bins = best_fit([x[:3] for x in rows], capacity, per_source)
        place, used, out = Counter(), Counter(), []
        base = found.column("shard")[0].as_py() << 32
        for (words, source, cluster, doc_id, piece, start), b in zip(rows, bins, strict=True):
            out.append((doc_id, piece, start, words, source, cluster, base + b, place[b], used[b]))
            place[b] += 1
            used[b] += words
        return pa.Table.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], schema.names)

    schema = T.StructType(
        [T.StructField("doc_id", id_type), T.StructField("piece", T.IntegerType()), T.StructField("first_word", T.LongType()), T.StructField("n_words", T.LongType()), T.StructField("source", T.StringType())]
        + [T.StructField("cluster", T.LongType()), T.StructField("bin_id", T.LongType()), T.StructField("place", T.IntegerType()), T.StructField("at", T.LongType())]
    )
    kinds = [f.type for f in to_arrow_schema(schema)]
    dealt = measured.where("n_words > 0").withColumn("shard", F.pmod(F.xxhash64("doc_id", "cluster", "source"), F.lit(shards)))
    packed = dealt.withColumn("source", F.col("source").cast("string")).groupBy("shard").applyInArrow(one, schema)
    wordless = measured.where("n_words = 0").select(
        "doc_id", F.lit(0).alias("piece"), F.lit(0).cast("long").alias("first_word"), "n_words", F.col("source").cast("string").alias("source"), "cluster", F.lit(None).cast("long").alias("bin_id"), F.lit(None).cast("int").alias("place"), F.lit(None).cast("long").alias("at")
    )
    return packed.unionByName(wordless)
