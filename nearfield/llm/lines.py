"""Line deduplication: lines that many documents share go from all of them.

Lines are exploded and normalised, a 128-bit hash stands for each, distinct
documents are counted per hash, hashes at or over the threshold are dropped, and
every text is put together again in line order.

The texts are read for hashes once, and only hashes and ids move in the count;
the texts move once, to meet the list of their own lines that go.  The count is
of (hash, document) pairs first and of hashes after, so a line that sits in a
third of all documents is summed on the map side and never gathered in one task.
Both tables of hashes are written, so the join of the two can be broadcast where
the common lines are few and split by Spark where one of them is hot.

Defined results: a null or empty text is one empty line; rows that repeat a
doc_id count as one document and each keeps its own row; rows whose doc_id is
null count together as one document; an empty table gives an empty table; other
columns pass through unread.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nearfield.llm.common import FOLD_BYTES, SPACE, keep, pieces


def _line_hash(line: str) -> bytes:
    return hashlib.md5(line.strip(SPACE).encode("utf-8", "surrogatepass").translate(FOLD_BYTES)).digest()


def _line_hashes(docs: DataFrame, min_chars: int) -> DataFrame:
    """The hashes of each row's lines, every one once."""

    def hashes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            row, out = [], []
            for i, text in enumerate(batch.column(1).to_pylist()):
                keys = {k for x in (text or "").split("\n") if len(k := x.strip(SPACE)) >= min_chars}
                out += {hashlib.md5(k.encode("utf-8", "surrogatepass").translate(FOLD_BYTES)).digest() for k in keys}
                row += [i] * (len(out) - len(row))
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(row, pa.int32())), pa.array(out, pa.binary())], ["doc_id", "line_hash"])

    return docs.mapInArrow(hashes, T.StructType([docs.schema["doc_id"], T.StructField("line_hash", T.BinaryType())]))


@F.pandas_udf(T.StructType([T.StructField("text", T.StringType()), T.StructField("n_dropped", T.LongType())]))
def _without(text: pd.Series, gone: pd.Series) -> pd.DataFrame:
    """Texts without the lines whose hash is in ``gone``; null where there are none to drop."""
    kept, dropped = [], []
    for whole, hashes in zip(text, gone, strict=True):
        if whole is None or hashes is None:
            kept.append(None)
            dropped.append(0)
            continue
        bad = set(map(bytes, hashes))
        lines = whole.split("\n")
        stay = [x for x in lines if _line_hash(x) not in bad]
        kept.append("\n".join(stay))
        dropped.append(len(lines) - len(stay))
    return pd.DataFrame({"text": kept, "n_dropped": dropped})


def drop_common_lines(docs: DataFrame, min_docs: int = 10, min_chars: int = 1) -> DataFrame:
    """``docs`` with common lines cut from ``text``, plus ``n_lines`` and ``n_dropped``.

    A line's key is the line without white space at its ends, A-Z folded; keys of
    at least ``min_chars`` code points found in at least ``min_docs`` documents
    lose all their lines.
    """
    pairs = keep(_line_hashes(docs.select("doc_id", "text"), max(1, min_chars)))
    counted = pairs.distinct().groupBy("line_hash").agg(F.count(F.lit(1)).alias("n_docs"))
    common = keep(counted.where(F.col("n_docs") >= min_docs).select("line_hash"))
    gone = pairs.join(common, "line_hash", "left_semi").groupBy(F.col("doc_id").alias("_hit_id")).agg(F.collect_set("line_hash").alias("gone"))
    met = docs.join(gone, F.col("doc_id").eqNullSafe(F.col("_hit_id")), "left").withColumn(
        "_cut", _without(F.when(F.col("gone").isNotNull(), F.col("text")), F.col("gone"))
    )
    text = F.coalesce(F.when(F.col("gone").isNotNull(), F.col("_cut.text")), F.col("text"), F.lit(""))
    taken = [F.col(c) for c in docs.columns if c not in ("text", "n_lines", "n_dropped")]
    at = docs.columns.index("text")
    return met.select(
        *taken[:at],
        text.alias("text"),
        *taken[at:],
        F.size(F.split(F.coalesce("text", F.lit("")), "\n", -1)).cast("long").alias("n_lines"),
        F.coalesce("_cut.n_dropped", F.lit(0)).cast("long").alias("n_dropped"),
    )


def digest(cut: DataFrame) -> DataFrame:
    return cut.select("doc_id", "n_lines", "n_dropped", F.sha2(F.encode("text", "UTF-8"), 256).alias("kept_sha256"))


#: The same rows in DuckDB SQL.
LINES_SQL = r"""
WITH lines AS (
  SELECT doc_id, i AS pos, list_extract(parts, i) AS line
  FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS parts FROM documents), unnest(range(1, len(parts) + 1)) AS u(i)
), keyed AS (
  SELECT doc_id, pos, line,
         translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k
  FROM lines
), common AS (
  SELECT k FROM keyed WHERE length(k) >= 1 GROUP BY k HAVING count(DISTINCT doc_id) >= 10
), marked AS (
  SELECT keyed.*, common.k IS NOT NULL AS gone FROM keyed LEFT JOIN common USING (k)
)
SELECT doc_id, count(*)::BIGINT AS n_lines, count(*) FILTER (WHERE gone)::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""
