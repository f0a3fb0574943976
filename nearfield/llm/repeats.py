"""Substring deduplication by level-wise doubling of repeated word windows.

Windows of one length that occur in two documents are the only candidates at up
to twice that length: a longer window is looked at only where the two shorter
ones that make it up are repeated.  The lengths halve from the wanted one down
to a seed, so 13 words come from 7, and 50 from 7, 13 and 25.  With ``extend``
the levels go on beyond the wanted length, 26, 52, ..., until no candidate
survives, and tell each document's longest repeated length.

The seed level would otherwise list a window for every word.  It is thinned by
content: of the seeds inside a window of the next length only the one with the
least hash counts.  Equal windows pick equal seeds, so none is lost, and a
quarter of the seeds remains.

Every level is two steps.  Distinct (hash, document) rows are summed to the
least and the greatest document of each hash, so a passage in a third of all
documents is combined on the map side; then the rows whose hash is repeated go
back to their documents by a join of two written tables, which Spark splits if
one hash is hot.  64-bit hashes stand for windows that are only candidates; at the
last level two independent ones do, so that a wrong match has the chance of the
number of windows over 2^96.

Defined results: words are judged on the input; a null or empty text has none; a
row without doc_id keeps its words and takes none from others; rows that repeat
a doc_id are one document, whose rows share what is repeated; an empty table
gives an empty table; very long texts count whole; other columns pass, but for
``n_words`` and ``n_removed``, which are replaced.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nearfield.llm.common import discard, keep, pieces, words_of
from nearfield.llm.shingles import mixed, window_hashes, word_hashes

#: The seed has at most so many words, and more than half of them.
SEED_WORDS = 8


def lengths(window: int) -> list[int]:
    """The levels up to ``window``: each is at most twice the one before."""
    out = [window]
    while out[0] > SEED_WORDS:
        out.insert(0, (out[0] + 1) // 2)
    return out


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    """The least of each ``width`` neighbours, by doubling."""
    if len(x) < width:
        return x[:0]
    done, low = 1, x
    while done < width:
        step = min(done, width - done)
        low = np.minimum(low[: len(low) - step], low[step:])
        done += step
    return low


def _among(x: np.ndarray, ordered: np.ndarray) -> np.ndarray:
    if not len(ordered):
        return np.zeros(len(x), bool)
    return ordered[np.minimum(np.searchsorted(ordered, x), len(ordered) - 1)] == x


#: A second hash of a window starts from its words' hashes turned by this.
_TURN = np.uint64(0xA0761D6478BD642F)


def _both_hashes(hashed: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Two independent hashes of each window, of 64 and 32 bits."""
    return window_hashes(hashed, size), (window_hashes(mixed(hashed ^ _TURN), size) >> np.uint64(32)).astype(np.uint32)


def _hashed(values) -> np.ndarray:
    """Sorted hashes from an Arrow list of 64-bit integers."""
    return np.sort(np.asarray(values, np.int64).view(np.uint64)) if values is not None else np.empty(0, np.uint64)


def _seeds(docs: DataFrame, low: int, high: int) -> DataFrame:
    """Distinct thinned seeds of each row: all of a level's first candidates."""

    def rows(text: str | None, _) -> np.ndarray:
        return np.unique(sliding_min(window_hashes(word_hashes(words_of(text)), low), high - low + 1))

    return _exploded(docs.select("doc_id", "text"), rows)


def _unique_both(hashed: np.ndarray, size: int, open_: np.ndarray | slice) -> tuple[np.ndarray, np.ndarray]:
    first, second = (x[open_] for x in _both_hashes(hashed, size))
    order = np.lexsort((second, first))
    first, second = first[order], second[order]
    new = np.r_[True, (first[1:] != first[:-1]) | (second[1:] != second[:-1])][: len(first)]
    return first[new], second[new]


def _longer(docs: DataFrame, low: int, high: int, thinned: bool, last: bool) -> DataFrame:
    """Distinct windows of ``high`` words whose parts of ``low`` words are in ``alive``; with both hashes at the last level."""

    def rows(text: str | None, alive) -> np.ndarray | tuple[np.ndarray, np.ndarray]:
        hashed = word_hashes(words_of(text))
        if len(hashed) < high:
            return (np.empty(0, np.uint64), np.empty(0, np.uint32)) if last else np.empty(0, np.uint64)
        short, alive = window_hashes(hashed, low), _hashed(alive)
        if thinned:
            open_ = _among(sliding_min(short, high - low + 1), alive)
        else:
            there = _among(short, alive)
            open_ = there[: len(hashed) - high + 1] & there[high - low :]
        return _unique_both(hashed, high, open_) if last else np.unique(window_hashes(hashed, high)[open_])

    return _exploded(docs.select("doc_id", "text", "alive"), rows, last)


def _exploded(docs: DataFrame, rows, both: bool = False) -> DataFrame:
    names = ["doc_id", "hash", "check"] if both else ["doc_id", "hash"]

    def listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            alive = batch.column(2) if batch.num_columns > 2 else None
            found = [rows(text, alive[i].values.to_numpy(zero_copy_only=False) if alive is not None and alive[i].is_valid else None) for i, text in enumerate(batch.column(1).to_pylist())]
            columns = [list(x) for x in zip(*found, strict=True)] if both and found else [found]
            index = np.repeat(np.arange(len(found), dtype=np.int32), [len(x) for x in columns[0]])
            hashes = [np.concatenate(x) if x else np.empty(0, t) for x, t in zip(columns, (np.uint64, np.uint32), strict=False)]
            for at in range(0, len(index), 1 << 20):
                part = slice(at, at + (1 << 20))
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(index[part])), *[pa.array(h[part].view(t)) for h, t in zip(hashes, (np.int64, np.int32), strict=False)]], names)

    return docs.mapInArrow(listed, T.StructType([docs.schema["doc_id"], *[T.StructField(n, t) for n, t in zip(names[1:], (T.LongType(), T.IntegerType()), strict=False)]]))


def _survivors(rows: DataFrame, later_only: bool) -> DataFrame:
    """Per document the hashes that another document has too; with ``later_only``, one with a smaller id."""
    key = [c for c in ("hash", "check") if c in rows.columns]
    repeated = keep(rows.groupBy(*key).agg(F.min("doc_id").alias("first_id"), F.max("doc_id").alias("last_id")).where("first_id < last_id").select(*key, "first_id"))
    met = rows.join(repeated, key)
    if later_only:
        met = met.where(F.col("doc_id") > F.col("first_id"))
    # Both hashes found the repeat; among a document's own windows one of them tells which it is.
    out = keep(met.groupBy("doc_id").agg(F.collect_set("hash").alias("alive")))
    discard(repeated)
    return out


def _joined(docs: DataFrame, alive: DataFrame, how: str) -> DataFrame:
    return docs.join(alive.withColumnRenamed("doc_id", "_hit_id"), F.col("doc_id") == F.col("_hit_id"), how).drop("_hit_id")


def repeated_windows(docs: DataFrame, window: int = 13, extend: bool = False) -> tuple[DataFrame, DataFrame | None]:
    """``doc_id, alive``: hashes of the windows that a document with a smaller id has too.

    With ``extend`` also ``doc_id, longest``: the longest level at which a
    window of the document is repeated elsewhere.
    """
    slim = docs.where(F.col("doc_id").isNotNull() & F.col("text").isNotNull()).select("doc_id", "text")
    steps = lengths(window)
    if len(steps) == 1:
        rows = keep(_exploded(slim, lambda text, _: _unique_both(word_hashes(words_of(text)), window, slice(None)), True))
    else:
        rows = keep(_seeds(slim, steps[0], steps[1]))
    for k, (low, high) in enumerate(zip(steps, steps[1:], strict=False)):
        alive = _survivors(rows, False)
        discard(rows)
        rows = keep(_longer(_joined(slim, alive, "inner"), low, high, k == 0, high == window))
        discard(alive)
    gone, longest, length = _survivors(rows, True), None, window
    while extend:
        alive = _survivors(rows, False)
        discard(rows)
        if alive.isEmpty():
            discard(alive)
            break
        reached = alive.select("doc_id", F.lit(length).alias("longest"))
        longest = reached if longest is None else longest.unionByName(reached)
        rows = keep(_longer(_joined(slim, alive, "inner"), length, 2 * length, False, False))
        length *= 2
    else:
        discard(rows)
    return gone, None if longest is None else longest.groupBy("doc_id").agg(F.max("longest").alias("longest"))


def cut_repeats(docs: DataFrame, window: int = 13) -> DataFrame:
    """``docs`` with repeated words cut from ``text``, plus ``n_words`` and ``n_removed``.

    A word goes if a window of ``window`` words that covers it also starts in a
    document with a smaller doc_id; the words that stay are joined by one space.
    """
    gone, _ = repeated_windows(docs, window)
    base = docs.drop("n_words", "n_removed")
    met = _joined(base, gone.withColumnRenamed("alive", "_gone"), "left")
    schema = T.StructType([*base.schema.fields, T.StructField("n_words", T.LongType()), T.StructField("n_removed", T.LongType())])
    at = base.columns.index("text")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            gone_at = batch.schema.get_field_index("_gone")
            texts, n_words, n_removed = [], [], []
            for text, hashes in zip(batch.column(at).to_pylist(), batch.column(gone_at), strict=True):
                words = words_of(text)
                n_words.append(len(words))
                if hashes.is_valid and len(words) >= window:
                    starts = np.flatnonzero(_among(window_hashes(word_hashes(words), window), _hashed(hashes.values.to_numpy(zero_copy_only=False))))
                    edge = np.zeros(len(words) + 1, np.int64)
                    edge[starts] += 1
                    edge[starts + window] -= 1
                    words = [w for w, hit in zip(words, np.cumsum(edge)[:-1], strict=True) if not hit]
                n_removed.append(n_words[-1] - len(words))
                texts.append(b" ".join(words).decode("utf-8", "surrogatepass"))
            columns = [c for i, c in enumerate(batch.columns) if i != gone_at]
            columns[at] = pa.array(texts, pa.string())
            yield pa.RecordBatch.from_arrays([*columns, pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64())], schema.names)

    return met.mapInArrow(cut, schema)


def digest(cut: DataFrame) -> DataFrame:
    return cut.select("doc_id", "n_words", "n_removed", F.sha2(F.encode("text", "UTF-8"), 256).alias("kept_sha256"))


def brute_force(texts: dict[int, str | None], window: int = 13) -> dict[int, tuple[int, int, str]]:
    """The same digest by a dictionary of all windows; for tests."""
    words = {d: words_of(t) for d, t in texts.items()}
    first: dict[tuple, int] = {}
    for d in sorted(words):
        for i in range(len(words[d]) - window + 1):
            first.setdefault(tuple(words[d][i : i + window]), d)
    out = {}
    for d, w in words.items():
        hit = [False] * len(w)
        for i in range(len(w) - window + 1):
            if first[tuple(w[i : i + window])] < d:
                hit[i : i + window] = [True] * window
        kept = [x for x, h in zip(w, hit, strict=True) if not h]
        out[d] = (len(w), len(w) - len(kept), hashlib.sha256(b" ".join(kept)).hexdigest())
    return out


#: The same rows in DuckDB SQL.
REPEATS_SQL = r"""
WITH words AS (
  SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents
), windows AS (
  SELECT doc_id, i, array_to_string(list_slice(w, i, i + 12), ' ') AS x
  FROM words, unnest(range(1, len(w) - 11)) AS u(i)
), firsts AS (
  SELECT x, min(doc_id) AS d FROM windows GROUP BY x
), hit AS (
  SELECT DISTINCT doc_id, i + j AS i FROM windows JOIN firsts USING (x), unnest(range(0, 13)) AS v(j) WHERE d < doc_id
), placed AS (
  SELECT doc_id, i, w[i] AS word FROM words, unnest(range(1, len(w) + 1)) AS u(i)
), kept AS (
  SELECT placed.doc_id, string_agg(word, ' ' ORDER BY placed.i) AS t, count(*) AS n FROM placed ANTI JOIN hit ON placed.doc_id = hit.doc_id AND placed.i = hit.i GROUP BY placed.doc_id
)
SELECT words.doc_id, len(w)::BIGINT AS n_words, (len(w) - coalesce(n, 0))::BIGINT AS n_removed, sha256(coalesce(t, '')) AS kept_sha256
FROM words LEFT JOIN kept ON words.doc_id = kept.doc_id
"""
