"""Language identification with hyperdimensional profiles.

Every letter of any script has a random vector of signs.  A three-letter sequence is the
element-wise product of its letters' vectors, each rotated by its place, so the
same letters in another order give an unrelated vector.  A text is the sum of
its sequences, a language the sum of its texts' unit vectors, and a text belongs
to the language whose prototype has the greatest cosine with it.

The vectors follow from a seed, so every executor makes the same ones.  Texts
never move: a task turns its rows into sequence counts and those into vectors by
one matrix product, and what leaves a task in training is one vector a language.

Defined results: a null text or one without letters is ``und`` with score 0; a
null ``lang`` takes no part in training; with nothing to learn from, every text
is ``und``; equal cosines go to the smaller language name; rows that repeat are
treated each for itself; an empty table gives an empty table; very long texts count
whole; other columns pass through, but for ``lang_pred`` and ``score``, which are
replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nearfield.llm.common import modest_batches, pieces
from nearfield.llm.shingles import mixed

#: Symbols of the plain alphabet: 0 is "no letter", 1 to 26 are a to z.  Any other letter is its own symbol, its code point.
PLAIN = 27
DIMENSIONS = 512
SEED = 20_240_101
UNDETERMINED = "und"

_CODES = PLAIN**3
#: Texts that a task turns into vectors at once, and sequences beyond the plain alphabet.
_BLOCK, _SEQUENCES = 32, 4096


@lru_cache(maxsize=1)
def _symbol_table() -> np.ndarray:
    """Symbol of every code point: case is folded, 0 for what is no letter."""
    table = np.zeros(0x110000, np.uint32)
    for point in range(0x20000):
        letter = chr(point)
        if letter.isalpha():
            low = letter.lower()
            table[point] = ord(low) - 96 if len(low) == 1 and "a" <= low <= "z" else ord(low[0])
    rest = np.arange(0x20000, 0x110000)
    alpha = np.fromiter((chr(x).isalpha() for x in rest), bool, len(rest))
    table[0x20000:][alpha] = rest[alpha]
    return table


def _letters(symbols: np.ndarray, dimensions: int) -> np.ndarray:
    """The vector of signs of each symbol: drawn for the plain ones, from the bits of a hash of the code point for all others."""
    words = -(-dimensions // 64)
    place = symbols.astype(np.uint64)[:, None] * np.uint64(words) + np.arange(words, dtype=np.uint64)[None, :]
    bits = np.unpackbits(mixed(mixed(place + np.uint64(SEED))).view(np.uint8), axis=1)[:, :dimensions]
    out = 2 * bits.astype(np.int8) - 1
    plain = symbols < PLAIN
    out[plain] = _plain_letters(dimensions)[symbols[plain]]
    return out


@lru_cache(maxsize=2)
def _plain_letters(dimensions: int) -> np.ndarray:
    return np.random.default_rng(SEED).choice(np.array([-1, 1], np.int8), (PLAIN, dimensions))


def _bound(first: np.ndarray, second: np.ndarray, third: np.ndarray) -> np.ndarray:
    """Permute by place, then bind by product."""
    return np.roll(first, 2, axis=-1) * np.roll(second, 1, axis=-1) * third


@lru_cache(maxsize=2)
def _sequence_vectors(dimensions: int) -> np.ndarray:
    """One vector for each three-symbol sequence of the plain alphabet."""
    letters = _plain_letters(dimensions)
    return _bound(letters[:, None, None, :], letters[None, :, None, :], letters[None, None, :, :]).reshape(_CODES, dimensions)


def sequences(text: str | None) -> tuple[np.ndarray, np.ndarray] | None:
    """The three-symbol sequences of a text: how often each plain one occurs, and a key for each other; None without letters."""
    if not text:
        return None
    symbols = _symbol_table()[np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)]
    if not symbols.any():
        return None
    # Runs of what is no letter count as one gap, and the text has a gap at both ends.
    padded = np.concatenate(([0], symbols, [0]))
    padded = padded[(padded != 0) | (np.concatenate(([1], padded[:-1])) != 0)].astype(np.int64)
    a, b, c = padded[:-2], padded[1:-1], padded[2:]
    plain = (a < PLAIN) & (b < PLAIN) & (c < PLAIN)
    codes = (a[plain] * PLAIN + b[plain]) * PLAIN + c[plain]
    other = ~plain
    return np.bincount(codes, minlength=_CODES).astype(np.float32), (a[other] << 42) | (b[other] << 21) | c[other]


def _other_vectors(keys: list[np.ndarray], dimensions: int) -> np.ndarray:
    """The summed vectors of each text's sequences beyond the plain alphabet, a few thousand distinct ones at a time."""
    out = np.zeros((len(keys), dimensions), np.float32)
    row = np.repeat(np.arange(len(keys)), [len(x) for x in keys])
    distinct, place = np.unique(np.concatenate(keys), return_inverse=True)
    for at in range(0, len(distinct), _SEQUENCES):
        some = distinct[at : at + _SEQUENCES]
        symbols, own = np.unique(np.stack((some >> 42, (some >> 21) & 0x1FFFFF, some & 0x1FFFFF)), return_inverse=True)
        vectors = _letters(symbols, dimensions)[own.reshape(3, -1)]
        held = (place >= at) & (place < at + len(some))
        counts = np.bincount(row[held] * len(some) + place[held] - at, minlength=len(keys) * len(some)).reshape(len(keys), len(some))
        out += counts.astype(np.float32) @ _bound(*vectors).astype(np.float32)
    return out


def text_vectors(texts: list[str | None], dimensions: int) -> tuple[np.ndarray, np.ndarray]:
    """Unit vectors of texts, and which of them have letters."""
    out, known = np.zeros((len(texts), dimensions), np.float32), np.zeros(len(texts), bool)
    vectors = _sequence_vectors(dimensions)
    for start in range(0, len(texts), _BLOCK):
        found = [(start + i, x) for i, t in enumerate(texts[start : start + _BLOCK]) if (x := sequences(t)) is not None]
        if not found:
            continue
        rows = [i for i, _ in found]
        counts = np.stack([plain for _, (plain, _) in found])
        used = np.flatnonzero(counts.any(axis=0))
        block = counts[:, used] @ vectors[used].astype(np.float32)
        block += _other_vectors([other for _, (_, other) in found], dimensions)
        norms = np.linalg.norm(block, axis=1)
        out[rows] = block / np.where(norms > 0, norms, 1)[:, None]
        known[rows] = True
    return out, known


def learn(docs: DataFrame, dimensions: int = DIMENSIONS) -> dict[str, np.ndarray]:
    """Prototypes from ``text`` and non-null ``lang``: one row of sums a task and language, added up by Spark.

    The driver gets one vector a language, whatever the size of ``docs``.
    """
    modest_batches(docs.sparkSession)

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for batch in pieces(batches):
            langs = np.array(batch.column(1).to_pylist(), object)
            vectors, known = text_vectors(batch.column(0).to_pylist(), dimensions)
            for lang in set(langs[known]):
                added = vectors[known & (langs == lang)].sum(axis=0, dtype=np.float64)
                total[lang] = total.get(lang, 0) + added
        if total:
            names = [x for x in sorted(total) for _ in range(dimensions)]
            yield pa.RecordBatch.from_arrays(
                [pa.array(names), pa.array(np.tile(np.arange(dimensions, dtype=np.int32), len(total))), pa.array(np.concatenate([total[x] for x in sorted(total)]))],
                ["lang", "place", "value"],
            )

    rows = (
        docs.where(F.col("text").isNotNull() & F.col("lang").isNotNull())
        .select("text", "lang")
        .mapInArrow(sums, "lang string, place int, value double")
        .groupBy("lang", "place")
        .agg(F.sum("value").alias("value"))
        .groupBy("lang")
        .agg(F.array_sort(F.collect_list(F.struct("place", "value"))).alias("vector"))
        .collect()
    )
    # Rounding hides the order in which tasks ended.
    return {r.lang: np.round([x.value for x in r.vector], 6) for r in sorted(rows, key=lambda r: r.lang)}


def predict(docs: DataFrame, prototypes: dict[str, np.ndarray], dimensions: int = DIMENSIONS) -> DataFrame:
    """``docs`` with ``lang_pred`` and ``score``: the best cosine, cut to 0 to 1."""
    names = list(prototypes)
    matrix = np.stack([v / (np.linalg.norm(v) or 1) for v in prototypes.values()]).astype(np.float32) if names else None

    def label(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            at = batch.schema.get_field_index("text")
            vectors, known = text_vectors(batch.column(at).to_pylist(), dimensions)
            preds, scores = [UNDETERMINED] * len(known), np.zeros(len(known))
            if matrix is not None and known.any():
                cosines = np.round(vectors @ matrix.T, 6)
                best = cosines.argmax(axis=1)
                scores = np.where(known, np.clip(cosines[np.arange(len(best)), best], 0, 1), 0).astype(np.float64)
                preds = [names[b] if k else UNDETERMINED for b, k in zip(best, known, strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(preds, pa.string()), pa.array(scores)], [*batch.schema.names, "lang_pred", "score"])

    slim = docs.drop("lang_pred", "score")
    schema = T.StructType([*slim.schema.fields, T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])
    return slim.mapInArrow(label, schema)


def held_out(doc_id: str = "doc_id"):
    """Whether crc32 of the id as text leaves 2 when divided by 4."""
    return F.coalesce(F.crc32(F.encode(F.col(doc_id).cast("string"), "UTF-8")) % 4 == 2, F.lit(False))


def identify(docs: DataFrame, dimensions: int = DIMENSIONS) -> DataFrame:
    """``docs`` with ``held_out``, ``lang_pred`` and ``score``, learned from the rows that are not held out."""
    prototypes = learn(docs.where(~held_out()), dimensions)
    return predict(docs.withColumn("held_out", held_out()), prototypes, dimensions)
