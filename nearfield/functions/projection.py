"""Random projection, its distortion, and text trigram vectors."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nearfield.functions.metrics import l2
from nearfield.operators.bruteforce import matrix
from nearfield.sources.points import PointSet


def coefficients(width: int, k: int, seed: int = 7, kind: str = "gauss") -> np.ndarray:
    """k rows of ``width`` coefficients that keep lengths on average; rounded to six places."""
    rng = np.random.default_rng(seed * 100 + k)
    drawn = rng.normal(0, 1, (k, width)) if kind == "gauss" else rng.choice([-1.0, 1.0], (k, width))
    return np.round(drawn / np.sqrt(k), 6)


def project(points: PointSet, k: int, seed: int = 7, kind: str = "gauss") -> PointSet:
    """The set in k dimensions: one matrix product for each batch, no shuffle."""
    mix = coefficients(points.metric.width, k, seed, kind)
    schema = T.StructType([points.df.schema["point_id"], T.StructField("value", T.ArrayType(T.DoubleType()))])

    def apply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                values = matrix(batch.column(1))
                # Axis by axis, in the order of the SQL form's sum.
                out = values[:, :1] * mix[:, 0]
                for j in range(1, values.shape[1]):
                    out = out + values[:, j : j + 1] * mix[:, j]
                offsets = pa.array(np.arange(0, out.size + 1, k, dtype=np.int32))
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(offsets, pa.array(out.ravel()))], ["point_id", "value"])

    return PointSet(points.df.select("point_id", "value").mapInArrow(apply, schema), l2(k))


def project_sql(source: str, width: int, k: int, seed: int = 7, kind: str = "gauss") -> str:
    mix = coefficients(width, k, seed, kind)
    parts = [" + ".join(f"v[{j + 1}]*({float(w)!r}::DOUBLE)" for j, w in enumerate(row)) for row in mix]
    return f"SELECT id, [{', '.join(parts)}]::DOUBLE[] AS v FROM ({source})"


def distortion(points: PointSet, k: int, every: int, seed: int = 7, kind: str = "gauss") -> DataFrame:
    """One row: least, mean and greatest ratio of projected to true distance over pairs of every n-th id."""
    some = points.where(F.col("point_id") % every == 0)
    small = project(some, k, seed, kind)
    both = some.df.join(small.df.select("point_id", F.col("value").alias("p")), "point_id")
    a, b = both.select(F.col("point_id").alias("ia"), F.col("value").alias("va"), F.col("p").alias("pa")), both.select(F.col("point_id").alias("ib"), F.col("value").alias("vb"), F.col("p").alias("pb"))
    full, low = points.metric.column(F.col("va"), F.col("vb")), l2(k).column(F.col("pa"), F.col("pb"))
    ratio = a.join(F.broadcast(b), F.col("ia") < F.col("ib")).select((low / full).alias("ratio"))
    return ratio.agg(F.count(F.lit(1)).alias("pairs"), F.round(F.min("ratio"), 6).alias("least"), F.round(F.avg("ratio"), 6).alias("mean"), F.round(F.max("ratio"), 6).alias("greatest"))


def _trigrams(text: str | None, places: int) -> np.ndarray:
    """Counts of the places of all character trigrams of the whole lower-case text."""
    points = np.frombuffer((text or "").lower().encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
    return np.bincount((points[:-2] * 961 + points[1:-1] * 31 + points[2:]) % places, minlength=places) if len(points) >= 3 else np.zeros(places, np.int64)


def trigram_counts(texts: DataFrame, places: int) -> DataFrame:
    """``point_id, place, n`` of whole texts; places that do not occur have no row."""

    def grams(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counts = np.array([_trigrams(t, places) for t in batch.column(1).to_pylist()]).reshape(batch.num_rows, places)
            row, place = np.nonzero(counts)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(row)), pa.array(place.astype(np.int32)), pa.array(counts[row, place])], ["point_id", "place", "n"])

    schema = T.StructType([texts.schema["point_id"], T.StructField("place", T.IntegerType()), T.StructField("n", T.LongType())])
    return texts.select("point_id", "text").mapInArrow(grams, schema)


def trigram_vectors(texts: DataFrame, places: int) -> DataFrame:
    """``point_id, value``: unit vectors of character-trigram counts of whole texts; texts under three characters are zero."""
    schema = T.StructType([texts.schema["point_id"], T.StructField("value", T.ArrayType(T.DoubleType()))])

    def grams(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = np.array([_trigrams(t, places) for t in batch.column(1).to_pylist()], float).reshape(batch.num_rows, places)
            norms = np.linalg.norm(out, axis=1, keepdims=True)
            out /= np.where(norms > 0, norms, 1)
            offsets = pa.array(np.arange(0, out.size + 1, places, dtype=np.int32))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(offsets, pa.array(out.ravel()))], ["point_id", "value"])

    return texts.select("point_id", "text").mapInArrow(grams, schema)
