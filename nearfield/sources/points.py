"""Point sets: an id and a value for each row, checked on entry."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nearfield.functions.metrics import Metric, edit, jaccard, l2


@dataclass(frozen=True)
class PointSet:
    """``df`` has ``point_id`` and ``value``; ``metric`` measures two values."""

    df: DataFrame
    metric: Metric

    @property
    def is_vector(self) -> bool:
        return self.metric.cells is not None

    @property
    def id_type(self) -> T.DataType:
        return self.df.schema["point_id"].dataType

    def where(self, condition: Column) -> PointSet:
        return PointSet(self.df.where(condition), self.metric)

    @staticmethod
    def from_table(df: DataFrame, point_id: Column, columns: list[Column], metric: Metric | None = None) -> PointSet:
        """Numeric columns (decimals and booleans too) as one vector of doubles."""
        vec = F.array(*[c.cast("double") for c in columns])
        return PointSet(df.select(point_id.alias("point_id"), vec.alias("value")), metric or l2(len(columns)))

    @staticmethod
    def from_array(df: DataFrame, point_id: str, column: str, width: int, metric: Metric | None = None) -> PointSet:
        return PointSet(df.select(F.col(point_id).alias("point_id"), F.col(column).cast("array<double>").alias("value")), metric or l2(width))

    @staticmethod
    def from_text(df: DataFrame, point_id: str, column: str) -> PointSet:
        return PointSet(df.select(F.col(point_id).alias("point_id"), F.col(column).alias("value")), edit())

    @staticmethod
    def from_tokens(df: DataFrame, point_id: str, column: str) -> PointSet:
        tokens = F.array_distinct(F.filter(F.split(F.lower(column), r"\s+"), lambda x: x != ""))
        return PointSet(df.select(F.col(point_id).alias("point_id"), tokens.alias("value")), jaccard())

    def invalid(self) -> DataFrame:
        """Rows that no search may see: null ids or values, wrong widths, what is not finite."""
        bad = F.col("point_id").isNull() | F.col("value").isNull()
        if self.is_vector:
            finite = F.forall("value", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
            bad = bad | (F.size("value") != self.metric.width) | ~finite
        return self.df.where(bad)

    def validate(self) -> PointSet:
        """Raise if a row is invalid (one pass), else the set itself."""
        found = self.invalid().limit(1).collect()
        if found:
            raise ValueError(f"invalid point: {found[0]}")
        return self


def spread(points: PointSet, parallel: int | None = None) -> PointSet:
    """A small file scans as one task; heavy pairings need as many tasks as there are cores."""
    spark: SparkSession = points.df.sparkSession
    return PointSet(points.df.repartition(parallel or 4 * spark.sparkContext.defaultParallelism), points.metric)
