"""Which vectors take part in a search, and how they travel."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def usable(df: DataFrame, nonzero: bool = False) -> DataFrame:
    """``vec_id, vec``: rows with an id and a vector of finite doubles of the usual width.

    The width that most vectors have is the usual one (the smaller of two as
    common); vectors of another width take no part.
    """
    vec = F.col("embedding").cast("array<double>")
    whole = (F.size("vec") > 0) & F.forall("vec", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    if nonzero:
        whole = whole & F.exists("vec", lambda x: x != 0)
    given = df.select("vec_id", vec.alias("vec")).where(F.col("vec_id").isNotNull() & F.col("vec").isNotNull()).where(whole)
    width = given.groupBy(F.size("vec").alias("width")).count().orderBy(F.desc("count"), "width").first()
    return given.where(F.size("vec") == (width.width if width else 0))


def matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """Rows of equal width as a matrix."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    return column.flatten().to_numpy(zero_copy_only=False).reshape(n, -1) if n else np.empty((0, 0))
