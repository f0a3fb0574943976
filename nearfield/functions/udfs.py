"""User surface in SQL: functions, an aggregate and a table function around distances."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def distance(a: pd.Series, b: pd.Series) -> pd.Series:
    """l2 of two vector columns, batch by batch."""
    left, right = np.stack(a.to_numpy()), np.stack(b.to_numpy())
    total = np.zeros(len(left))
    for i in range(left.shape[1]):
        total = total + (left[:, i] - right[:, i]) ** 2
    return pd.Series(np.sqrt(total))


@F.pandas_udf(T.DoubleType())
def spread(v: pd.Series) -> float:
    """The mean distance of a group's values to their median."""
    return float((v - v.median()).abs().mean())


@F.udtf(returnType=T.StructType([T.StructField("item", T.LongType()), T.StructField("dist", T.DoubleType()), T.StructField("rank_no", T.IntegerType())]))
class Neighbours:
    """``ms_neighbors(TABLE(...), k)``: the k rows of least dist; rows are (item, dist)."""

    def __init__(self):
        self.rows, self.k = [], 1

    def eval(self, row: T.Row, k: int):
        self.k = k
        self.rows.append((row[1], row[0]))
        if len(self.rows) > 4 * k + 1024:
            self.rows = sorted(self.rows)[:k]

    def terminate(self):
        for place, (dist, item) in enumerate(sorted(self.rows)[: self.k], 1):
            yield item, dist, place


def register(spark: SparkSession) -> None:
    """Make the functions known to SQL."""
    spark.udf.register("ms_distance", distance)
    spark.udf.register("ms_spread", spread)
    spark.udtf.register("ms_neighbors", Neighbours)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION ms_l2(ax DOUBLE, ay DOUBLE, bx DOUBLE, by DOUBLE) RETURNS DOUBLE RETURN sqrt((ax - bx) * (ax - bx) + (ay - by) * (ay - by))")
