"""Sets by value: equal points are measured once, under their least id, and every row gets the answer of its value.

Ties go to the smaller id, so of equal points only the one of the least id can be
a nearest neighbour; counts weigh a value by its copies.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nearfield.operators import bruteforce as bf
from nearfield.sources.points import PointSet

#: Rows that a task gathers before it drops repeated ones, and different ones that it holds before they leave.
GATHERED, HELD = 1 << 18, 1 << 19


def _gathered(points: PointSet) -> DataFrame:
    """Map-side step for ids that no hash aggregate can hold (strings): ``value, point_id, copies`` of each task's repeats."""
    rows = points.df.select("value", "point_id")
    schema = T.StructType([*rows.schema.fields, T.StructField("copies", T.LongType())])

    def merged(tables: list[pa.Table], width: int) -> pa.Table:
        axes = [f"v{i}" for i in range(width)]
        return pa.concat_tables(tables).group_by(axes).aggregate([("id", "min"), ("copies", "sum")]).rename_columns([*axes, "id", "copies"])

    def out(table: pa.Table, width: int) -> Iterator[pa.RecordBatch]:
        import numpy as np

        values = np.stack([table.column(f"v{i}").to_numpy() for i in range(width)], axis=1)
        for at in range(0, len(values), 1 << 14):
            part = values[at : at + (1 << 14)]
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, part.size + 1, width, dtype=np.int32)), pa.array(part.ravel(), pa.float64(), from_pandas=False))
            some = table.slice(at, len(part))
            yield pa.RecordBatch.from_arrays([lists, some.column("id").combine_chunks(), some.column("copies").combine_chunks()], ["value", "point_id", "copies"])

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows, width = [], 0, 0
        for batch in batches:
            if not batch.num_rows:
                continue
            m = bf.matrix(batch.column(0)) + 0.0
            width = m.shape[1]
            held.append(pa.table({f"v{i}": pa.array(m[:, i]) for i in range(width)} | {"id": batch.column(1), "copies": pa.array([1] * len(m), pa.int64())}))
            rows += len(m)
            if rows >= GATHERED:
                held = [merged(held, width)]
                rows = 0
                if held[0].num_rows >= HELD:
                    yield from out(held[0], width)
                    held = []
        if held:
            yield from out(merged(held, width), width)

    return rows.mapInArrow(gather, schema)


def heads(points: PointSet) -> PointSet:
    """``point_id, value, copies``: one row a value, under its least id."""
    if points.is_vector and points.id_type == T.StringType():
        rows = _gathered(points).groupBy("value").agg(F.min("point_id").alias("point_id"), F.sum("copies").alias("copies"))
    else:
        rows = points.df.groupBy("value").agg(F.min("point_id").alias("point_id"), F.count(F.lit(1)).alias("copies"))
    return PointSet(rows.select("point_id", "value", "copies"), points.metric)


def members(points: PointSet, own: PointSet) -> DataFrame:
    """``query_id, head_id``: every row with the head of its value."""
    return points.df.select(F.col("point_id").alias("query_id"), "value").join(own.df.select(F.col("point_id").alias("head_id"), "value"), "value").select("query_id", "head_id")


def everyone(asked: DataFrame, found: DataFrame) -> DataFrame:
    """The answers of heads (``query_id, ...``), for all rows that they stand for."""
    return asked.join(found.withColumnRenamed("query_id", "head_id"), "head_id").select("query_id", *[c for c in found.columns if c != "query_id"])
