"""Which pairing a search uses, and whether it pays to search at all.

``nested``  one side is broadcast and the distance is a Column (any metric);
``kernel``  one side travels in the task closure and distances are numpy blocks;
``grid``    neither side is small: blocks of both meet by a shuffle on block ids.

A side is broadcast only if its checked size is under ``BROADCAST_BYTES``.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import SparkSession

from nearfield.sources.points import PointSet

#: Most bytes that a side may have to be sent to every task.
BROADCAST_BYTES = 256 << 20
#: Rows of a block of the grid.
BLOCK_ROWS = 65_536


@dataclass(frozen=True)
class Pairing:
    kind: str
    small: str
    reason: str


def bytes_of(rows: int, points: PointSet) -> int:
    """What a side takes in memory: doubles for vectors, 200 bytes for anything else."""
    return rows * (8 * (points.metric.width or 25) + 24)


def choose_pairing(q: PointSet, x: PointSet, rows_q: int, rows_x: int, limit: int = BROADCAST_BYTES) -> Pairing:
    """The pairing for these sizes; the smaller side is the one that is sent."""
    small, rows = ("q", rows_q) if rows_q <= rows_x else ("x", rows_x)
    size = bytes_of(rows, q if small == "q" else x)
    if size > limit:
        return Pairing("grid", small, f"{size} bytes of the smaller side are over {limit}")
    return Pairing("kernel" if x.is_vector else "nested", small, f"{size} bytes of side {small} are sent")


def choose_method(rows_x: int, survivors: float | None, wants_exact: bool = True, n_r: int | None = None) -> str:
    """brute, exact or oneshot, from the share of the table that a sample of queries had to examine.

    Below half of the table, pivots and pruned lists cost less than a scan.
    """
    if not wants_exact:
        return "oneshot"
    if survivors is None or rows_x < 1000:
        return "brute"
    return "exact" if survivors + (n_r or 0) / max(1, rows_x) < 0.5 else "brute"


def describe(spark: SparkSession, cases: list[tuple[str, int, int, int]]):
    """The planner's decisions for (name, rows_q, rows_x, width) as a DataFrame."""
    from nearfield.functions.metrics import l2

    rows = []
    for name, rows_q, rows_x, width in cases:
        points = PointSet(spark.range(0), l2(width))
        p = choose_pairing(points, points, rows_q, rows_x)
        rows.append((name, rows_q, rows_x, width, p.kind, p.small))
    return spark.createDataFrame(rows, "case_name string, rows_q long, rows_x long, width int, pairing string, sent_side string")
