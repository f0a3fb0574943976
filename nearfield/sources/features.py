"""Feature sets over the given tables, each as a PointSet and as DuckDB text.

Scales are fixed constants, so both engines compute the same doubles.  Lifted and
projected sets use coefficients drawn from a seed and rounded to six places.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from nearfield.functions.metrics import l1, l2
from nearfield.sources.points import PointSet


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def days(c: str) -> Column:
    """Days since the epoch of a zone-less time, whatever the session's zone."""
    return F.datediff(F.col(c).cast("date"), F.lit("1970-01-01")) + (F.hour(c) * 3600 + F.minute(c) * 60 + F.second(c)) / F.lit(86400.0)


def _days_sql(c: str) -> str:
    return f"(epoch({c}::TIMESTAMP)/86400.0)"


_LINE_ID = "l_orderkey||'-'||l_linenumber||'-'||l_partkey||'-'||l_suppkey"


def _line_id() -> Column:
    return F.concat_ws("-", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")


def _line4() -> list[Column]:
    return [F.col("l_quantity") / 50.0, F.col("l_extendedprice") / 105000.0, F.col("l_discount") / 0.1, F.col("l_tax") / 0.08]


_LINE4 = ["l_quantity/50.0::DOUBLE", "l_extendedprice/105000.0::DOUBLE", "l_discount/0.1::DOUBLE", "l_tax/0.08::DOUBLE"]


#: Which rows of lineitem a set holds, by the order's key, which stands first in an id.
Keep = Callable[[Column], Column]


def _lines(spark: SparkSession, sf_dir: str, keep: Keep | None) -> DataFrame:
    """Rows are chosen by the column, before ids are made; an id is read only where its first part is not that column's."""
    rows = table(spark, sf_dir, "lineitem")
    if keep is None:
        return rows
    return rows.where(keep(F.when(F.col("l_orderkey") >= 0, F.col("l_orderkey").cast("long")).otherwise(F.substring_index(_line_id(), "-", 1).cast("long"))))


def line4(spark: SparkSession, sf_dir: str, keep: Keep | None = None) -> PointSet:
    return PointSet.from_table(_lines(spark, sf_dir, keep), _line_id(), _line4())


def line8(spark: SparkSession, sf_dir: str, keep: Keep | None = None) -> PointSet:
    parts, supps = (float(table(spark, sf_dir, t).count()) for t in ("part", "supplier"))
    more = [(days("l_shipdate") - 9131.0) / 2500.0, F.col("l_linenumber") / F.lit(7.0), F.col("l_suppkey") / F.lit(supps), F.col("l_partkey") / F.lit(parts)]
    return PointSet.from_table(_lines(spark, sf_dir, keep), _line_id(), _line4() + more)


def lift_matrix(width: int, base: int, seed: int = 13) -> np.ndarray:
    return np.round(np.random.default_rng(seed * 1000 + width).normal(0, 1, (width, base)), 6)


def lifted(width: int) -> Callable[[SparkSession, str], PointSet]:
    """Four or eight columns of lineitem in ``width`` dimensions: tanh of a fixed mix."""

    def points(spark: SparkSession, sf_dir: str, keep: Keep | None = None) -> PointSet:
        return lift(SETS[lift_base(width)](spark, sf_dir, keep), width)

    return points


def lift_base(width: int) -> str:
    return "line8" if width == 21 else "line4"


def lift(base: PointSet, width: int) -> PointSet:
    mix = lift_matrix(width, base.metric.width)
    vec = F.array(*[F.tanh(sum((F.lit(float(w)) * F.col("value")[j] for j, w in enumerate(row) if j), F.lit(float(row[0])) * F.col("value")[0])) for row in mix])
    return PointSet(base.df.select("point_id", vec.alias("value")), l2(width))


def orders2(spark: SparkSession, sf_dir: str) -> PointSet:
    return PointSet.from_table(table(spark, sf_dir, "orders"), F.col("o_orderkey"), [F.col("o_totalprice") / 500000.0, (days("o_orderdate") - 9131.0) / 2500.0])


def events3(spark: SparkSession, sf_dir: str) -> PointSet:
    users = float(table(spark, sf_dir, "customer").count()) / 10.0
    return PointSet.from_table(table(spark, sf_dir, "events"), F.col("event_id"), [(F.hour("ts") * 60 + F.minute("ts")) / F.lit(1440.0), F.col("value") / 500.0, F.col("user_id") / F.lit(users)])


def part2(spark: SparkSession, sf_dir: str) -> PointSet:
    return PointSet.from_table(table(spark, sf_dir, "part"), F.col("p_partkey"), [F.col("p_size") / F.lit(50.0), F.col("p_retailprice") / 1000.0])


def part2_l1(spark: SparkSession, sf_dir: str) -> PointSet:
    return PointSet(part2(spark, sf_dir).df, l1(2))


def cust2(spark: SparkSession, sf_dir: str) -> PointSet:
    return PointSet.from_table(table(spark, sf_dir, "customer"), F.col("c_custkey"), [F.col("c_acctbal") / 10000.0, F.col("c_nationkey") / F.lit(25.0)])


def supp2(spark: SparkSession, sf_dir: str) -> PointSet:
    return PointSet.from_table(table(spark, sf_dir, "supplier"), F.col("s_suppkey"), [F.col("s_acctbal") / 10000.0, F.col("s_nationkey") / F.lit(25.0)])


def emb64(spark: SparkSession, sf_dir: str) -> PointSet:
    return PointSet.from_array(table(spark, sf_dir, "embeddings"), "vec_id", "embedding", 64)


def urls(spark: SparkSession, sf_dir: str) -> PointSet:
    return PointSet.from_text(table(spark, sf_dir, "pages"), "page_id", "url")


def passages(spark: SparkSession, sf_dir: str) -> PointSet:
    """Benchmark texts; letters beyond ASCII become question marks, as engines differ in counting their edits."""
    texts = table(spark, sf_dir, "benchmark").withColumn("text", F.regexp_replace("text", r"[^\x20-\x7E]", "?"))
    return PointSet.from_text(texts, "item_id", "text")


def doc_tokens(spark: SparkSession, sf_dir: str) -> PointSet:
    return PointSet.from_tokens(table(spark, sf_dir, "documents"), "doc_id", "text")


#: Width of the trigram vectors.
GRAMS = 54


def doc54(spark: SparkSession, sf_dir: str) -> PointSet:
    """Unit vectors of character-trigram counts, hashed to GRAMS places (cut up in Arrow batches)."""
    from nearfield.functions.projection import trigram_vectors

    return PointSet(trigram_vectors(table(spark, sf_dir, "documents").select(F.col("doc_id").alias("point_id"), "text"), GRAMS), l2(GRAMS))


def _select(point_id: str, parts: list[str], source: str) -> str:
    return f"SELECT {point_id} AS id, [{', '.join(parts)}]::DOUBLE[] AS v FROM {source}"


def _lift_sql(width: int) -> str:
    base, n = ("line8", 8) if width == 21 else ("line4", 4)
    mix = lift_matrix(width, n)
    parts = [f"tanh({' + '.join(f'{float(w)!r}::DOUBLE*v[{j + 1}]' for j, w in enumerate(row))})" for row in mix]
    return f"SELECT id, [{', '.join(parts)}]::DOUBLE[] AS v FROM ({SQL[base]})"


#: DuckDB text of each set: columns ``id`` and ``v``.
SQL: dict[str, str] = {
    "line4": _select(_LINE_ID, _LINE4, "lineitem"),
    "line8": _select(
        _LINE_ID,
        [*_LINE4, f"({_days_sql('l_shipdate')}-9131.0)/2500.0", "l_linenumber/7.0::DOUBLE", "l_suppkey/(SELECT count(*) FROM supplier)::DOUBLE", "l_partkey/(SELECT count(*) FROM part)::DOUBLE"],
        "lineitem",
    ),
    "orders2": _select("o_orderkey", ["o_totalprice/500000.0::DOUBLE", f"({_days_sql('o_orderdate')}-9131.0)/2500.0"], "orders"),
    "events3": _select("event_id", ["(hour(ts)*60+minute(ts))/1440.0::DOUBLE", "value/500.0::DOUBLE", "user_id/((SELECT count(*) FROM customer)/10.0::DOUBLE)"], "events"),
    "part2": _select("p_partkey", ["p_size/50.0::DOUBLE", "p_retailprice/1000.0::DOUBLE"], "part"),
    "cust2": _select("c_custkey", ["c_acctbal/10000.0::DOUBLE", "c_nationkey/25.0::DOUBLE"], "customer"),
    "supp2": _select("s_suppkey", ["s_acctbal/10000.0::DOUBLE", "s_nationkey/25.0::DOUBLE"], "supplier"),
    "emb64": "SELECT vec_id AS id, embedding::DOUBLE[] AS v FROM embeddings",
    "urls": "SELECT page_id AS id, url AS v FROM pages",
    "passages": r"SELECT item_id AS id, regexp_replace(text, '[^\x20-\x7E]', '?', 'g') AS v FROM benchmark",
    "doc_tokens": r"SELECT doc_id AS id, list_distinct(list_filter(regexp_split_to_array(lower(text), '\s+'), lambda x: x <> '')) AS v FROM documents",
}
SQL |= {"part2_l1": SQL["part2"]} | {f"lift{w}": _lift_sql(w) for w in (21, 54, 74, 78)}

#: Every set by name.
SETS: dict[str, Callable[..., PointSet]] = {
    "line4": line4, "line8": line8, "orders2": orders2, "events3": events3, "part2": part2, "part2_l1": part2_l1, "cust2": cust2, "supp2": supp2,
    "emb64": emb64, "urls": urls, "passages": passages, "doc_tokens": doc_tokens, "doc54": doc54,
} | {f"lift{w}": lifted(w) for w in (21, 54, 74, 78)}
