"""Queries of the corpus operators, each over its whole table, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from nearfield.llm import curves, html, kdtree, language, lines, mixing, neardup, packing, private, repeats
from nearfield.llm.common import table


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lines.digest(lines.drop_common_lines(table(spark, sf_dir, "documents")))


def op8_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"))


def op9_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    return language.identify(docs).select("doc_id", "held_out", "lang_pred", "score")


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = mixing.domains_of_labels(table(spark, sf_dir, "labels"))
    return mixing.mix(table(spark, sf_dir, "documents"), labels)


def op2_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html.extract(table(spark, sf_dir, "pages").select("page_id", "url", "html")).select("page_id", "url", "text", "n_chars")


def op3_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return kdtree.top_k(table(spark, sf_dir, "embeddings"))


def op4_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return repeats.digest(repeats.cut_repeats(docs))


def op5_private_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return private.digest(private.find(table(spark, sf_dir, "documents")))


def op6_nearest_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return curves.nearest(table(spark, sf_dir, "embeddings"))


def op7_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.group(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_mixing": op1_mixing,
        "op2_html_text": op2_html_text,
        "op3_exact_top_k": op3_exact_top_k,
        "op4_substring_dedup": op4_substring_dedup,
        "op5_private_spans": op5_private_spans,
        "op6_nearest_neighbours": op6_nearest_neighbours,
        "op7_near_duplicates": op7_near_duplicates,
        "op8_best_fit_packing": op8_best_fit_packing,
        "op9_language_id": op9_language_id,
        "op10_line_dedup": op10_line_dedup,
    }


def oracle_sql() -> dict[str, str]:
    return {"op2_html_text": html.PAGES_SQL, "op3_exact_top_k": kdtree.TOP_SQL, "op4_substring_dedup": repeats.REPEATS_SQL, "op7_near_duplicates": neardup.NEAR_SQL, "op10_line_dedup": lines.LINES_SQL}
