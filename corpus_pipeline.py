"""From raw documents to packed training sequences in five stages.

1. language: documents whose language can't be told go;
2. lines: lines that ten or more documents share are cut;
3. near duplicates: one document of each group stays (five words, 0.8);
4. mixing: documents are drawn by rates that bring the labels' domains to their
   target shares of words;
5. packing: what is left goes to sequences of bounded length.

Every stage works on all that its predecessor kept, and all but the last return
the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nearfield.llm import language, lines, mixing, neardup, packing
from nearfield.llm.common import discard, keep, table, temporaries

#: Iteration, hashing and training are beyond SQL; the tests hold the stages against brute force.
ORACLE_SQL = None


def tell_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return language.identify(docs).where(F.col("lang_pred") != language.UNDETERMINED).select(docs.columns)


def cut_common_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The cut text and its new length; a document that loses all its lines stays, with an empty text."""
    cut = lines.drop_common_lines(docs)
    sized = cut.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else cut
    return sized.select(docs.columns)


def keep_one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return neardup.keep_one(docs)


def mix_to_targets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.drawn(docs, mixing.mix(docs, mixing.domains_of_labels(table(spark, sf_dir, "labels"))))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs)


STAGES = [
    ("language", tell_language),
    ("lines", cut_common_lines),
    ("near_duplicates", keep_one_of_each),
    ("mixing", mix_to_targets),
    ("packing", pack_sequences),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last stage's rows; every stage before it is written and read again."""
    docs, previous = table(spark, sf_dir, "documents"), None
    for _, stage in STAGES[:-1]:
        # What a stage wrote on its way goes when its result is written, and so does its input.
        with temporaries() as spared:
            docs = keep(stage(spark, docs, sf_dir))
            spared.append(docs)
        if previous is not None:
            discard(previous)
        previous = docs
    return STAGES[-1][1](spark, docs, sf_dir)
