"""A training-data pipeline over ``documents``: each stage works on what the one before it kept.

1. quality: documents that the compression classifier scores below 0.3 go;
2. near_duplicates: one document of each near-duplicate group stays;
3. decontamination: documents that leak a benchmark item go;
4. personal_data: personal data and terms that disclose it are replaced in the texts, and n_chars follows;
5. tokens: the texts' ids, as digests (``bpe.encode`` gives the lists).

Defined results: a null or empty text gets the score of no evidence (the share of good labels), is no one's duplicate, leaks nothing, holds no personal data and has no
tokens; rows with the same id and the same words are one document after stage 2, rows with a null id all stay; empty tables give no rows;
extra columns pass through the first four stages whatever their names, unless they are named like ``documents``' own.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fdrepair.llm import bpe, decontaminate, neardup, pii, quality
from fdrepair.llm.common import dropped, freed, table, written
from fdrepair.llm.queries import tokenizer


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = quality.fit(docs, table(spark, sf_dir, "labels"))
    return quality.score(docs, model, out="__score").where("__score >= 0.3").select(*docs.columns)


def keep_one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return neardup.keep_one(docs).select(*docs.columns)


def keep_uncontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark")).select(*docs.columns)


def sanitised(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pii.sanitise(docs).withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return bpe.digests(docs, *tokenizer())


STAGES = [
    ("quality", keep_good),
    ("near_duplicates", keep_one_of_each),
    ("decontamination", keep_uncontaminated),
    ("personal_data", sanitised),
    ("tokens", encoded),
]

#: No stage can be written in SQL: compression, darts, templates, co-occurrence spans and byte pairs have no counterpart there.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each stage's result is written and read again, in the shared checkpoint folder."""
    docs = table(spark, sf_dir, "documents")
    kept: list[DataFrame] = []
    for _, stage in STAGES[:-1]:
        kept.append(written(stage(spark, docs, sf_dir)))
        dropped(*kept[:-1])
        kept, docs = kept[-1:], kept[-1]
        freed(spark)
    return STAGES[-1][1](spark, docs, sf_dir)
