"""A training corpus from `documents`: language ID, near-duplicate removal, passage removal, mixing, packing.

Each stage takes all that its predecessor kept, is written as Parquet and read again. All but the last keep the columns of documents.
Empty inputs give empty outputs; null ids, texts, languages and sources are handled as the operators say.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from topfd.llm import language_id, mixing, near_dedup, packing, substring_dedup
from topfd.llm.common import marked, removed, table, written

#: Texts whose words agree on no language, on average, go. Clean single-language texts score above 0.9.
LEAST_SCORE = 0.4


def identified(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in one of the learned languages. A missing lang is filled with the predicted one. Where no language can be learned (no labelled row), all stay."""
    field = language_id.train(docs)
    if field is None:
        return docs
    lang, score = (next(n for k in range(len(docs.columns) + 1) if (n := f"{name}{k}") not in docs.columns) for name in ("judged_lang", "judged_score"))
    judged = language_id.predict(docs, field, docs.columns, (lang, score))
    kept = judged.where((F.col(lang) != language_id.UNKNOWN) & (F.col(score) >= LEAST_SCORE))
    return kept.select(*[F.coalesce("lang", lang).alias(c) if c == "lang" else F.col(f"`{c}`").alias(c) for c in docs.columns])


def distinct_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group: five-word shingles, similarity 0.8 or more."""
    return near_dedup.one_of_each(docs, width=5, percent=80)


def distinct_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of 20 words and more stay where they stand first; documents of which nothing is left go."""
    out = substring_dedup.deduplicated(docs).where(F.length("text") > 0)
    return out.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else out


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.sample(docs)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs)


STAGES = [("language ID", identified), ("near-duplicates", distinct_documents), ("repeated passages", distinct_passages), ("mixing", mixed), ("packing", packed)]

#: A learned field and byte-pair ids have no SQL form.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, begun = table(spark, sf_dir, "documents"), marked(spark)
    for _, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir))
        # what led to these rows is stored in them
        removed(spark, begun, keep=docs)
    return docs
