"""The training-data pipeline: five stages over ``documents``, each written and read again."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geoherald.llm import decontaminate, line_dedup, mixing, near_dedup, registry, toxicity
from geoherald.llm.scratch import store


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the lexicon, trained on the labels in ``sf_dir``, scores under the threshold."""
    lexicon = registry.toxic_lexicon(spark, sf_dir)
    return docs.filter(toxicity.toxicity_score(lexicon, F.col("text")) < toxicity.ToxicParams().threshold)


def dedup_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, without lines that repeat an earlier one; ``n_chars`` follows the text."""
    cleaned = line_dedup.dedup_lines(docs, params=line_dedup.ALL_LINES)
    return cleaned.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)).select(*docs.columns)


def dedup_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates."""
    return near_dedup.keep_one_of_each(docs)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    return decontaminate.drop_leaking(docs, registry.table(spark, sf_dir, "benchmark"))


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix: one row for each copy taken of a document."""
    return mixing.emit_copies(mixing.mix_sources(docs)).select(*docs.columns, "copy_no")


STAGES = [
    ("toxicity", drop_toxic),
    ("line dedup", dedup_lines),
    ("near dedup", dedup_documents),
    ("decontamination", drop_leaks),
    ("mixing", mix),
]

#: A learned lexicon and edit distances over all pairs of lines are out of reach for SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents in ``sf_dir``; what lies between two stages is a written table."""
    docs = registry.table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = store(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
