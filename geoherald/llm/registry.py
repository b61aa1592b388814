"""The thin queries over this subpackage's operators, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geoherald.llm import decontaminate, html_text, images, labelled, line_dedup, mixing, near_dedup, oracles, quality, suffixes, toxicity, url_rules

Query = Callable[[SparkSession, str], DataFrame]

URL_RULES = [
    url_rules.Rule.parse("block", "com/en/"),
    url_rules.Rule.parse("allow", "example.com/en/7"),
    url_rules.Rule.parse("allow", "net/de/"),
    url_rules.Rule.parse("block", "example.net/de/8"),
    url_rules.Rule.parse("block", "org/es/"),
]

OP8 = near_dedup.NearParams(shingle=3, num=85, den=100)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url", "html")
    return html_text.extract_text(pages).select("page_id", "url", "text", "n_chars")


def op2_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixes.repeated_passages(table(spark, sf_dir, "documents"))


def op3_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    cleaned = line_dedup.dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"), params=line_dedup.ALL_LINES)
    return cleaned.select("doc_id", "n_lines", "n_removed", F.length("text").alias("n_chars"), F.md5("text").alias("text_md5"))


def op5_image_copies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pictures drawn from ``embeddings``; cropped, dimmed copies of those with an id divisible by 50 are searched in all."""
    # a vector is a few hundred bytes and its picture takes milliseconds, so the rows are spread out first
    vectors = table(spark, sf_dir, "embeddings").repartition(3 * spark.sparkContext.defaultParallelism)
    media = vectors.select("vec_id", images.rendered(F.col("embedding")).alias("image"))
    return images.find_copies(media, F.col("vec_id") % 50 == 0, key="vec_id", change=images.edited)


def toxic_lexicon(spark: SparkSession, sf_dir: str) -> toxicity.Lexicon:
    """Learned from the tables in ``sf_dir``, never from held-out rows."""
    return toxicity.train_lexicon(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), labelled.remainder(F.col("doc_id"), 5) != 0)


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    lexicon = toxic_lexicon(spark, sf_dir)
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    scored = docs.select("doc_id", (labelled.remainder(F.col("doc_id"), 5) == 0).alias("held_out"), toxicity.toxicity_score(lexicon, F.col("text")).alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= toxicity.ToxicParams().threshold).cast("int"))


def op7_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mixing.mix_sources(table(spark, sf_dir, "documents"))
    return mixed.select("doc_id", "size", "source_size", "target", "taken")


def op8_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicates(table(spark, sf_dir, "documents"), params=OP8)


def op9_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = url_rules.judge_urls(table(spark, sf_dir, "pages").select("page_id", "url"), URL_RULES)
    return judged.select("page_id", "host", "path", "rule", "verdict")


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = quality.measured(table(spark, sf_dir, "documents").select("doc_id", "text"))
    ranker = quality.train_measured(docs, table(spark, sf_dir, "labels"), labelled.remainder(F.col("doc_id"), 4) != 2)
    scored = docs.select(F.col("key").alias("doc_id"), (labelled.remainder(F.col("key"), 4) == 2).alias("held_out"), quality.measured_score(ranker, F.col("x")).alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= quality.QualityParams().threshold).cast("int"))


def queries() -> dict[str, Query]:
    return {
        "op1_html_text": op1_html_text,
        "op2_suffix_dedup": op2_suffix_dedup,
        "op3_decontaminate": op3_decontaminate,
        "op4_line_dedup": op4_line_dedup,
        "op5_image_copies": op5_image_copies,
        "op6_toxicity": op6_toxicity,
        "op7_mixing": op7_mixing,
        "op8_near_dedup": op8_near_dedup,
        "op9_url_filter": op9_url_filter,
        "op10_quality": op10_quality,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op3_decontaminate": oracles.leaks(5, 80, 100),
        "op7_mixing": oracles.MIXING,
        "op8_near_dedup": oracles.near_dedup(3, 85, 100),
        "op9_url_filter": oracles.URL_RULES,
    }
