"""Streams of located messages made of the given tables, in whole numbers only.

Every engine that has integer division derives the same rows; ``plans.oracles`` has the SQL.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from geoherald.functions.expr import distinct, tokens
from geoherald.sources.shared import settle
from geoherald.sources.tables import read_table

WIDE_SIDE = 1 << 22
SMALL_SIDE = 1 << 20
_CITY = 838860


def wide_objects(spark: SparkSession, folder: str) -> DataFrame:
    """``obj_id, ts, x, y, terms``: events of users who live in 25 cities.

    A message is short: twelve words in a row of a document, from a place that the event decides. The other
    sources take whole texts.
    """
    docs = read_table(spark, folder, "documents").select("doc_id", tokens(F.col("text")).alias("toks"))
    homes = read_table(spark, folder, "customer").join(F.broadcast(read_table(spark, folder, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    homes = homes.select("c_custkey", "c_nationkey", "n_regionkey")
    count = docs.agg(F.count(F.lit(1))).first()[0]
    rows = read_table(spark, folder, "events").withColumn("doc", (F.col("event_id") * 7919) % max(count, 1)).join(homes, F.col("user_id") == F.col("c_custkey"))
    rows = rows.join(docs, F.col("doc") == F.col("doc_id"))
    cents = F.round(F.col("value") * 100).cast("long")

    def spread(centre, prime: int):
        """Around a centre, further out for larger values."""
        offset = F.floor((cents * 16 * ((F.col("event_id") * prime) % 2001)) / 2000).cast("long") - cents * 8
        return F.least(F.greatest(centre + offset, F.lit(0)), F.lit(WIDE_SIDE - 1)).cast("long")

    start = (1 + (F.col("event_id") * 31) % F.greatest(F.size("toks") - 11, F.lit(1))).cast("int")
    return rows.select(
        F.col("event_id").alias("obj_id"),
        "ts",
        spread(F.col("n_regionkey") * _CITY + _CITY // 2, 104729).alias("x"),
        spread(F.floor(F.col("c_nationkey") / 5) * _CITY + _CITY // 2, 1299709).alias("y"),
        distinct(F.slice("toks", start, F.lit(12))).alias("terms"),
    )


def small_objects(spark: SparkSession, folder: str) -> DataFrame:
    """``obj_id, x, y, terms``: documents placed by two components of embeddings."""
    vectors = read_table(spark, folder, "embeddings").select("vec_id", F.col("embedding")[0].cast("double").alias("e1"), F.col("embedding")[1].cast("double").alias("e2"))
    count = vectors.agg(F.count(F.lit(1))).first()[0]
    docs = read_table(spark, folder, "documents").select("doc_id", tokens(F.col("text")).alias("toks"))
    rows = docs.join(vectors, F.col("doc_id") % max(count, 1) == F.col("vec_id"))

    def place(e: str, prime: int):
        at = F.floor((F.col(e) + 0.5) * SMALL_SIDE).cast("long") + (F.floor(F.col("doc_id") / max(count, 1)).cast("long") * prime) % 4096
        return F.least(F.greatest(at, F.lit(0)), F.lit(SMALL_SIDE - 1)).cast("long")

    return rows.select(F.col("doc_id").alias("obj_id"), place("e1", 7919).alias("x"), place("e2", 104729).alias("y"), distinct(F.col("toks")).alias("terms"))


def product_objects(spark: SparkSession, folder: str) -> DataFrame:
    """``obj_id, x, y, terms`` of order lines: very short texts from a tiny lexicon, many alike."""
    lines = read_table(spark, folder, "lineitem")
    order = [F.col(c) for c in lines.columns]
    lines = lines.join(read_table(spark, folder, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    homes = read_table(spark, folder, "customer").join(F.broadcast(read_table(spark, folder, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "c_nationkey", "n_regionkey")
    parts = read_table(spark, folder, "part")
    rows = lines.join(homes, F.col("o_custkey") == F.col("c_custkey")).join(parts.select("p_partkey", "p_name", "p_type"), F.col("l_partkey") == F.col("p_partkey"))
    cents = F.round(F.col("l_quantity") * 100).cast("long")

    def spread(centre, prime: int):
        offset = F.floor((cents * 16 * ((F.col("l_partkey") * prime) % 2001)) / 2000).cast("long") - cents * 8
        return F.least(F.greatest(centre + offset, F.lit(0)), F.lit(WIDE_SIDE - 1)).cast("long")

    numbered = rows.withColumn("obj_id", numbered_by(rows, order))
    words = F.concat(F.split(F.lower("p_name"), " "), F.array(F.lower("p_type")))
    return numbered.select("obj_id", spread(F.col("n_regionkey") * _CITY + _CITY // 2, 104729).alias("x"), spread(F.floor(F.col("c_nationkey") / 5) * _CITY + _CITY // 2, 1299709).alias("y"), distinct(words).alias("terms"))


def numbered_by(rows: DataFrame, order: list) -> Column:
    """A stable id of a row: the hash of the columns that tell rows apart. Needs no order of all rows."""
    return F.xxhash64(*order)


def object_source(spark: SparkSession, folder: str, kind: str = "wide") -> DataFrame:
    """Any of the streams by name; ``conversations`` and ``pages`` give text without a place of its own, so
    they are spread over the small world by a multiplicative hash of the id."""
    if kind == "wide":
        return wide_objects(spark, folder)
    if kind == "small":
        return small_objects(spark, folder)
    if kind == "product":
        return product_objects(spark, folder)
    if kind == "pages":
        plain = F.regexp_replace(F.regexp_replace("html", r"(?s)<(script|style).*?</\1>", " "), r"<[^>]*>", " ")
        rows = read_table(spark, folder, "pages").select(F.col("page_id").alias("obj_id"), plain.alias("text"))
    elif kind == "conversations":
        rows = read_table(spark, folder, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("obj_id"), "text")
    else:
        raise ValueError(kind)
    at = lambda prime: ((F.col("obj_id") * prime) % SMALL_SIDE).cast("long")
    return rows.select("obj_id", at(48271).alias("x"), at(69621).alias("y"), distinct(tokens(F.col("text"))).alias("terms"))


def lexicon(objects: DataFrame) -> DataFrame:
    """``term, df``: objects that have the term."""
    return objects.select(F.explode("terms").alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("df"))


def ranked(terms: DataFrame) -> DataFrame:
    """Adds ``rk``, 1 for the most frequent; of equal ones the smaller term first.

    Numbers come from a range partitioning, so that no task sorts the whole lexicon.
    """
    order = [F.desc("df"), F.col("term")]
    parted = settle(terms.repartitionByRange(*order).withColumn("part", F.spark_partition_id()), "lexicon")
    sizes = parted.groupBy("part").agg(F.count(F.lit(1)).alias("size"))
    # one row per partition
    starts = sizes.select("part", F.sum("size").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)).alias("start"))
    local = F.row_number().over(Window.partitionBy("part").orderBy(*order))
    return parted.withColumn("local", local).join(F.broadcast(starts), "part").select("term", "df", (F.coalesce("start", F.lit(0)) + F.col("local")).cast("long").alias("rk"))
