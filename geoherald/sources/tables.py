"""Readers with fixed schemas, and round trips through the other formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

#: Columns of the given tables that the engine reads.
SCHEMAS = {
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "region": "r_regionkey int, r_name string",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "pages": "page_id long, url string, html string",
    "conversations": "conv_id long, turn long, role string, text string",
}


def read_table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    """A table of the folder; where its schema is fixed here, nothing is inferred."""
    reader = spark.read
    if name in SCHEMAS:
        reader = reader.schema(SCHEMAS[name])
    return reader.parquet(f"{folder}/{name}.parquet")


def stream_table(spark: SparkSession, path: str, schema: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def rate_source(spark: SparkSession, rows_per_second: int, partitions: int) -> DataFrame:
    """Synthetic load for throughput runs: a counter to derive tuples from."""
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).option("numPartitions", partitions).load()


def write_by_worker(df: DataFrame, path: str) -> None:
    """Parquet partitioned by worker, so that a reader of one worker's share opens that folder only."""
    df.repartition("worker").write.mode("overwrite").partitionBy("worker").parquet(path)


def write_index_table(df: DataFrame, name: str, buckets: int = 64) -> None:
    """Bucketed table of postings: joins on worker and cell need no exchange on this side."""
    df.write.mode("overwrite").bucketBy(buckets, "worker", "cell").sortBy("worker", "cell", "term").saveAsTable(name)


def round_trip(df: DataFrame, path: str, fmt: str) -> DataFrame:
    """Write as csv, json or parquet and read back with the same schema."""
    options = {"header": "true", "escape": '"', "multiLine": "true"} if fmt == "csv" else {}
    df.write.mode("overwrite").options(**options).format(fmt).save(path)
    return df.sparkSession.read.schema(df.schema).options(**options).format(fmt).load(path)
