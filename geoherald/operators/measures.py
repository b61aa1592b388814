"""What the experiments report: throughput, latency, memory, migration, replication."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from geoherald.operators.load import sub_bytes

#: Milliseconds at which a tuple counts as delayed and as heavily delayed.
BANDS = (100, 1000)


def throughput(n_tuples: int, job: Callable[[], object]) -> tuple[float, float]:
    """Tuples per second of a job that works through ``n_tuples``, and its seconds."""
    began = time.perf_counter()
    job()
    seconds = time.perf_counter() - began
    return n_tuples / seconds, seconds


def model_throughput(loads: DataFrame, n_tuples: int) -> DataFrame:
    """Tuples per unit of the most loaded worker's time: compares partitions whatever the hardware."""
    return loads.agg((F.lit(float(n_tuples)) / F.max("load")).alias("tuples_per_load"))


def latency(progress: list[dict]) -> float:
    """Mean milliseconds of a trigger, weighted by its rows, from a stream's progress reports."""
    rows = [(p["numInputRows"], p["durationMs"]["triggerExecution"]) for p in progress if p["numInputRows"]]
    return sum(n * ms for n, ms in rows) / max(1, sum(n for n, _ in rows))


def latency_bands(delays: DataFrame, ms: str = "ms", by: tuple[str, ...] = ()) -> DataFrame:
    """Shares of tuples under 100 ms, up to a second, and over."""
    low, high = BANDS
    share = lambda c: F.avg(F.when(c, 1.0).otherwise(0.0))
    delay = F.col(ms)
    return delays.groupBy(*by).agg(share(delay < low).alias("prompt"), share((delay >= low) & (delay <= high)).alias("delayed"), share(delay > high).alias("late"))


def queued(tuples: DataFrame, service_ms: Column, start: str = "arrive_ms") -> DataFrame:
    """Delay of each tuple at a worker that serves one at a time, in the order of arrival.

    The end of a service is the arrival plus all services since the queue was last empty: the running sum
    of services plus the greatest lead of an arrival over it.
    """
    order = Window.partitionBy("worker").orderBy(start, "seq").rowsBetween(Window.unboundedPreceding, 0)
    rows = tuples.withColumn("service", service_ms).withColumn("done", F.sum("service").over(order))
    lead = F.max(F.col(start) - (F.col("done") - F.col("service"))).over(order)
    return rows.withColumn("ms", F.col("done") + lead - F.col(start)).drop("done")


def dispatcher_bytes(live: DataFrame, head_terms: DataFrame) -> DataFrame:
    """Bytes of a dispatcher's two maps: a term with its length, a cell and a worker per entry."""
    entry = F.octet_length("term") + 4 + 4 + 4
    a = live.agg(F.coalesce(F.sum(entry), F.lit(0)).alias("live_bytes"))
    b = head_terms.agg(F.coalesce(F.sum(entry), F.lit(0)).alias("full_bytes"))
    return a.join(b, F.lit(True)).withColumn("bytes", F.col("live_bytes") + F.col("full_bytes"))


def worker_bytes(index: DataFrame) -> DataFrame:
    """Bytes of the posting lists per worker: each stored subscription once, and an entry per list."""
    once = index.select("worker", "sub_id", sub_bytes(F.col("dnf")).alias("b")).distinct().groupBy("worker").agg(F.sum("b").alias("subs"))
    entries = index.groupBy("worker").agg(F.sum(F.octet_length("term") + 16).alias("entries"))
    return once.join(entries, "worker").select("worker", (F.col("subs") + F.col("entries")).alias("bytes"))


def migration_cost(index: DataFrame, cells: tuple[int, ...], donor: int) -> DataFrame:
    """Bytes of the subscriptions stored in the moved cells."""
    moved = index.filter((F.col("worker") == donor) & F.col("cell").isin(*(cells or (-1,))))
    return moved.select("cell", "sub_id", sub_bytes(F.col("dnf")).alias("b")).distinct().agg(F.coalesce(F.sum("b"), F.lit(0)).alias("bytes"), F.countDistinct("sub_id").alias("subs"))


def timed(job: Callable[[], object]) -> tuple[float, object]:
    """Seconds that a job takes, and its result; for selection and migration times."""
    began = time.perf_counter()
    out = job()
    return time.perf_counter() - began, out
