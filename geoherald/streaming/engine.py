"""The stream: dispatch, matching and merging of a stream of objects, registrations and cancellations.

``replay`` works micro-batch by micro-batch with the batch plan and an index table (registrations
and cancellations of a batch are entered before its objects are matched, and the places in the stream
decide what stands). ``stateful`` keeps posting lists as keyed state per cell and term, for a stream
without a table to rewrite.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from geoherald.operators.adjust import detect, phase_two, share_to_move
from geoherald.operators.assignment import Assignment
from geoherald.operators.load import cell_load, worker_load
from geoherald.operators.matching import match, merge
from geoherald.operators.routing import live_map, route_objects, subs_at_cells
from geoherald.sources.shared import settle

#: Terms whose frequencies a stateful stream takes along.
MAX_TERMS = 1_000_000

TUPLE = (
    "seq long, op string, ts timestamp, obj_id long, x long, y long, terms array<string>, "
    "sub_id long, owner long, x0 long, x1 long, y0 long, y1 long, dnf array<array<string>>"
)


def as_tuples(objects: DataFrame, subs: DataFrame) -> DataFrame:
    """One table of the three kinds, with the columns of ``TUPLE``; a cancellation repeats its subscription."""
    last = objects.agg(F.max("seq")).first()[0]
    ts = F.col("ts").cast("timestamp") if "ts" in objects.columns else F.timestamp_seconds("seq")
    body = ("sub_id", "owner", "x0", "x1", "y0", "y1", "dnf")
    parts = [objects.select("seq", F.lit("obj").alias("op"), ts.alias("ts"), "obj_id", "x", "y", "terms")]
    parts.append(subs.select(F.col("reg_seq").alias("seq"), F.lit("reg").alias("op"), *body))
    parts.append(subs.filter(F.col("cancel_seq") <= last).select(F.col("cancel_seq").alias("seq"), F.lit("cancel").alias("op"), *body))
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part, allowMissingColumns=True)
    names = [c.split()[0] for c in TUPLE.split(", ")]
    return out.select(*names)


def write_slices(tuples: DataFrame, path: str, slices: int) -> list[str]:
    """The stream cut into ``slices`` files' worth of consecutive tuples, one folder each, in order."""
    ends = tuples.agg(F.min("seq").alias("a"), F.max("seq").alias("b")).first()
    step = max(1, -(-(ends["b"] - ends["a"] + 1) // slices))
    cut = tuples.withColumn("slice", F.floor((F.col("seq") - ends["a"]) / step).cast("int"))
    out = []
    for k in range(slices):
        cut.filter(F.col("slice") == k).drop("slice").coalesce(1).write.mode("append").parquet(path)
        out.append(path)
    return out


def source(spark: SparkSession, path: str) -> DataFrame:
    return spark.readStream.schema(TUPLE).option("maxFilesPerTrigger", 1).parquet(path)


class Replay:
    """State of a replay between micro-batches: the index, the routing version, and what was delivered.

    A batch is entered under its number, so that one that runs again after a failure leaves what it left
    the first time. Postings are kept by cell and term and get their worker from the routing version in
    force, so that cells can change hands between batches. Index and tombstones have generations:
    :meth:`compact` writes the next one and a marker after it, and what has no marker is not read.

    ``hook`` is called after each batch with its number and tables. Objects more than ``late_s`` seconds
    behind the latest of earlier batches are matched like any other, and counted.
    """

    def __init__(self, spark: SparkSession, assignment: Assignment, freq: DataFrame, folder: str, hook: Callable[["Replay", int, dict[str, DataFrame]], None] | None = None, late_s: int = 3600):
        self.spark, self.assignment, self.freq, self.folder, self.hook, self.late_s = spark, assignment, freq, folder, hook, late_s

    def _path(self, name: str):
        return self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/{name}")

    def _exists(self, name: str) -> bool:
        path = self._path(name)
        return path.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(path)

    def _generation(self) -> int:
        found = 0
        while self._exists(f"generations/{found + 1}"):
            found += 1
        return found

    def table(self, name: str, number: int | None = None) -> DataFrame | None:
        """A table as of a batch, or of the last."""
        if not self._exists(name):
            return None
        rows = self.spark.read.parquet(f"{self.folder}/{name}")
        return (rows if number is None else rows.filter(F.col("batch") <= number)).drop("batch")

    def _held(self, name: str) -> str:
        return f"{name}/gen={self._generation()}"

    def on_batch(self, batch: DataFrame, number: int) -> None:
        began = time.perf_counter()
        batch = batch.persist()
        payload = ["sub_id", "owner", "x0", "x1", "y0", "y1", "dnf"]
        regs = batch.filter("op = 'reg'").select(*payload, F.col("seq").alias("reg_seq"))
        cancels = batch.filter("op = 'cancel'").select("sub_id", F.col("seq").alias("cancel_seq"))
        subs_at_cells(regs, self.freq, self.assignment.grid).write.mode("overwrite").parquet(f"{self.folder}/{self._held('index')}/batch={number}")
        cancels.write.mode("overwrite").parquet(f"{self.folder}/{self._held('tombstones')}/batch={number}")
        dead = self.table(self._held("tombstones"), number).select("sub_id", "cancel_seq")
        index = self.assignment.place(self.table(self._held("index"), number).join(dead, "sub_id", "left"))
        objects = batch.filter("op = 'obj'").select("obj_id", "seq", "x", "y", "terms")
        routed = route_objects(objects, live_map(index), self.assignment.grid)
        merge(match(objects, routed, index, self.assignment.grid)).write.mode("overwrite").parquet(f"{self.folder}/matches/batch={number}")
        self._clocked(batch, number, time.perf_counter() - began)
        if self.hook is not None:
            self.hook(self, number, {"batch": batch, "index": index, "routed": routed})
        batch.unpersist()

    def _clocked(self, batch: DataFrame, number: int, seconds: float) -> None:
        """One row per batch: its latest event, its late objects, and how long its tuples waited for their delivery."""
        times = batch.filter("op = 'obj' and ts is not null")
        known = self.table("clock", number - 1)
        before = known.agg(F.max("latest")).first()[0] if known is not None else None
        late = F.lit(0).cast("long") if before is None else F.coalesce(F.sum((F.col("ts") < F.lit(before) - F.make_dt_interval(secs=F.lit(self.late_s))).cast("long")), F.lit(0).cast("long"))
        times.agg(F.max("ts").alias("latest"), late.alias("late"), F.count(F.lit(1)).alias("n"), F.lit(seconds * 1000).alias("wait_ms")).write.mode("overwrite").parquet(f"{self.folder}/clock/batch={number}")

    def late_objects(self) -> int:
        return self.table("clock").agg(F.sum("late")).first()[0]

    def wait_ms(self) -> float:
        """Mean milliseconds from a batch's start to the delivery of its objects, weighted by objects."""
        return self.table("clock").agg(F.sum(F.col("wait_ms") * F.col("n")) / F.sum("n")).first()[0]

    def compact(self, up_to: int) -> None:
        """A next generation of the index without subscriptions that were cancelled before the tuple ``up_to``, and
        of the tombstones without theirs."""
        nxt = self._generation() + 1
        dead = self.table(self._held("tombstones"))
        gone = dead.filter(F.col("cancel_seq") < up_to).select("sub_id")
        self.table(self._held("index")).join(gone, "sub_id", "left_anti").write.mode("overwrite").parquet(f"{self.folder}/index/gen={nxt}/batch=-1")
        dead.filter(F.col("cancel_seq") >= up_to).write.mode("overwrite").parquet(f"{self.folder}/tombstones/gen={nxt}/batch=-1")
        marker = self._path(f"generations/{nxt}")
        marker.getFileSystem(self.spark._jsc.hadoopConfiguration()).create(marker, True).close()

    def matches(self) -> DataFrame:
        return self.table("matches").distinct()


@dataclass
class Adjuster:
    """A hook that moves cells from the most to the least loaded worker when a batch breaks the balance.

    ``moves`` lists what it did: batch, workers, cells, bytes, the load before, and seconds of the choice. The routing version
    grows with each move. Loads are counted on all rows of the batch.
    """

    sigma: float = 1.5
    method: str = "ratio_greedy"
    moves: list[dict] = field(default_factory=list)
    tops: list[dict] = field(default_factory=list)
    active: bool = True

    def __call__(self, state: Replay, number: int, parts: dict[str, DataFrame]) -> None:
        standing = parts["index"].filter("cancel_seq is null")
        routed, index = settle(parts["routed"], "routed"), settle(standing, "standing")
        loads = settle(worker_load(routed, index, state.assignment.m), "loads")
        ends = loads.agg(F.max("load").alias("top"), F.sum("load").alias("total"), F.sum("n_obj").alias("sends")).first()
        self.tops.append({"batch": number, "top": ends["top"], "total": ends["total"], "tuples": parts["batch"].count(), "moved": 0})
        found = detect(loads, self.sigma) if self.active else None
        if found is None:
            return
        donor, receiver, high, _ = found
        share = share_to_move(loads, donor, receiver, self.sigma)
        if share == 0:
            return
        began = time.perf_counter()
        state.assignment, choice = phase_two(cell_load(routed, index), state.assignment, donor, receiver, share, self.method)
        self.tops[-1]["moved"] = choice.size
        self.moves.append({"batch": number, "donor": donor, "receiver": receiver, "cells": choice.cells, "bytes": choice.size, "load": high, "seconds": time.perf_counter() - began, "version": state.assignment.version})


def replay(stream: DataFrame, state: Replay, checkpoint: str) -> list[dict]:
    """Runs a finite stream to its end, one file per micro-batch; progress reports are returned."""
    query = stream.writeStream.foreachBatch(state.on_batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return [p.asDict() if hasattr(p, "asDict") else p for p in query.recentProgress]


def load_per_window(stream: DataFrame, length: str = "4 hours", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Tuples per kind and window, tumbling or sliding, with a watermark."""
    frame = F.window("ts", length, slide) if slide else F.window("ts", length)
    return stream.withWatermark("ts", late).groupBy(frame, "op").agg(F.count(F.lit(1)).alias("n"))


def merged_stream(pairs: DataFrame, late: str = "10 minutes") -> DataFrame:
    """The merger over a stream of pairs: each once, remembered as long as the watermark allows."""
    return pairs.withWatermark("ts", late).dropDuplicatesWithinWatermark(["sub_id", "obj_id"])


def standing(regs: DataFrame, cancels: DataFrame, longest: str = "30 days") -> DataFrame:
    """Registrations with their cancellations, if any, by an interval join of two streams: the way without
    tombstones. Both sides have ``sub_id`` and ``ts``."""
    a = regs.withWatermark("ts", "1 hour").withColumnRenamed("ts", "reg_ts")
    b = cancels.select(F.col("sub_id").alias("gone"), F.col("ts").alias("cancel_ts")).withWatermark("cancel_ts", "1 hour")
    within = (F.col("sub_id") == F.col("gone")) & (F.col("cancel_ts") >= F.col("reg_ts")) & (F.col("cancel_ts") <= F.col("reg_ts") + F.expr(f"interval {longest}"))
    return a.join(b, within, "leftOuter").drop("gone")


class PostingLists(StatefulProcessor):
    """State of one (cell, term): its posting list by subscription, and when entries were cancelled.

    Within a call, tuples are taken in the order of their places in the stream.
    """

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.postings = handle.getMapState("postings", "sub_id long", "x0 long, x1 long, y0 long, y1 long, dnf array<array<string>>")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        held = {k[0]: v for k, v in self.postings.iterator()}
        out = []
        for r in pd.concat(list(rows)).sort_values("seq").itertuples(index=False):
            if r.op == "reg":
                held[r.sub_id] = (r.x0, r.x1, r.y0, r.y1, [list(c) for c in r.dnf])
                self.postings.updateValue((int(r.sub_id),), tuple(held[r.sub_id]))
            elif r.op == "cancel":
                if held.pop(r.sub_id, None) is not None:
                    self.postings.removeKey((int(r.sub_id),))
            else:
                terms = set(r.terms)
                for sub, (x0, x1, y0, y1, dnf) in held.items():
                    if x0 <= r.x <= x1 and y0 <= r.y <= y1 and any(terms.issuperset(c) for c in dnf):
                        out.append((sub, r.obj_id))
        yield pd.DataFrame(out, columns=["sub_id", "obj_id"]).astype("int64")

    def close(self) -> None:
        pass


def stateful(stream: DataFrame, assignment: Assignment, freq: DataFrame) -> DataFrame:
    """Pairs found by keyed state, with repeats; the key is (cell, term), the worker only a label of it.

    Needs the RocksDB state store.
    """
    grid = assignment.grid
    subs = stream.filter("op <> 'obj'")
    # the frozen frequencies travel with the function, within a bound that is checked
    if freq.limit(MAX_TERMS + 1).count() > MAX_TERMS:
        raise ValueError(f"over {MAX_TERMS} terms: use replay, which joins the table")
    df = dict(freq.select("term", "df").collect())

    @F.pandas_udf("array<string>")
    def least(dnf: pd.Series) -> pd.Series:
        return dnf.map(lambda clauses: sorted({min(c, key=lambda t: (df.get(t, 0), t)) for c in clauses}))

    keyed = subs.withColumn("term", F.explode(least("dnf"))).withColumn("cell", F.explode(grid.overlapped(F.col("x0"), F.col("y0"), F.col("x1"), F.col("y1"))))
    probes = stream.filter("op = 'obj'").withColumn("term", F.explode(F.array_distinct("terms"))).withColumn("cell", grid.cell(F.col("x"), F.col("y")))
    both = keyed.unionByName(probes)
    return both.groupBy("cell", "term").transformWithStateInPandas(statefulProcessor=PostingLists(), outputStructType="sub_id long, obj_id long", outputMode="Append", timeMode="None")

