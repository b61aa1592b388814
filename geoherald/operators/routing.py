"""Dispatch: which workers get an object, a registration or a cancellation.

A clause is kept under its least frequent keyword, so an object can only satisfy it if it has that
keyword, and lies in a cell that the rectangle overlaps. Hence (cell, keyword) finds every match.
Frequencies are frozen with a routing version: a cancellation then goes where its registration went.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from geoherald.functions.expr import codes
from geoherald.functions.geometry import Grid
from geoherald.operators import cellmatch, rowroute
from geoherald.operators.assignment import Assignment
from geoherald.sources.world import lexicon

# tasks need no path to the package
register_pickle_by_value(cellmatch)
register_pickle_by_value(rowroute)

#: Rows up to which a frequency table is broadcast; beyond, it is joined by shuffling.
BROADCAST_TERMS = 1_000_000
#: Rows up to which tasks get a live map whole; beyond, objects meet it by shuffling.
HELD_LIVE = 8_000_000


def term_freq(objects: DataFrame) -> DataFrame:
    """``term, df`` of a sample of objects or of all; terms it lacks count as 0."""
    return lexicon(objects)


def routing_terms(subs: DataFrame, freq: DataFrame) -> DataFrame:
    """``sub_id, term, clauses``: for each clause its least frequent keyword, of equal ones the smaller term, with the
    places of the clauses that it stands for. One exchange, by ``sub_id``, where the frequencies can be broadcast."""
    clauses = subs.select("sub_id", "dnf").repartition("sub_id").select("sub_id", F.posexplode("dnf").alias("clause", "words"))
    words = clauses.select("sub_id", "clause", F.explode("words").alias("term")).join(few(freq, BROADCAST_TERMS), "term", "left")
    least = words.groupBy("sub_id", "clause").agg(F.min(F.struct(F.coalesce("df", F.lit(0)).alias("df"), F.col("term").alias("term"))).alias("least"))
    return least.groupBy("sub_id", F.col("least.term").alias("term")).agg(F.collect_list("clause").alias("clauses"))


def few(df: DataFrame, most: int) -> DataFrame:
    """Broadcast, if there are no more than ``most`` rows."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


def subs_at_cells(subs: DataFrame, freq: DataFrame, grid: Grid) -> DataFrame:
    """``sub_id, cell, term, clauses`` with the payload of the subscription, for every cell and routing term. Up to
    ``BROADCAST_TERMS`` frequencies are looked up where the subscription is; beyond, :func:`routing_terms` are joined."""
    terms = freq.orderBy("df", "term").select("term").limit(BROADCAST_TERMS + 1).toArrow()["term"].combine_chunks()
    if len(terms) > BROADCAST_TERMS:
        keyed = subs.join(routing_terms(subs, freq), "sub_id")
    else:
        held = subs.sparkSession.sparkContext.broadcast(terms)
        routes = T.StructType([T.StructField("term", T.StringType()), T.StructField("clauses", T.ArrayType(T.IntegerType()))])
        found = subs.mapInArrow(lambda batches: rowroute.keyed(batches, held.value), T.StructType([*subs.schema.fields, T.StructField("routes", T.ArrayType(routes))]))
        keyed = found.withColumn("route", F.explode("routes")).select(*subs.columns, "route.term", "route.clauses")
    return keyed.withColumn("cell", F.explode(grid.overlapped(F.col("x0"), F.col("y0"), F.col("x1"), F.col("y1"))))


def route_subs(subs: DataFrame, assignment: Assignment, freq: DataFrame, by_tree: bool = False) -> DataFrame:
    """Registrations at their workers: ``worker, cell, term`` with the payload. Cancellations, which repeat
    the whole subscription, go through the same plan."""
    return assignment.place(subs_at_cells(subs, freq, assignment.grid), by_tree)


route_cancels = route_subs


def live_map(routed_subs: DataFrame) -> DataFrame:
    """``cell, term, worker, n_live``: where a term is waited for, and by how many subscriptions."""
    return routed_subs.groupBy("cell", "term", "worker").agg(F.count(F.lit(1)).alias("n_live"))


def posted(subs: DataFrame, freq: DataFrame, grid: Grid) -> DataFrame:
    """``cell, term, n_live`` without workers: placed under an assignment it is that one's live map."""
    return subs_at_cells(subs, freq, grid).groupBy("cell", "term").agg(F.count(F.lit(1)).alias("n_live"))


def maintained(live: DataFrame, added: DataFrame, removed: DataFrame) -> DataFrame:
    """A live map after more registrations and cancellations; places without subscriptions go."""
    parts = live.select("cell", "term", "worker", "n_live")
    parts = parts.union(live_map(added)).union(live_map(removed).withColumn("n_live", -F.col("n_live")))
    return parts.groupBy("cell", "term", "worker").agg(F.sum("n_live").alias("n_live")).filter("n_live > 0")


def object_terms(objects: DataFrame, grid: Grid) -> DataFrame:
    """One row per object and distinct term, with its cell."""
    carried = [c for c in objects.columns if c not in {"cell", "term"}]
    return objects.select(*carried, grid.cell(F.col("x"), F.col("y")).alias("cell"), F.explode(F.array_distinct("terms")).alias("term"))


def route_objects(objects: DataFrame, live: DataFrame, grid: Grid) -> DataFrame:
    """Objects at the workers that wait for one of their terms in their cell: ``obj_id, worker, cell``.

    Only ids go through the exchange on (cell, term); objects without a waiting worker have no row.
    """
    probes = object_terms(objects.select("obj_id", "x", "y", "terms"), grid).select("obj_id", "cell", "term")
    return probes.join(live.select("cell", "term", "worker"), ["cell", "term"]).select("obj_id", "worker", "cell").distinct()


def send_waiting(objects: DataFrame, live: DataFrame, grid: Grid) -> DataFrame:
    """As :func:`route_objects`, with all columns of the objects. Up to ``HELD_LIVE`` rows of the live map are looked up where the
    object is; beyond, ids meet it by shuffling."""
    held = live.select("cell", "term", "worker").distinct().limit(HELD_LIVE + 1).toArrow()
    if held.num_rows > HELD_LIVE:
        return objects.join(route_objects(objects, live, grid), "obj_id")
    place = pa.concat_arrays(held["term"].chunks or [pa.array([], pa.string())]).dictionary_encode()
    key = held["cell"].to_numpy().astype(np.int64) * len(place.dictionary) + place.indices.to_numpy()
    order = np.argsort(key)
    whole = objects.sparkSession.sparkContext.broadcast((place.dictionary, key[order], held["worker"].to_numpy().astype(np.int16)[order]))
    at = objects.withColumn("cell", grid.cell(F.col("x"), F.col("y")))
    return at.mapInArrow(lambda batches: rowroute.waiting(batches, *whole.value), T.StructType([*at.schema.fields, T.StructField("worker", T.IntegerType())]))


def dispatched(objects: DataFrame, dispatchers: int) -> DataFrame:
    """Objects with the ``dispatcher`` that takes them; all dispatchers hold the same maps, so any share will do."""
    return objects.withColumn("dispatcher", F.pmod(F.col("obj_id"), F.lit(dispatchers)).cast("int"))


def sends_by_dispatcher(objects: DataFrame, routed: DataFrame, dispatchers: int) -> DataFrame:
    """``dispatcher, n_obj, sends``: objects that each dispatcher takes, and copies that it sends to workers."""
    sends = routed.select("obj_id", "worker").distinct().groupBy("obj_id").agg(F.count(F.lit(1)).alias("sends"))
    rows = dispatched(objects.select("obj_id"), dispatchers).join(sends, "obj_id", "left")
    return rows.groupBy("dispatcher").agg(F.count(F.lit(1)).alias("n_obj"), F.coalesce(F.sum("sends"), F.lit(0)).alias("sends"))


def cell_maps(live: DataFrame) -> DataFrame:
    """``cell, terms``: for each cell the map from its terms to the number of subscriptions that wait for them,
    as a dispatcher holds it."""
    entries = live.groupBy("cell", "term").agg(F.sum("n_live").alias("n"))
    return entries.groupBy("cell").agg(F.map_from_entries(F.collect_list(F.struct("term", "n"))).alias("terms"))


def route_all_objects(objects: DataFrame, assignment: Assignment) -> DataFrame:
    """Objects at every worker that is responsible for one of their terms, waited for or not: what a
    partitioner without a live map sends."""
    return send_all(objects.select("obj_id", "x", "y", "terms"), assignment).select("obj_id", "worker", "cell")


def send_all(objects: DataFrame, assignment: Assignment) -> DataFrame:
    """As :func:`route_all_objects`, with all columns of the objects; an object's workers are told where it is."""
    at = objects.withColumn("cell", assignment.grid.cell(F.col("x"), F.col("y"))).filter(F.size("terms") > 0)
    if not any(leaf.by_text for leaf in assignment.leaves):
        return assignment.place(at)
    chart = objects.sparkSession.sparkContext.broadcast(assignment.chart())
    coded = at.withColumn("codes", codes(F.col("terms")))
    return coded.mapInArrow(lambda batches: rowroute.responsible(batches, cellmatch.Chart(*chart.value)), T.StructType([*at.schema.fields, T.StructField("worker", T.IntegerType())]))


def dropped_objects(objects: DataFrame, routed: DataFrame) -> DataFrame:
    return objects.join(routed.select("obj_id").distinct(), "obj_id", "left_anti")


def replication(objects: DataFrame, routed_objects: DataFrame, subs: DataFrame, routed_subs: DataFrame) -> DataFrame:
    """``sends_per_object, copies_per_sub, dropped_share``, counting an object or subscription once per worker."""
    sends = routed_objects.select("obj_id", "worker").distinct().agg(F.count(F.lit(1)).alias("sends"), F.countDistinct("obj_id").alias("reached"))
    copies = routed_subs.select("sub_id", "worker").distinct().agg(F.count(F.lit(1)).alias("copies"))
    n, q = objects.agg(F.count(F.lit(1)).alias("n")), subs.agg(F.count(F.lit(1)).alias("q"))
    one = sends.withColumn("k", F.lit(1)).join(copies.withColumn("k", F.lit(1)), "k").join(n.withColumn("k", F.lit(1)), "k").join(q.withColumn("k", F.lit(1)), "k")
    return one.select((F.col("sends") / F.col("n")).alias("sends_per_object"), (F.col("copies") / F.col("q")).alias("copies_per_sub"), ((F.col("n") - F.col("reached")) / F.col("n")).alias("dropped_share"))
