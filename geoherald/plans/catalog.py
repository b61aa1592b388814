"""Queries over the given tables for every method, baseline, measure and operator."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from geoherald.functions.geometry import Grid
from geoherald.operators import adjust, load, matching, migrate, routing, spacesplit
from geoherald.operators.assignment import Assignment, whole_world
from geoherald.operators.measures import latency_bands, queued
from geoherald.operators.sample import take_sample
from geoherald.plans import experiments, oracles, surface
from geoherald.plans.settings import BY_SPACE, GRID, MU, PARTITIONERS, PLANNED, SMALL_GRID, WORKERS
from geoherald.sources.shared import settle, settle_parts, shared_folder
from geoherald.sources.tables import read_table
from geoherald.sources.workload import TEXTS, drift, subscription_parts, subscriptions, timed, tuple_mix
from geoherald.sources.world import lexicon, object_source, ranked, wide_objects
from geoherald.streaming import engine

Query = Callable[[SparkSession, str], DataFrame]
def workload(spark: SparkSession, folder: str, group: str, world: str = "wide", spare: tuple[str, ...] = ()) -> tuple[DataFrame, DataFrame]:
    """Objects and subscriptions of a group, written once, without the columns that are ``spare``."""
    objects = settle(object_source(spark, folder, world).drop(*spare), "objects")
    return objects, settle_parts(subscription_parts(spark, folder, group, world, objects=objects, spare=spare, texts_at_once=TEXTS), "subs")


def matchable(spark: SparkSession, folder: str, group: str, world: str = "wide") -> tuple[DataFrame, DataFrame]:
    """The workload without what no matcher looks at."""
    return workload(spark, folder, group, world, ("ts", "owner"))


def planned(name: str, objects: DataFrame, subs: DataFrame, grid: Grid, m: int = WORKERS) -> tuple[Assignment, DataFrame]:
    freq = settle(routing.term_freq(objects), "freq")
    sample = take_sample(objects, subs, grid, freq, PLANNED, PLANNED)
    return PARTITIONERS[name](sample, m), freq


def match_by(name: str, group: str, world: str = "wide") -> Query:
    def query(spark: SparkSession, folder: str) -> DataFrame:
        objects, subs = matchable(spark, folder, group, world)
        grid = GRID if world == "wide" else SMALL_GRID
        assignment, freq = planned(name, objects, subs, grid)
        # the text baselines have no destination for terms that nobody waits for; those of space send all
        return matching.run(objects, subs, assignment, freq, drop_unmatched=name not in BY_SPACE)["matches"]

    return query


def match_bruteforce(spark: SparkSession, folder: str) -> DataFrame:
    """Every pair is looked at; few enough subscriptions for that."""
    objects, subs = workload(spark, folder, "Q1")
    return matching.match_nested_loop(objects, subs)


def match_single(spark: SparkSession, folder: str) -> DataFrame:
    objects, subs = workload(spark, folder, "Q1")
    return matching.match_single(objects, subs, GRID)


def match_fast(group: str) -> Query:
    def query(spark: SparkSession, folder: str) -> DataFrame:
        objects, subs = matchable(spark, folder, group)
        return matching.match_fast(objects, subs, GRID)

    return query


def match_inverted_only(spark: SparkSession, folder: str) -> DataFrame:
    return matching.match_inverted_only(*workload(spark, folder, "Q1"))


def match_grid_only(spark: SparkSession, folder: str) -> DataFrame:
    return matching.match_grid_only(*workload(spark, folder, "Q1"), GRID)


def _timed(spark: SparkSession, folder: str, group: str = "Q1") -> tuple[DataFrame, DataFrame]:
    objects, subs = workload(spark, folder, group)
    timed_subs, timed_objects = timed(subs, objects, MU)
    return settle(timed_objects, "timed-objects"), settle(timed_subs, "timed-subs")


def match_after_cancel(spark: SparkSession, folder: str) -> DataFrame:
    """Registrations and cancellations in between the objects."""
    objects, subs = _timed(spark, folder)
    assignment, freq = planned("hybrid", objects, subs, GRID)
    return matching.run(objects, subs, assignment, freq)["matches"]


def match_dual_routing(spark: SparkSession, folder: str) -> DataFrame:
    """Old subscriptions under a kd-tree, later ones under the hybrid partition, objects under both."""
    objects, subs = _timed(spark, folder)
    old, freq = planned("kdtree", objects, subs, GRID)
    new, _ = planned("hybrid", objects, subs, GRID)
    return adjust.DualRouting(old, new, 6000, freq).run(objects, subs)


def match_after_migration(spark: SparkSession, folder: str) -> DataFrame:
    """Cells of the most loaded worker go to the least loaded one; what is delivered must not change. The posting lists
    after the move are planned, not written: they are made row by row, and a table of them is larger than the subscriptions."""
    objects, subs = matchable(spark, folder, "Q1")
    assignment, freq = planned("grid", objects, subs, GRID)
    parts = matching.run(objects, subs, assignment, freq)
    loads = load.worker_load(parts["routed_objects"], parts["routed_subs"], WORKERS)
    found = adjust.detect(loads, 1.05)
    if found is None:
        return parts["matches"]
    donor, receiver, high, low = found
    cells = load.cell_load(parts["routed_objects"], parts["index"])
    moved, choice = adjust.phase_two(cells, assignment, donor, receiver, adjust.target(high, low, 1.05) / high)
    index = adjust.apply(parts["index"], choice.cells, donor, receiver)
    routed = routing.send_waiting(objects, routing.live_map(index), GRID)
    return matching.matched(objects, subs, routed, index, GRID, freq=freq)


def match_phase_one(spark: SparkSession, folder: str) -> DataFrame:
    """After cells of the most loaded worker were cut by text between it and another."""
    objects, subs = matchable(spark, folder, "Q1")
    freq = settle(routing.term_freq(objects), "freq")
    sample = take_sample(objects, subs, GRID, freq, PLANNED, PLANNED)
    assignment = spacesplit.by_kdtree(sample, WORKERS)
    loads = adjust.modelled_loads(sample, assignment)
    donor, receiver = loads.index(max(loads)), loads.index(min(loads))
    changed, _ = adjust.phase_one(sample, assignment, donor, receiver, 16)
    return matching.run(objects, subs, changed, freq)["matches"]


def match_stream_replay(spark: SparkSession, folder: str) -> DataFrame:
    """The timed workload as a stream of three micro-batches."""
    objects, subs = _timed(spark, folder)
    assignment, freq = planned("hybrid", objects, subs, GRID)
    place = f"{shared_folder(spark)}/replay-{uuid.uuid4().hex}"
    engine.write_slices(settle(engine.as_tuples(objects, subs), "tuples"), f"{place}/tuples", 3)
    state = engine.Replay(spark, assignment, freq, place)
    engine.replay(engine.source(spark, f"{place}/tuples"), state, f"{place}/checkpoint")
    return state.matches()


def match_stream_adjusted(spark: SparkSession, folder: str) -> DataFrame:
    """The timed workload in six micro-batches; cells change hands between them, which must not change what is found."""
    objects, subs = _timed(spark, folder)
    assignment, freq = planned("kdtree", objects, subs, GRID)
    place = f"{shared_folder(spark)}/adjusted-{uuid.uuid4().hex}"
    engine.write_slices(settle(engine.as_tuples(objects, subs), "tuples"), f"{place}/tuples", 6)
    state = engine.Replay(spark, assignment, freq, place, engine.Adjuster(1.1))
    engine.replay(engine.source(spark, f"{place}/tuples"), state, f"{place}/checkpoint")
    return state.matches()


def match_tree_routing(spark: SparkSession, folder: str) -> DataFrame:
    """Subscriptions find their workers by the leaves' rectangles instead of the routing grid."""
    objects, subs = workload(spark, folder, "Q3")
    assignment, freq = planned("hybrid", objects, subs, GRID)
    index = matching.build_index(routing.route_subs(subs, assignment, freq, by_tree=True))
    routed = routing.route_objects(objects, routing.live_map(index), GRID)
    return matching.matched(objects, subs, routed, index, GRID)


def partition_check(name: str) -> Query:
    """Terms that a partition gives to no or several workers somewhere; there must be none."""

    def query(spark: SparkSession, folder: str) -> DataFrame:
        objects, subs = workload(spark, folder, "Q3")
        assignment, freq = planned(name, objects, subs, GRID)
        return load.check_partition(spark, assignment, freq).select("cell", "term")

    return query


def match_lazy_deletion(spark: SparkSession, folder: str) -> DataFrame:
    """Tombstones for every third subscription, with a purge of the touched lists on the way."""
    objects, subs = workload(spark, folder, "Q1")
    parts = matching.run(objects, subs, whole_world(GRID, 1))
    dead = matching.cancel(None, subs.filter("sub_id % 3 = 0"))
    touched = routing.object_terms(objects.select("obj_id", "x", "y", "terms"), GRID).select("cell", "term")
    index, dead = matching.purge(parts["index"], dead, touched)
    return matching.matched(objects, subs, parts["routed_objects"], settle(index, "index"), GRID, dead)


def simple_queries() -> dict[str, Query]:
    wide = lambda s, d: wide_objects(s, d)
    single = lambda s, d: matching.run(*workload(s, d, "Q1"), whole_world(GRID, 1))

    def lex(s, d):
        return ranked(lexicon(settle(wide(s, d), "objects")))

    def top(s, d):
        table = settle(lex(s, d), "lexicon")
        return table.filter(F.col("rk") * 100 <= table.agg(F.count(F.lit(1))).first()[0])

    def live_counts(s, d):
        objects, subs = _timed(s, d)
        last = objects.agg(F.max("seq")).first()[0]
        steps = subs.select(F.col("reg_seq").alias("seq"), F.lit(1).alias("step")).union(subs.filter(F.col("cancel_seq") <= last).select("cancel_seq", F.lit(-1)))
        # several cancellations can fall on one place
        return running_sum(steps.groupBy("seq").agg(F.sum("step").alias("step")), "seq", "step", "live")

    def dropped(s, d):
        objects, subs = workload(s, d, "Q1")
        return routing.dropped_objects(objects, matching.run(objects, subs, whole_world(GRID, 1))["routed_objects"]).select("obj_id")

    def replication(s, d):
        objects, subs = workload(s, d, "Q1")
        parts = matching.run(objects, subs, whole_world(GRID, 1))
        return routing.replication(objects, parts["routed_objects"], subs, parts["routed_subs"])

    def cosine(s, d):
        objects, subs = workload(s, d, "Q1")
        axis = lambda v: F.least(F.lit(9), F.floor(v / 419431))
        middle = lambda a, b: F.greatest(F.lit(0), F.floor((F.col(a) + F.col(b)) / 2))
        ot = objects.select((axis(F.col("x")) + 10 * axis(F.col("y"))).alias("g"), F.explode("terms").alias("term"))
        st = subs.select((axis(middle("x0", "x1")) + 10 * axis(middle("y0", "y1"))).alias("g"), F.explode(F.flatten("dnf")).alias("term"))
        return load.cosine(ot, st, "g").withColumn("sim", F.round("sim", 6))

    def windows(s, d, slide=None):
        rows = wide(s, d).withColumn("ts", F.col("ts").cast("timestamp"))
        frame = F.window("ts", "4 hours", slide) if slide else F.window("ts", "4 hours")
        return rows.groupBy(frame).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")

    def sessions(s, d):
        rows = read_table(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
        return rows.groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), "n")

    def asof(s, d):
        left = read_table(s, d, "events").select("event_id", F.col("user_id").alias("owner"), (F.col("event_id") % 43200).alias("minute"))
        right = read_table(s, d, "orders").select(F.col("o_custkey").alias("owner"), (F.col("o_orderkey") % 43200).alias("minute"), "o_orderkey")
        found = asof_join(left, right, "owner", "minute", "o_orderkey")
        return found.select("event_id", F.col("owner").alias("user_id"), "o_orderkey")

    def delivered(s, d):
        objects, subs = workload(s, d, "Q1")
        return matching.match_fast(objects, subs, GRID).join(subs.select("sub_id", "owner"), "sub_id")

    def rollup(s, d):
        homes = read_table(s, d, "customer").join(F.broadcast(read_table(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_nationkey", "n_regionkey")
        rows = delivered(s, d).join(homes, F.col("owner") == F.col("c_custkey"))
        return rows.rollup("n_regionkey", "n_nationkey").agg(F.count(F.lit(1)).alias("n"), F.grouping_id("n_regionkey", "n_nationkey").cast("long").alias("level"))

    def cube(s, d):
        objects, subs = _timed(s, d)
        # seq % 12 of either engine has the sign of seq
        return tuple_mix(subs, objects).select("op", (F.col("seq") % 12).alias("slot")).cube("op", "slot").agg(F.count(F.lit(1)).alias("n"))

    def tiles(s, d):
        cells = wide(s, d).groupBy(GRID.axis(F.col("x")).alias("cx"), GRID.axis(F.col("y")).alias("cy")).agg(F.count(F.lit(1)).alias("n"))
        # at most one row per cell of the grid
        slabs = cells.withColumn("slab", F.ntile(8).over(Window.orderBy("cx", "cy")))
        return slabs.withColumn("tile", F.ntile(8).over(Window.partitionBy("slab").orderBy("cy", "cx"))).select("slab", "tile", "cx", "cy", "n")

    def json_props(s, d):
        k = F.get_json_object("props", "$.k").cast("long")
        return read_table(s, d, "events").groupBy("event_type").agg(F.sum(k).alias("k"), F.count(F.lit(1)).alias("n"))

    def top3(s, d):
        objects, subs = workload(s, d, "Q1")
        # counted before the owner is known, so that no pair meets the owners
        n = matching.match_fast(objects, subs, GRID).groupBy("sub_id").agg(F.count(F.lit(1)).alias("n"))
        n = n.join(subs.select("sub_id", "owner"), "sub_id").select("owner", "sub_id", "n")
        return n.withColumn("r", F.row_number().over(Window.partitionBy("owner").orderBy(F.desc("n"), "sub_id"))).filter("r <= 3").withColumn("r", F.col("r").cast("long"))

    def trailing(s, d):
        micros = F.unix_micros(F.col("ts").cast("timestamp"))
        rows = read_table(s, d, "events").select("event_id", "user_id", micros.alias("at"))
        per = Window.partitionBy("user_id").orderBy("at")
        gap = F.col("at") - F.lag("at").over(Window.partitionBy("user_id").orderBy("at", "event_id"))
        return rows.select("event_id", F.count(F.lit(1)).over(per.rangeBetween(-14400000000, 0)).alias("n"), gap.alias("gap"))

    def pivot(s, d):
        rows = read_table(s, d, "events")
        kinds = rows.groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1)))
        return kinds.join(rows.groupBy("user_id").agg(F.count(F.lit(1)).alias("n")), "user_id").select("user_id", *[F.coalesce(c, F.lit(0)).alias(c) for c in ("click", "view")], "n")

    def dispatchers(s, d):
        objects, subs = workload(s, d, "Q1")
        return routing.sends_by_dispatcher(objects, matching.run(objects, subs, whole_world(GRID, 1))["routed_objects"], 4)

    def cell_maps(s, d):
        held = routing.cell_maps(single(s, d)["live"])
        return held.select("cell", F.size("terms").cast("long").alias("n_terms"), F.aggregate(F.map_values("terms"), F.lit(0).cast("long"), lambda a, b: a + b).alias("n_live"))

    def deliveries(s, d):
        return delivered(s, d).select(F.to_json(F.struct("owner", "sub_id", "obj_id")).alias("delivery"))

    def cancelled(s, d):
        """Where cancellations go: the cells and terms of their registrations."""
        objects, subs = _timed(s, d)
        last = objects.agg(F.max("seq")).first()[0]
        return routing.route_cancels(subs.filter(F.col("cancel_seq") <= last), whole_world(GRID, 1), routing.term_freq(objects)).select("sub_id", "cell", "term")

    def time_weighted(s, d):
        """Subscriptions that stand in each cell on average over the stream, in thousandths."""
        objects, subs = _timed(s, d)
        parts = matching.run(objects, subs, whole_world(GRID, 1))
        last = objects.agg(F.max("seq")).first()[0]
        return load.averaged_subs(parts["index"], 0, last).select("cell", F.round(F.col("avg_subs") * 1000).cast("long").alias("thousandths"))

    return {
        "dispatcher_sends": dispatchers,
        "routing_cell_maps": cell_maps,
        "owner_deliveries": deliveries,
        "routed_cancels": cancelled,
        "averaged_cell_subs": time_weighted,
        "subs_small_q1": lambda s, d: subscriptions(s, d, "Q1", "small"),
        "subs_small_q2": lambda s, d: subscriptions(s, d, "Q2", "small"),
        "product_lexicon": lambda s, d: lexicon(object_source(s, d, "product")),
        "conversation_terms": lambda s, d: object_source(s, d, "conversations"),
        "wide_objects": lambda s, d: wide(s, d).select("obj_id", "x", "y", "terms"),
        "small_objects": lambda s, d: object_source(s, d, "small"),
        "lexicon": lex,
        "top1pct_terms": top,
        "subs_q1": lambda s, d: subscriptions(s, d, "Q1"),
        "subs_q2": lambda s, d: subscriptions(s, d, "Q2"),
        "subs_q2_rare": lambda s, d: subscriptions(s, d, "Q2", all_rare=True),
        "subs_q3": lambda s, d: subscriptions(s, d, "Q3"),
        "subs_small_q3": lambda s, d: subscriptions(s, d, "Q3", "small"),
        "subs_q3_drift": lambda s, d: subscriptions(s, d, "Q3", flips=drift(MU)),
        "tuple_mix": lambda s, d: tuple_mix(*reversed(_timed(s, d))),
        "live_counts": live_counts,
        "grid_histogram": lambda s, d: wide(s, d).groupBy(GRID.cell(F.col("x"), F.col("y")).alias("cell")).agg(F.count(F.lit(1)).alias("n")),
        "routed_objects": lambda s, d: single(s, d)["routed_objects"].select("obj_id", "cell"),
        "dropped_objects": dropped,
        "postings_per_cell": lambda s, d: single(s, d)["index"].groupBy("cell", "term").agg(F.count(F.lit(1)).alias("n")),
        "cell_load": lambda s, d: load.cell_load((p := single(s, d))["routed_objects"], p["index"]).drop("worker"),
        "single_worker_load": lambda s, d: load.worker_load((p := single(s, d))["routed_objects"], p["routed_subs"], 1),
        "replication": replication,
        "cosine_regions": cosine,
        "load_per_window": windows,
        "sliding_load": lambda s, d: windows(s, d, "1 hour"),
        "session_users": sessions,
        "asof_registration": asof,
        "rollup_matches": rollup,
        "cube_ops": cube,
        "ntile_tiles": tiles,
        "json_props": json_props,
        "owner_top3": top3,
        "trailing_activity": trailing,
        "pivot_types": pivot,
        "page_terms": lambda s, d: object_source(s, d, "pages"),
    }


def running_sum(rows: DataFrame, order: str, value: str, name: str) -> DataFrame:
    """Running sum over a unique order, range by range: sums of whole ranges are added up first, so no
    task sees all rows."""
    parted = settle(rows.repartitionByRange(order).withColumn("part", F.spark_partition_id()), "ranges")
    sums = parted.groupBy("part").agg(F.sum(value).alias("whole"))
    starts = sums.select("part", F.coalesce(F.sum("whole").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("start"))
    local = F.sum(value).over(Window.partitionBy("part").orderBy(order))
    return parted.withColumn("local", local).join(F.broadcast(starts), "part").select(order, (F.col("start") + F.col("local")).alias(name))


def asof_join(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """Left rows with the value of the last right row of their key at or before them; of equal ones the largest.

    Both sides are put in one order per key and the last value seen is carried on: one exchange, no pairs.
    """
    a = left.withColumn("__side", F.lit(1)).withColumn(value, F.lit(None).cast(right.schema[value].dataType))
    b = right.select(key, at, value).withColumn("__side", F.lit(0))
    both = a.unionByName(b, allowMissingColumns=True)
    seen = Window.partitionBy(key).orderBy(at, "__side", F.col(value).asc_nulls_last()).rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(value, F.last(value, ignorenulls=True).over(seen)).filter("__side = 1").drop("__side")


def _loaded_cells(spark: SparkSession, folder: str) -> tuple[list[migrate.Cell], float]:
    """All cells of one worker that have a load, at most one for each of the grid, and a third of their load."""
    parts = matching.run(*workload(spark, folder, "Q1"), whole_world(GRID, 1))
    rows = load.cell_load(parts["routed_objects"], parts["index"]).filter("load > 0").collect()
    cells = [migrate.Cell(r.cell, r.load, r.size_bytes) for r in rows]
    return cells, float(sum(c.load for c in cells) // 3)


def select_by(method: str) -> Query:
    def query(spark: SparkSession, folder: str) -> DataFrame:
        cells, tau = _loaded_cells(spark, folder)
        if method == "exact_dp":  # its table has a column per unit of size
            cells = [migrate.Cell(c.id, c.load, -(-c.size // 1024)) for c in cells]
        choice = migrate.SELECTORS[method](cells, tau)
        if method == "largest_first":
            return spark.createDataFrame([(c.id, c.load, c.size) for c in cells if c.id in choice.cells], "cell int, load double, size long")
        return spark.createDataFrame([(choice.size,)], "size long")

    return query


def select_random(spark: SparkSession, folder: str) -> DataFrame:
    cells, tau = _loaded_cells(spark, folder)
    choice = migrate.random_pick(cells, tau)
    return spark.createDataFrame([(c,) for c in choice.cells], "cell int")


def tree_hybrid(spark: SparkSession, folder: str) -> DataFrame:
    objects, subs = workload(spark, folder, "Q3")
    assignment, _ = planned("hybrid", objects, subs, GRID)
    return assignment.describe(spark)


def delays(spark: SparkSession, folder: str) -> DataFrame:
    """Shares of tuples by delay at workers of fixed service times, under the kd-tree, by worker."""
    objects, subs = _timed(spark, folder)
    assignment, freq = planned("kdtree", objects, subs, GRID)
    parts = matching.run(objects, subs, assignment, freq)
    tuples = parts["routed_objects"].join(objects.select("obj_id", "seq"), "obj_id").select("worker", "seq", (F.col("seq") * 2.0).alias("arrive_ms")).distinct()
    return latency_bands(queued(tuples, F.lit(9.0)), by=("worker",))


def queries() -> dict[str, Query]:
    found: dict[str, Query] = simple_queries() | surface.queries()
    for name in PARTITIONERS:
        for group in ("Q1", "Q2", "Q3"):
            found[f"match_{name}_{group.lower()}"] = match_by(name, group)
    found |= {f"partition_check_{name}": partition_check(name) for name in PARTITIONERS}
    found |= {
        "match_hybrid_small_q3": match_by("hybrid", "Q3", "small"),
        "match_bruteforce": match_bruteforce,
        "match_single": match_single,
        "match_fast_q1": match_fast("Q1"),
        "match_fast_q2": match_fast("Q2"),
        "match_fast_q3": match_fast("Q3"),
        "match_inverted_only": match_inverted_only,
        "match_grid_only": match_grid_only,
        "match_after_cancel": match_after_cancel,
        "match_dual_routing": match_dual_routing,
        "match_after_migration": match_after_migration,
        "match_phase_one": match_phase_one,
        "match_stream_replay": match_stream_replay,
        "match_lazy_deletion": match_lazy_deletion,
        "match_stream_adjusted": match_stream_adjusted,
        "match_tree_routing": match_tree_routing,
        "select_exact_dp": select_by("exact_dp"),
        "select_ratio_greedy": select_by("ratio_greedy"),
        "select_largest_first": select_by("largest_first"),
        "select_random": select_random,
        "tree_hybrid": tree_hybrid,
        "delays_kdtree": delays,
        "loads_by_partitioner": experiments.loads_by_partitioner,
        "loads_by_partitioner_q2": lambda s, d: experiments.loads_by_partitioner(s, d, ("Q2",)),
        "loads_by_partitioner_q3": lambda s, d: experiments.loads_by_partitioner(s, d, ("Q3",)),
        "sample_study": experiments.sample_study,
        "latency_study": experiments.latency_study,
        "migration_delays": experiments.migration_delays,
        "stream_study": experiments.stream_study,
        "migration_study": experiments.migration_study,
        "drift_study": experiments.drift_study,
        "scalability_small": experiments.scalability,
    }
    return found


def oracle_sql() -> dict[str, str]:
    found = oracles.simple() | oracles.selections() | surface.oracle_sql()
    for name in PARTITIONERS:
        for group in ("Q1", "Q2", "Q3"):
            found[f"match_{name}_{group.lower()}"] = oracles.match(group)
    q1 = oracles.match("Q1")
    found |= {n: q1 for n in ("match_bruteforce", "match_single", "match_fast_q1", "match_inverted_only", "match_grid_only", "match_after_migration", "match_phase_one")}
    found |= {"match_fast_q2": oracles.match("Q2"), "match_fast_q3": oracles.match("Q3"), "match_hybrid_small_q3": oracles.match("Q3", "small")}
    found |= {n: oracles.match_timed() for n in ("match_after_cancel", "match_dual_routing", "match_stream_replay", "match_stream_adjusted")}
    found["match_tree_routing"] = oracles.match("Q3")
    found |= {f"partition_check_{name}": "select 0 as cell, '' as term where false" for name in PARTITIONERS}
    found["match_lazy_deletion"] = q1.replace("select sub_id, obj_id from pairs", "select sub_id, obj_id from pairs where sub_id % 3 <> 0")
    return found
