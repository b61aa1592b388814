"""The studies, on the given tables: loads of the partitioners, selectors, and adjustment under drift."""

from __future__ import annotations

import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geoherald.functions.geometry import Grid
from geoherald.operators import adjust, hybrid, load, matching, migrate, routing, spacesplit
from geoherald.operators.assignment import Assignment
from geoherald.operators.measures import dispatcher_bytes, latency, latency_bands, queued, timed
from geoherald.operators.sample import Costs, take_sample
from geoherald.plans.settings import BY_SPACE, GRID, MU, PARTITIONERS, PLANNED, SMALL_GRID
from geoherald.plans.settings import WORKERS as M
from geoherald.sources.shared import settle, shared_folder
from geoherald.sources.workload import drift, subscriptions
from geoherald.sources.workload import timed as timed_mix
from geoherald.sources.world import object_source
from geoherald.streaming import engine


def _setting(spark: SparkSession, folder: str, group: str, world: str = "wide", live: int | None = None, all_rare: bool = False):
    objects = settle(object_source(spark, folder, world), "objects")
    subs = subscriptions(spark, folder, group, world, all_rare=all_rare, objects=objects)
    if live is not None:
        subs = subs.orderBy("sub_id").limit(live)
    subs = settle(subs, "subs")
    grid = GRID if world == "wide" else SMALL_GRID
    freq = settle(routing.term_freq(objects), "freq")
    return objects, subs, grid, freq, take_sample(objects, subs, grid, freq, PLANNED, PLANNED)


@dataclass
class Laid:
    """What an assignment is measured on, laid down once for all: ``keyed`` the subscriptions by cell and term,
    ``posted`` the lengths of the lists, ``reached`` for each object the terms that somebody waits for."""

    objects: DataFrame
    grid: Grid
    n_objects: int
    n_subs: int
    keyed: DataFrame
    posted: DataFrame
    reached: DataFrame

    @classmethod
    def of(cls, objects: DataFrame, subs: DataFrame, freq: DataFrame, grid: Grid) -> "Laid":
        keyed = settle(routing.subs_at_cells(subs, freq, grid).select("cell", "term", "sub_id", load.sub_bytes(F.col("dnf")).alias("bytes")), "keyed")
        posted = settle(keyed.groupBy("cell", "term").agg(F.count(F.lit(1)).alias("n_live")), "posted")
        probes = routing.object_terms(objects.select("obj_id", "x", "y", "terms"), grid).select("obj_id", "cell", "term")
        reached = probes.join(posted.select("cell", "term"), ["cell", "term"]).groupBy("obj_id", "cell").agg(F.collect_list("term").alias("terms"))
        return cls(objects, grid, objects.count(), subs.count(), keyed, posted, settle(reached, "reached"))


def measured(laid: Laid, assignment: Assignment, drop_unmatched: bool, costs: Costs = Costs()) -> dict[str, float]:
    """Total load, balance, replication and memory of an assignment, counted on all rows: a worker gets an object
    or a subscription once."""
    probes = laid.reached.select("obj_id", "cell", F.explode("terms").alias("term")) if drop_unmatched else routing.object_terms(laid.objects.select("obj_id", "x", "y", "terms"), laid.grid).select("obj_id", "cell", "term")
    sent = assignment.place(probes).select("worker", "obj_id").distinct().groupBy("worker").agg(F.count(F.lit(1)).alias("n")).collect()
    stored = assignment.place(laid.keyed).groupBy("worker", "sub_id").agg(F.max("bytes").alias("bytes"), F.sum(F.octet_length("term") + 16).alias("entries"))
    stored = stored.groupBy("worker").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("bytes") + F.col("entries")).alias("bytes")).collect()
    n_obj, n_reg = {r.worker: r.n for r in sent}, {r.worker: r.n for r in stored}
    loads = [costs.load(n_obj.get(w, 0), n_reg.get(w, 0)) for w in range(assignment.m)]
    top, low = max(loads), min(loads)
    dispatcher = dispatcher_bytes(laid.posted, assignment.head_terms(laid.objects.sparkSession)).first()["bytes"]
    rate = (laid.n_objects + laid.n_subs) / top if top else 0.0
    share = lambda n, of: n / of if of else 0.0
    return {"total": sum(loads), "ratio": top / low if low > 0 else float("inf"), "top": top, "tuples_per_load": rate, "sends": share(sum(n_obj.values()), laid.n_objects), "copies": share(sum(n_reg.values()), laid.n_subs), "dispatcher_bytes": float(dispatcher), "worker_bytes": sum(r.bytes for r in stored) / assignment.m}


MEASURES = ("total", "ratio", "top", "tuples_per_load", "sends", "copies", "dispatcher_bytes", "worker_bytes")


def loads_by_partitioner(spark: SparkSession, folder: str, groups: tuple[str, ...] = ("Q1",), m: int = M, live: int | None = None, all_rare: bool = False, world: str = "wide") -> DataFrame:
    """One row per group and partitioner with all measures. Partitioners of space send every object; the
    others, and ``drop`` for those of space, only what somebody waits for."""
    rows = []
    for group in groups:
        objects, subs, grid, freq, sample = _setting(spark, folder, group, world, live, all_rare)
        laid = Laid.of(objects, subs, freq, grid)
        for name, builder in PARTITIONERS.items():
            assignment = builder(sample, m)
            for drop in (True, False) if name in BY_SPACE else (True,):
                got = measured(laid, assignment, drop)
                rows.append((group, name, drop, m, *[float(got[k] or 0.0) for k in MEASURES]))
    return spark.createDataFrame(rows, "group string, partitioner string, drop boolean, m int, " + ", ".join(f"{k} double" for k in MEASURES))


def scalability(spark: SparkSession, folder: str, group: str = "Q3", ms: tuple[int, ...] = (4, 8, 16)) -> DataFrame:
    """Load of the most loaded worker by the number of workers, on the small world."""
    rows = []
    objects, subs, grid, freq, sample = _setting(spark, folder, group, "small")
    laid = Laid.of(objects, subs, freq, grid)
    for m in ms:
        for name in ("hybrid", "metric", "kdtree"):
            got = measured(laid, PARTITIONERS[name](sample, m), name != "kdtree")
            rows.append((m, name, got["top"], got["total"]))
    return spark.createDataFrame(rows, "m int, partitioner string, top double, total double")


def migration_study(spark: SparkSession, folder: str, lives: tuple[int | None, ...] = (None,)) -> DataFrame:
    """Every selector on the cells of the most loaded of the grid's workers: seconds, bytes and cells moved.

    A number in ``lives`` takes so many subscriptions, None all; ``live`` of the result is how many there were.
    The exact one counts sizes in KiB, rounded up, and is left out where its table would be too large.
    """
    rows = []
    for live in lives:
        objects, subs, grid, freq, sample = _setting(spark, folder, "Q1", live=live)
        live = subs.count()
        assignment = spacesplit.by_grid(sample, M)
        parts = matching.run(objects, subs, assignment, freq)
        index, routed = settle(parts["index"], "index"), settle(parts["routed_objects"], "routed")
        loads = {r.worker: r.load for r in load.worker_load(routed, index, M).collect()}
        donor, receiver = max(loads, key=loads.get), min(loads, key=loads.get)
        cells = [migrate.Cell(r.cell, r.load, r.size_bytes) for r in load.cell_load(routed, index).filter(F.col("worker") == donor).collect()]
        tau = sum(c.load for c in cells) / 4
        for name, selector in migrate.SELECTORS.items():
            units = [migrate.Cell(c.id, c.load, -(-c.size // 1024)) for c in cells] if name == "exact_dp" else cells
            try:
                seconds, choice = timed(lambda s=selector, u=units: s(u, tau))
            except MemoryError:
                rows.append((live, name, None, None, None, None))
                continue
            chosen = set(choice.cells)
            moved = sum(c.size for c in cells if c.id in chosen)
            move_s, _ = timed(lambda ids=choice.cells: settle(adjust.apply(index, ids, donor, receiver), "moved"))
            rows.append((live, name, seconds, moved, len(chosen), move_s))
    return spark.createDataFrame(rows, "live int, selector string, select_s double, bytes long, cells int, move_s double")


def drift_study(spark: SparkSession, folder: str, epochs: int | None = None, share_of_ten: int = 1) -> DataFrame:
    """Q3 whose regions turn style epoch by epoch, with and without local adjustment: total load and the most
    loaded worker's, counted on all rows, and the bytes moved. All epochs, or the first ``epochs`` of them.

    Plans and adjustments are made on samples of ``PLANNED`` objects and subscriptions.
    """
    objects, _, grid, freq, sample = _setting(spark, folder, "Q3")
    all_subs = settle(subscriptions(spark, folder, "Q3", flips=drift(MU, share_of_ten), objects=objects), "drifting")
    fixed = moving = hybrid.build(sample, M)
    rows = []
    number = F.floor(F.col("sub_id") / MU).cast("int")
    for epoch in sorted(r.epoch for r in all_subs.select(number.alias("epoch")).distinct().collect())[:epochs]:
        now = all_subs.filter(number == epoch)
        seen = take_sample(objects, now, grid, freq, PLANNED, PLANNED)
        loads = adjust.modelled_loads(seen, moving)
        donor, receiver = loads.index(max(loads)), loads.index(min(loads))
        moved = 0
        if loads[receiver] == 0 or loads[donor] / loads[receiver] > 1.5:
            moving, _ = adjust.phase_one(seen, moving, donor, receiver, 8)
            loads = adjust.modelled_loads(seen, moving)
            parts = matching.run(objects, now, moving, freq)
            cells, counted = load.cell_load(parts["routed_objects"], parts["index"]), settle(load.worker_load(parts["routed_objects"], parts["index"], M), "loads")
            uneven = adjust.detect(counted, 1.5)
            share = adjust.share_to_move(counted, uneven[0], uneven[1], 1.5) if uneven else 0.0
            if share > 0:
                moving, choice = adjust.phase_two(cells, moving, uneven[0], uneven[1], share)
                moved = choice.size
        for name, assignment in (("fixed", fixed), ("adjusted", moving)):
            parts = matching.run(objects, now, assignment, freq)
            after = [r.load for r in load.worker_load(parts["routed_objects"], parts["index"], M).collect()]
            rows.append((epoch, name, float(sum(after)), float(max(after)), moved if name == "adjusted" else 0))
    return spark.createDataFrame(rows, "epoch int, routing string, total double, top double, bytes long")


def sample_study(spark: SparkSession, folder: str, group: str = "Q3", sizes: tuple[int, ...] = (500, PLANNED)) -> DataFrame:
    """The hybrid partition planned on samples of growing size, its loads counted on all rows: what planning on a
    sample costs."""
    objects, subs, grid, freq, _ = _setting(spark, folder, group)
    laid = Laid.of(objects, subs, freq, grid)
    rows = []
    for size in sizes:
        got = measured(laid, hybrid.build(take_sample(objects, subs, grid, freq, size, size), M), True)
        rows.append((size, got["total"], got["top"], got["ratio"]))
    return spark.createDataFrame(rows, "sample int, total double, top double, ratio double")


def served(objects: DataFrame, posted: DataFrame, assignment: Assignment, drop_unmatched: bool, check_ms: float, object_ms: float) -> DataFrame:
    """``worker, seq, service``: what each tuple costs its workers, by the entries of the lists that it goes through.

    The lists' lengths (``posted``: :func:`routing.posted`) give that number; no entry is looked at.
    """
    probes = routing.object_terms(objects.select("obj_id", "seq", "x", "y", "terms"), assignment.grid).select("obj_id", "seq", "cell", "term")
    lists = posted.select("cell", "term", "n_live")
    if drop_unmatched:
        sent = probes.join(assignment.place(lists), ["cell", "term"])
    else:
        sent = assignment.place(probes).join(lists, ["cell", "term"], "left")
    checks = sent.groupBy("worker", "obj_id", "seq").agg(F.coalesce(F.sum("n_live"), F.lit(0)).alias("checks"))
    return checks.select("worker", "seq", (F.lit(object_ms) + F.col("checks") * check_ms).alias("service"))


def latency_study(spark: SparkSession, folder: str, group: str = "Q2", check_ms: float = 0.02, object_ms: float = 1.0, gap_ms: float = 1.0) -> DataFrame:
    """Mean delay and bands of the three best partitioners: each worker serves its tuples one at a time, in the
    time that their checks take; a tuple comes every ``gap_ms``."""
    objects, subs, grid, freq, sample = _setting(spark, folder, group)
    objects = settle(objects.withColumn("seq", F.col("obj_id")), "placed")
    posted = settle(routing.posted(subs, freq, grid), "posted")
    rows = []
    for name in ("hybrid", "metric", "kdtree"):
        tuples = served(objects, posted, PARTITIONERS[name](sample, M), name not in BY_SPACE, check_ms, object_ms).withColumn("arrive_ms", F.col("seq") * F.lit(gap_ms))
        delays = settle(queued(tuples, F.col("service")), "delays")
        bands, mean = latency_bands(delays).first(), delays.agg(F.avg("ms")).first()[0]
        rows.append((group, name, mean, bands["prompt"], bands["delayed"], bands["late"]))
    return spark.createDataFrame(rows, "group string, partitioner string, mean_ms double, prompt double, delayed double, late double")


def migration_delays(spark: SparkSession, folder: str, bytes_per_ms: float = 50.0) -> DataFrame:
    """Delays while cells move, by selector: at half of the stream donor and receiver stop for as long as the chosen
    cells' bytes take."""
    objects, subs, grid, freq, sample = _setting(spark, folder, "Q1")
    objects = settle(objects.withColumn("seq", F.col("obj_id")), "placed")
    assignment = spacesplit.by_grid(sample, M)
    parts = matching.run(objects, subs, assignment, freq)
    loads = {r.worker: r.load for r in load.worker_load(parts["routed_objects"], parts["index"], M).collect()}
    donor, receiver = max(loads, key=loads.get), min(loads, key=loads.get)
    rows = [migrate.Cell(r.cell, r.load, r.size_bytes) for r in load.cell_load(parts["routed_objects"], parts["index"]).filter(F.col("worker") == donor).collect()]
    tau, half = sum(c.load for c in rows) / 4, (objects.agg(F.max("seq")).first()[0] or 0) // 2
    tuples = settle(served(objects, routing.posted(subs, freq, grid), assignment, False, 0.002, 0.2).withColumn("arrive_ms", F.col("seq") * F.lit(1.0)), "served")
    out = []
    for name, selector in migrate.SELECTORS.items():
        cells = [migrate.Cell(c.id, c.load, -(-c.size // 1024)) for c in rows] if name == "exact_dp" else rows
        try:
            chosen = set(selector(cells, tau).cells)
        except MemoryError:
            out.append((name, None, None, None, None))
            continue
        moved = sum(c.size for c in rows if c.id in chosen)
        pause = spark.createDataFrame([(w, half, moved / bytes_per_ms, float(half), True) for w in {donor, receiver}], "worker int, seq long, service double, arrive_ms double, pause boolean")
        delays = queued(tuples.withColumn("pause", F.lit(False)).unionByName(pause), F.col("service")).filter("not pause")
        bands = latency_bands(delays).first()
        out.append((name, moved, bands["prompt"], bands["delayed"], bands["late"]))
    return spark.createDataFrame(out, "selector string, bytes long, prompt double, delayed double, late double")


def stream_study(spark: SparkSession, folder: str, slices: int = 4, sigma: float = 1.5, methods: tuple[str, ...] = ("ratio_greedy",)) -> DataFrame:
    """The timed stream of Q3 replayed with no adjustment and with each selector: per run the tuples per unit of the
    most loaded worker's time, summed over batches, moves and bytes, mean milliseconds of a batch and of an object until its delivery, late objects."""
    objects, subs, grid, freq, _ = _setting(spark, folder, "Q3")
    timed_subs, timed_objects = timed_mix(subs, objects, MU)
    timed_objects, timed_subs = settle(timed_objects, "timed-objects"), settle(timed_subs, "timed-subs")
    assignment = PARTITIONERS["hybrid"](take_sample(timed_objects, timed_subs.filter("reg_seq < 0"), grid, freq, PLANNED, PLANNED), M)
    tuples = settle(engine.as_tuples(timed_objects, timed_subs), "tuples")
    rows = []
    for method in ("none", *methods):
        place = f"{shared_folder(spark)}/study-{uuid.uuid4().hex}"
        engine.write_slices(tuples, f"{place}/tuples", slices)
        hook = engine.Adjuster(sigma, method, active=method != "none")
        state = engine.Replay(spark, assignment, freq, place, hook)
        progress = engine.replay(engine.source(spark, f"{place}/tuples"), state, f"{place}/checkpoint")
        rate = sum(t["tuples"] for t in hook.tops) / sum(t["top"] for t in hook.tops)
        rows.append((method, float(rate), len(hook.moves), sum(m["bytes"] for m in hook.moves), float(latency(progress)), float(state.wait_ms()), state.late_objects()))
    return spark.createDataFrame(rows, "selector string, tuples_per_load double, moves int, bytes long, batch_ms double, wait_ms double, late long")
