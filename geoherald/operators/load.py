"""Load of workers and cells, balance, sizes, similarity: counted on whole tables."""

from __future__ import annotations

import time

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from geoherald.functions.geometry import Grid
from geoherald.operators import matching
from geoherald.operators.assignment import Assignment, whole_world
from geoherald.operators.sample import Costs
from geoherald.operators.tally import PARTS, distinct_ids


def worker_load(routed_objects: DataFrame, routed_regs: DataFrame, m: int, routed_cancels: DataFrame | None = None, costs: Costs = Costs()) -> DataFrame:
    """``worker, n_obj, n_reg, n_cancel, load`` for all ``m`` workers, idle ones included.

    A worker is sent an object or a request once, whatever the number of cells and terms.
    """
    spark = routed_objects.sparkSession
    count = lambda df, key, name: distinct_ids(df, ("worker",), key, parts=PARTS).select("worker", F.col("n").alias(name))
    out = spark.range(m).select(F.col("id").cast("int").alias("worker"))
    out = out.join(count(routed_objects, "obj_id", "n_obj"), "worker", "left").join(count(routed_regs, "sub_id", "n_reg"), "worker", "left")
    if routed_cancels is not None:
        out = out.join(count(routed_cancels, "sub_id", "n_cancel"), "worker", "left")
    else:
        out = out.withColumn("n_cancel", F.lit(0).cast("long"))
    out = out.select("worker", *[F.coalesce(c, F.lit(0)).alias(c) for c in ("n_obj", "n_reg", "n_cancel")])
    return out.withColumn("load", costs.check * F.col("n_obj") * F.col("n_reg") + costs.obj * F.col("n_obj") + costs.reg * F.col("n_reg") + costs.cancel * F.col("n_cancel"))


def total(loads: DataFrame) -> DataFrame:
    return loads.agg(F.sum("load").alias("total"))


def balance(loads: DataFrame) -> DataFrame:
    """``l_max, l_min, ratio``; the ratio is infinite if a worker has no load."""
    ends = loads.agg(F.max("load").alias("l_max"), F.min("load").alias("l_min"))
    return ends.withColumn("ratio", F.when(F.col("l_min") > 0, F.col("l_max") / F.col("l_min")).otherwise(F.lit(float("inf"))))


def sub_bytes(dnf: Column) -> Column:
    """Bytes of a stored subscription: six numbers of eight bytes, and each term with its length."""
    words = F.flatten(dnf)
    return (F.lit(48) + F.aggregate(F.transform(words, lambda t: F.octet_length(t) + 4), F.lit(0), lambda a, b: a + b)).cast("long")


def cell_load(routed_objects: DataFrame, index: DataFrame) -> DataFrame:
    """``worker, cell, n_obj, avg_subs, load, size_bytes``: objects times stored subscriptions, and their bytes.

    Without times of registration the subscriptions stand for the whole period.
    """
    objects = distinct_ids(routed_objects, ("worker", "cell"), "obj_id").select("worker", "cell", F.col("n").alias("n_obj"))
    stored = distinct_ids(index, ("worker", "cell"), "sub_id", sub_bytes(F.col("dnf"))).select("worker", "cell", F.col("n").alias("n_sub"), F.col("total").alias("size_bytes"))
    both = stored.join(objects, ["worker", "cell"], "full")
    both = both.select("worker", "cell", F.coalesce("n_obj", F.lit(0)).alias("n_obj"), F.coalesce("n_sub", F.lit(0)).cast("double").alias("avg_subs"), F.coalesce("size_bytes", F.lit(0)).alias("size_bytes"))
    return both.withColumn("load", F.col("n_obj") * F.col("avg_subs"))


def averaged_subs(index: DataFrame, start: int, end: int) -> DataFrame:
    """``worker, cell, avg_subs`` over the tuples ``[start, end)``: each subscription by its share of the period."""
    span = F.least(F.coalesce("cancel_seq", F.lit(end)), F.lit(end)) - F.greatest("reg_seq", F.lit(start))
    stored = index.select("worker", "cell", "sub_id", F.greatest(span, F.lit(0)).alias("span")).distinct()
    return stored.groupBy("worker", "cell").agg((F.sum("span") / F.lit(float(end - start))).alias("avg_subs"))


def check_partition(spark: SparkSession, assignment: Assignment, terms: DataFrame) -> DataFrame:
    """Pairs of cell and term that have not exactly one worker; empty for a right partition.

    All cells of a leaf place a term alike, so its first cell stands for them; that every cell lies in one
    leaf is checked too. The leaves, a number that the grid bounds, meet each term once.
    """
    assignment.check()
    firsts = [(leaf.y0 * assignment.grid.n + leaf.x0,) for leaf in assignment.leaves]
    cells = F.broadcast(spark.createDataFrame(firsts, "cell int").groupBy().agg(F.collect_list("cell").alias("cells")))
    each = terms.select("term").distinct().join(cells, F.lit(True)).select("term", F.explode("cells").alias("cell"))
    return assignment.place(each).groupBy("cell", "term").agg(F.countDistinct("worker").alias("workers"), F.count(F.lit(1)).alias("n")).filter("workers <> 1 or n <> 1")


def cosine(object_terms: DataFrame, sub_terms: DataFrame, key: str) -> DataFrame:
    """``key, sim``: per region, the cosine of the counts of terms on both sides; 0 if one side is empty."""
    o = object_terms.groupBy(key, "term").agg(F.count(F.lit(1)).alias("o"))
    q = sub_terms.groupBy(key, "term").agg(F.count(F.lit(1)).alias("q"))
    both = o.join(q, [key, "term"], "full").select(key, F.coalesce("o", F.lit(0)).alias("o"), F.coalesce("q", F.lit(0)).alias("q"))
    sums = both.groupBy(key).agg(F.sum(F.col("o") * F.col("q")).alias("oq"), F.sum(F.col("o") * F.col("o")).alias("oo"), F.sum(F.col("q") * F.col("q")).alias("qq"))
    size = F.sqrt(F.col("oo").cast("double")) * F.sqrt(F.col("qq").cast("double"))
    return sums.select(key, F.when(size > 0, F.col("oq") / size).otherwise(F.lit(0.0)).alias("sim"))


def optimal_small(units: list[tuple[frozenset, frozenset]], m: int, sigma: float, costs: Costs = Costs()) -> tuple[float, list[int]] | None:
    """The least total load of units (objects, subscriptions) on ``m`` workers within the balance, by trying all."""
    if m ** len(units) > 4**8:
        raise ValueError("too many ways")
    best = None
    for code in range(m ** len(units)):
        owners = [code // m**k % m for k in range(len(units))]
        loads = []
        for w in range(m):
            mine = [u for u, o in zip(units, owners, strict=True) if o == w]
            loads.append(costs.load(len(frozenset().union(*(u[0] for u in mine))), len(frozenset().union(*(u[1] for u in mine)))))
        if min(loads) > 0 and max(loads) / min(loads) <= sigma and (best is None or sum(loads) < best[0]):
            best = (sum(loads), owners)
    return best


def calibrate(objects: DataFrame, subs: DataFrame, grid: Grid, repeats: int = 1) -> Costs:
    """Seconds per check, object, registration and cancellation, from four timed jobs on the given rows."""
    def timed(df: DataFrame) -> tuple[float, int]:
        began = time.perf_counter()
        for _ in range(repeats):
            n = df.agg(F.count(F.lit(1))).first()[0]
        return (time.perf_counter() - began) / repeats, max(n, 1)

    parts = matching.run(objects, subs, whole_world(grid, 1))
    obj_s, n_obj = timed(parts["routed_objects"])
    reg_s, n_reg = timed(parts["index"])
    cancel_s, n_cancel = timed(subs.select("sub_id").distinct())
    check_s, n_check = timed(matching.candidates(objects, parts["routed_objects"], parts["index"], grid))
    return Costs(check_s / n_check, obj_s / n_obj, reg_s / n_reg, cancel_s / n_cancel)
