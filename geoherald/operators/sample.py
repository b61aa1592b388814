"""What a partitioner plans from: a bounded sample of objects and subscriptions, on the driver.

The sample is the rows of least key hash, so it is the same on every run; its size is a parameter.
Loads are counted on it, and only their proportions matter to a plan.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geoherald.functions.geometry import Grid
from geoherald.operators.routing import routing_terms, term_freq

OBJECTS, SUBSCRIPTIONS = 20_000, 20_000


@dataclass(frozen=True)
class Costs:
    """Of a check, an object, a registration and a cancellation."""

    check: float = 1.0
    obj: float = 1.0
    reg: float = 1.0
    cancel: float = 1.0

    def load(self, objects: float, regs: float, cancels: float = 0.0) -> float:
        return self.check * objects * regs + self.obj * objects + self.reg * regs + self.cancel * cancels


@dataclass
class Sample:
    """Objects as (column, row, terms); subscriptions as (first and last column and row, routing terms,
    all keywords)."""

    grid: Grid
    objects: list[tuple[int, int, frozenset[str]]]
    subs: list[tuple[int, int, int, int, frozenset[str], tuple[str, ...]]]
    costs: Costs = field(default_factory=Costs)

    @property
    def routed(self) -> Counter:
        """Subscriptions per routing term."""
        return Counter(t for s in self.subs for t in s[4])

    @property
    def df(self) -> Counter:
        return Counter(t for o in self.objects for t in o[2])

    def by_cell(self) -> tuple[dict[tuple[int, int], list[int]], dict[tuple[int, int], list[int]]]:
        """Numbers of the objects in each cell, and of the subscriptions over it."""
        at: dict[tuple[int, int], list[int]] = {}
        over: dict[tuple[int, int], list[int]] = {}
        for k, o in enumerate(self.objects):
            at.setdefault((o[0], o[1]), []).append(k)
        for k, q in enumerate(self.subs):
            for cx in range(q[0], q[1] + 1):
                for cy in range(q[2], q[3] + 1):
                    over.setdefault((cx, cy), []).append(k)
        return at, over


def take_sample(objects: DataFrame, subs: DataFrame, grid: Grid, freq: DataFrame | None = None, n_objects: int = OBJECTS, n_subs: int = SUBSCRIPTIONS, seed: int = 1, costs: Costs = Costs()) -> Sample:
    """The sample; ``freq`` is the routing version's frequency table."""
    freq = freq if freq is not None else term_freq(objects)
    some = objects.select("obj_id", "x", "y", "terms").orderBy(F.xxhash64(F.lit(seed), F.col("obj_id")), "obj_id").limit(n_objects)
    rows = some.select(grid.axis(F.col("x")).alias("cx"), grid.axis(F.col("y")).alias("cy"), "terms").collect()
    few = subs.orderBy(F.xxhash64(F.lit(seed), F.col("sub_id")), "sub_id").limit(n_subs)
    keys = routing_terms(few, freq).groupBy("sub_id").agg(F.collect_set("term").alias("route"))
    axis = {c: grid.axis(F.col(c)).alias(c) for c in ("x0", "x1", "y0", "y1")}
    wanted = few.join(keys, "sub_id").select("sub_id", *axis.values(), "route", F.flatten("dnf").alias("words")).orderBy("sub_id").collect()
    return Sample(grid, sorted(((r.cx, r.cy, frozenset(r.terms)) for r in rows), key=lambda o: (o[0], o[1], sorted(o[2]))), [(r.x0, r.x1, r.y0, r.y1, frozenset(r.route), tuple(r.words)) for r in wanted], costs)
