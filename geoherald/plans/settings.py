"""Numbers and partitioners that the queries and the studies share."""

from __future__ import annotations

from collections.abc import Callable

from geoherald.functions.geometry import Grid
from geoherald.operators import hybrid, spacesplit, textsplit
from geoherald.operators.assignment import Assignment
from geoherald.operators.sample import Sample
from geoherald.plans.oracles import MU
from geoherald.sources.world import SMALL_SIDE, WIDE_SIDE

GRID = Grid(WIDE_SIDE, 6)
SMALL_GRID = Grid(SMALL_SIDE, 6)
WORKERS = 8
#: Rows of the planner's sample.
PLANNED = 4000

PARTITIONERS: dict[str, Callable[[Sample, int], Assignment]] = {
    "hybrid": hybrid.build,
    "grid": spacesplit.by_grid,
    "kdtree": spacesplit.by_kdtree,
    "rtree": spacesplit.by_rtree,
    "frequency": textsplit.by_frequency,
    "hypergraph": textsplit.by_hypergraph,
    "metric": textsplit.by_metric,
}
BY_SPACE = ("grid", "kdtree", "rtree")

__all__ = ["BY_SPACE", "GRID", "MU", "PARTITIONERS", "PLANNED", "SMALL_GRID", "WORKERS"]
