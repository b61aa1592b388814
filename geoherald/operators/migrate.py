"""Which cells to move: load of at least ``tau`` at the least size.

Four selectors. A cell is (id, load, size). ``feasible`` is False if all cells together are not enough; all
of them are chosen then. Equal choices go by id.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Entries that the table of the exact selector may have.
MAX_TABLE = 200_000_000


@dataclass(frozen=True)
class Cell:
    id: int
    load: float
    size: int


@dataclass(frozen=True)
class Choice:
    cells: tuple[int, ...]
    size: int
    load: float
    feasible: bool = True


def _choice(cells: list[Cell], tau: float) -> Choice:
    load = sum(c.load for c in cells)
    return Choice(tuple(sorted(c.id for c in cells)), sum(c.size for c in cells), load, load >= tau)


def ratio_greedy(cells: list[Cell], tau: float) -> Choice:
    """Cells by size per load. One that leaves the sum under ``tau`` is kept; one that would reach it
    closes a candidate with all kept so far. The cheapest candidate wins."""
    order = sorted(cells, key=lambda c: (c.size / c.load if c.load > 0 else float("inf"), c.id))
    kept: list[Cell] = []
    load = size = 0
    best: list[Cell] | None = None
    cheapest = float("inf")
    for c in order:
        if load + c.load < tau:
            kept.append(c)
            load, size = load + c.load, size + c.size
        elif size + c.size < cheapest:
            cheapest, best = size + c.size, [*kept, c]
    return _choice(best if best is not None else kept, tau)


def largest_first(cells: list[Cell], tau: float) -> Choice:
    """Cells by size, largest first, until ``tau`` is reached."""
    return _until(sorted(cells, key=lambda c: (-c.size, c.id)), tau)


def random_pick(cells: list[Cell], tau: float, seed: int = 1) -> Choice:
    """Cells in an order without regard to load or size, until ``tau`` is reached: by multiples of the id modulo
    a prime, which any engine can follow."""
    return _until(sorted(cells, key=lambda c: ((c.id * 48271 + seed * 7919) % 65537, c.id)), tau)


def _until(order: list[Cell], tau: float) -> Choice:
    taken, load = [], 0.0
    for c in order:
        if load >= tau:
            break
        taken.append(c)
        load += c.load
    return _choice(taken, tau)


def exact_dp(cells: list[Cell], tau: float, bound: int | None = None) -> Choice:
    """The least size, by the most load that fits each size up to a bound (that of :func:`ratio_greedy`).

    Raises MemoryError where the table would be larger than ``MAX_TABLE``.
    """
    greedy = ratio_greedy(cells, tau)
    if not greedy.feasible:
        return greedy
    bound = greedy.size if bound is None else bound
    cells = sorted(cells, key=lambda c: c.id)
    if len(cells) * (bound + 1) > MAX_TABLE:
        raise MemoryError(f"{len(cells)} cells by {bound + 1} sizes")
    most = np.zeros(bound + 1)
    taken = np.zeros((len(cells), bound + 1), dtype=bool)
    for k, c in enumerate(cells):
        if c.size > bound:
            continue
        moved = np.full(bound + 1, -np.inf)
        moved[c.size :] = most[: bound + 1 - c.size] + c.load
        taken[k] = moved > most
        most = np.maximum(most, moved)
    reached = np.flatnonzero(most >= tau)
    if not len(reached):
        return greedy
    j, out = int(reached[0]), []
    for k in range(len(cells) - 1, -1, -1):
        if taken[k, j]:
            out.append(cells[k])
            j -= cells[k].size
    return _choice(out, tau)


SELECTORS = {"exact_dp": exact_dp, "ratio_greedy": ratio_greedy, "largest_first": largest_first, "random_pick": random_pick}


def select(cells: DataFrame, tau: float, method: str) -> Choice:
    """Cells of one worker (``cell, load, size_bytes``; at most one row per cell of the grid) to a choice."""
    rows = [Cell(r.cell, float(r.load), int(r.size_bytes)) for r in cells.select("cell", "load", "size_bytes").collect()]
    return SELECTORS[method](rows, tau)


def prefix_selected(cells: DataFrame, tau: float, order: list) -> DataFrame:
    """Selection until ``tau`` as a table: a cell is taken if those before it stay under ``tau``. One worker's
    cells, a number that the grid bounds."""
    before = F.coalesce(F.sum("load").over(Window.partitionBy("worker").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    return cells.withColumn("before", before).filter(F.col("before") < tau).drop("before")
