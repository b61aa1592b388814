"""Load adjustment while the stream runs: locally between two workers, globally by a new partition."""

from __future__ import annotations

from copy import deepcopy
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geoherald.operators import hybrid
from geoherald.operators.assignment import Assignment, Leaf, part_of
from geoherald.operators.matching import build_index, matched
from geoherald.operators.migrate import Choice, select
from geoherald.operators.node import Node, pack_terms
from geoherald.operators.routing import live_map, route_objects, route_subs
from geoherald.operators.sample import Costs, Sample


def detect(loads: DataFrame, sigma: float) -> tuple[int, int, float, float] | None:
    """Most and least loaded worker with their loads if the balance is broken, else None."""
    rows = sorted(((r.load, r.worker) for r in loads.select("worker", "load").collect()), key=lambda x: (-x[0], x[1]))
    high, low = rows[0], rows[-1]
    if low[0] > 0 and high[0] / low[0] <= sigma or high[0] == 0:
        return None
    return high[1], low[1], high[0], low[0]


def target(high: float, low: float, sigma: float, half: bool = False) -> float:
    """Load to move: the least that restores the balance of the two, or half their difference."""
    return max(0.0, (high - low) / 2 if half else (high - sigma * low) / (1 + sigma))


def share_to_move(loads: DataFrame, donor: int, receiver: int, sigma: float, costs: Costs = Costs()) -> float:
    """The least part of the donor's objects and subscriptions whose move restores the balance of the two.

    A worker's objects meet all of its subscriptions, so its load falls with the square of what goes. 0 if
    no part leaves the more loaded of the two better off than the donor was.
    """
    rows = {r.worker: r for r in loads.filter(F.col("worker").isin(donor, receiver)).collect()}
    high, low = rows[donor], rows[receiver]
    after = lambda s: (costs.load((1 - s) * high.n_obj, (1 - s) * high.n_reg), costs.load(low.n_obj + s * high.n_obj, low.n_reg + s * high.n_reg))
    for step in range(1, 101):
        left, more = after(step / 200)
        if left <= sigma * more:
            return step / 200 if max(left, more) < high.load else 0.0
    return 0.0


def by_cells(assignment: Assignment) -> Assignment:
    """The same assignment with one leaf per cell, so that single cells can change hands."""
    out = deepcopy(assignment)
    out.leaves = [Leaf(cx, cy, cx + 1, cy + 1, list(leaf.workers), leaf.terms) for leaf in assignment.leaves for cy in range(leaf.y0, leaf.y1) for cx in range(leaf.x0, leaf.x1)]
    return out


@dataclass
class Move:
    """What an adjustment did: cells moved, their bytes, and the steps of the first phase."""

    cells: tuple[int, ...]
    size: int
    load: float
    steps: list[str]


def phase_one(sample: Sample, assignment: Assignment, donor: int, receiver: int, p: int) -> tuple[Assignment, list[str]]:
    """On the ``p`` heaviest cells of the donor: cut one by text, moving the smaller half, or give a part
    to its twin on the receiver.

    A change stays if it lowers the load of the two together, by the definition, on the sample; each is
    judged with what the changes before it left.
    """
    out, steps = by_cells(assignment), []
    root = Node.root(sample)
    at, over = sample.by_cell()
    weight = lambda leaf: len(at.get((leaf.x0, leaf.y0), ())) * len(over.get((leaf.x0, leaf.y0), ()))
    mine = sorted((k for k, leaf in enumerate(out.leaves) if donor in leaf.workers), key=lambda k: (-weight(out.leaves[k]), k))[:p]

    def together() -> float:
        loads = modelled_loads(sample, out)
        return loads[donor] + loads[receiver]

    before = together()
    for k in mine:
        leaf = out.leaves[k]
        if weight(leaf) == 0:
            break
        kept = Leaf(leaf.x0, leaf.y0, leaf.x1, leaf.y1, list(leaf.workers), leaf.terms, leaf.load)
        if leaf.by_text and receiver in leaf.workers:
            leaf.workers = [receiver if w == donor else w for w in leaf.workers]
            step = "merge"
        elif not leaf.by_text:
            halves = root.within(leaf.x0, leaf.y0, leaf.x1, leaf.y1).text_cut(2, pack_terms)
            if halves is None:
                continue
            size = [sum(len(t) for q in h.subs for t in sample.subs[q][5]) + 48 * len(h.subs) for h in halves]
            small = 0 if size[0] <= size[1] else 1
            leaf.terms = {t: int(t in halves[small].terms) for h in halves for t in h.terms}
            leaf.workers = [donor, receiver]
            step = "split"
        else:
            continue
        after = together()
        if after < before:
            before = after
            steps.append(f"{step} cell {leaf.y0 * out.grid.n + leaf.x0}")
        else:
            out.leaves[k] = kept
    return out, steps


def phase_two(cells: DataFrame, assignment: Assignment, donor: int, receiver: int, share: float, method: str = "ratio_greedy") -> tuple[Assignment, Choice]:
    """Cells of the donor (``worker, cell, load, size_bytes``) chosen by a selector go to the receiver.

    ``share`` is the part of the donor's load to move. Loads of cells add up to less than that of their
    worker, whose objects meet all of its subscriptions by the definition, so the part is taken of their sum.
    """
    mine = cells.filter(F.col("worker") == donor)
    whole = mine.agg(F.sum("load")).first()[0] or 0.0
    choice = select(mine, share * whole, method)
    out, chosen = by_cells(assignment), set(choice.cells)
    for leaf in out.leaves:
        if leaf.y0 * out.grid.n + leaf.x0 in chosen:
            leaf.workers = [receiver if w == donor else w for w in leaf.workers]
    out.version = assignment.version + 1
    return out, choice


def apply(index: DataFrame, cells: tuple[int, ...], donor: int, receiver: int) -> DataFrame:
    """The posting lists after a move: only rows of the moved cells change."""
    moved = F.col("cell").isin(*cells) & (F.col("worker") == donor) if cells else F.lit(False)
    return index.withColumn("worker", F.when(moved, F.lit(receiver)).otherwise(F.col("worker")))


def needs_repartition(sample: Sample, current: Assignment, m: int, gain: float = 0.1, params: hybrid.HybridParams = hybrid.HybridParams()) -> Assignment | None:
    """A new partition of the sample if its total load is lower by more than ``gain``, else None."""
    fresh = hybrid.build(sample, m, params)
    fresh.version = current.version + 1
    return fresh if modelled(sample, fresh) < (1 - gain) * modelled(sample, current) else None


def modelled(sample: Sample, assignment: Assignment) -> float:
    """Total load of an assignment on a sample, a worker's objects and subscriptions counting once."""
    return sum(modelled_loads(sample, assignment))


def modelled_loads(sample: Sample, assignment: Assignment) -> list[float]:
    """Loads of the workers on a sample, as the routing grid would send it: cell by cell."""
    objects: list[set[int]] = [set() for _ in range(assignment.m)]
    subs: list[set[int]] = [set() for _ in range(assignment.m)]
    at, over = sample.by_cell()
    for leaf in assignment.leaves:
        parts = len(leaf.workers)
        for cell in ((cx, cy) for cy in range(leaf.y0, leaf.y1) for cx in range(leaf.x0, leaf.x1)):
            owner = {}
            for q in over.get(cell, ()):
                for t in sample.subs[q][4]:
                    worker = leaf.workers[(leaf.terms[t] if t in leaf.terms else part_of(t, parts)) if parts > 1 else 0]
                    owner[t] = worker
                    subs[worker].add(q)
            for o in at.get(cell, ()) if owner else ():
                for t in sample.objects[o][2]:
                    if t in owner:
                        objects[owner[t]].add(o)
    return [sample.costs.load(len(o), len(q)) for o, q in zip(objects, subs, strict=True)]


@dataclass
class DualRouting:
    """Two versions side by side: subscriptions registered before ``cut_seq`` under the old one, later ones
    under the new, objects probing both."""

    old: Assignment
    new: Assignment
    cut_seq: int
    freq: DataFrame

    def index(self, subs: DataFrame) -> DataFrame:
        before = route_subs(subs.filter(F.col("reg_seq") < self.cut_seq), self.old, self.freq)
        after = route_subs(subs.filter(F.col("reg_seq") >= self.cut_seq), self.new, self.freq)
        return build_index(before).unionByName(build_index(after))

    def run(self, objects: DataFrame, subs: DataFrame) -> DataFrame:
        index = self.index(subs)
        routed = route_objects(objects, live_map(index), self.old.grid)
        return matched(objects, subs, routed, index, self.old.grid)

    def retire(self, subs: DataFrame, at_seq: int, threshold: int) -> "DualRouting":
        """Once at most ``threshold`` old subscriptions stand, they move over and the old version ends."""
        standing = subs.filter((F.col("reg_seq") < self.cut_seq) & (F.col("cancel_seq").isNull() | (F.col("cancel_seq") > at_seq)))
        if standing.count() > threshold:
            return self
        return DualRouting(self.new, self.new, self.cut_seq, self.freq)
