"""The hybrid partitioner: space or text, region by region.

First the world is cut at medians as long as that separates regions where objects and subscriptions talk
about different things; such regions are cut by text, the others by whatever makes the smaller load.
The number of pieces per region comes from a dynamic program. Pieces are packed into workers, and the
heaviest is cut again while the workers are out of balance.
"""

from __future__ import annotations

from dataclasses import dataclass

from geoherald.operators.assignment import Assignment, Leaf
from geoherald.operators.node import Node
from geoherald.operators.numparts import allocate
from geoherald.operators.pack import pack_nodes, packed_loads, relabel
from geoherald.operators.sample import Sample


@dataclass(frozen=True)
class HybridParams:
    """``delta``: similarity from which a region is left to space. ``eps``: gain in dissimilarity under
    which it is cut no further. ``theta``: most leaves, per worker. ``stop`` is ``prose`` (no smaller
    similarity in a child) or ``absolute`` (none that differs)."""

    delta: float = 0.5
    sigma: float = 1.5
    theta: int = 8
    eps: float = 0.01
    max_depth: int = 8
    min_objects: int = 16
    stop: str = "prose"
    seed: int = 1
    model: str = "definition"


def classify(sample: Sample, params: HybridParams) -> list[Node]:
    """Regions with their kinds. All regions of one depth are looked at together; a region's verdict
    depends on its own contents only."""
    frontier, done = [Node.root(sample)], []
    for depth in range(params.max_depth + 1):
        following = []
        for node in frontier:
            node.sim = node.similarity()
            if node.sim >= params.delta:
                node.kind = "space"
                done.append(node)
                continue
            cut = best_split(node) if depth < params.max_depth and len(node.objects) >= params.min_objects else None
            if cut is None or _stop(node.sim, cut[0], params):
                node.kind = "text"
                done.append(node)
            else:
                following += cut[1]
        frontier = following
        if not frontier:
            break
    return done


def best_split(node: Node) -> tuple[float, tuple[Node, Node]] | None:
    """Of the two median cuts the one with the least similar child, and that similarity."""
    options = []
    for axis in ("x", "y"):
        pair = node.median_cut(axis)
        if pair:
            options.append((min(pair[0].similarity(), pair[1].similarity()), pair))
    return min(options, key=lambda o: o[0]) if options else None


def _stop(sim: float, child: float, params: HybridParams) -> bool:
    return abs(child - sim) <= params.eps if params.stop == "absolute" else sim - child <= params.eps


def cut_node(node: Node, parts: int) -> list[Node] | None:
    """A node in ``parts`` pieces: by text if that is its kind, else by text or space, whichever is lighter."""
    if parts == 1:
        return [node]
    text = node.text_cut(parts)
    space = node.space_cut(parts) if node.kind != "text" or node.terms is None else None
    if node.kind == "text" and text:
        return text
    options = [o for o in (space, text) if o]
    return min(options, key=lambda o: sum(n.load for n in o)) if options else None


def trial_costs(nodes: list[Node], k_max: int) -> list[list[float]]:
    """Loads of the nodes in 1, 2, ... pieces; a row ends where a node can't be cut further."""
    table = []
    for node in nodes:
        row = [node.load]
        for k in range(2, k_max + 1):
            pieces = cut_node(node, k)
            if pieces is None:
                break
            row.append(sum(p.load for p in pieces))
        table.append(row)
    return table


def build(sample: Sample, m: int, params: HybridParams = HybridParams()) -> Assignment:
    """The assignment; ``feasible`` says whether the balance asked for was reached."""
    costs = sample.costs
    nodes = classify(sample, params)
    if len(nodes) < m:
        table = trial_costs(nodes, m - len(nodes) + 1)
        wanted = min(m, sum(map(len, table)))
        pieces = []
        for family, (node, parts) in enumerate(zip(nodes, allocate(table, wanted), strict=True)):
            for piece in cut_node(node, parts):
                piece.family = family
                pieces.append(piece)
        nodes = pieces
    for k, node in enumerate(nodes):
        node.family = node.family if node.family >= 0 else 10_000 + k
    owners = pack_nodes(nodes, m, costs, params.model)
    best = _ratio(packed_loads(nodes, owners, m, costs))
    kept = (nodes, owners, best)
    while best > params.sigma and len(nodes) < params.theta * m:
        open_nodes = sorted((n for n in nodes if not n.frozen), key=lambda n: -n.load)
        if not open_nodes:
            break
        heavy = open_nodes[0]
        pieces = cut_node(heavy, 2)
        if pieces is None:
            heavy.frozen = True
            continue
        nodes = [n for n in nodes if n is not heavy] + pieces
        owners = pack_nodes(nodes, m, costs, params.model)
        best = _ratio(packed_loads(nodes, owners, m, costs))
        if best < kept[2]:
            kept = (nodes, owners, best)
    nodes, owners, best = kept
    return Assignment(sample.grid, m, _leaves(nodes, relabel(owners, m, params.seed)), "hybrid", feasible=best <= params.sigma)


def _ratio(loads: list[float]) -> float:
    return max(loads) / min(loads) if min(loads) > 0 else float("inf")


def _leaves(nodes: list[Node], owners: list[int]) -> list[Leaf]:
    """Pieces over the same cells become one leaf with several workers.

    Text pieces of one region may have been cut by space afterwards, differently for each; the common
    refinement of their borders is taken then.
    """
    groups: dict[object, list[int]] = {}
    for k, n in enumerate(nodes):
        groups.setdefault(("t", n.family) if n.terms is not None else ("s", k), []).append(k)
    leaves = []
    for members in groups.values():
        xs = sorted({v for k in members for v in (nodes[k].x0, nodes[k].x1)})
        ys = sorted({v for k in members for v in (nodes[k].y0, nodes[k].y1)})
        for x0, x1 in zip(xs, xs[1:], strict=False):
            for y0, y1 in zip(ys, ys[1:], strict=False):
                here = [k for k in members if nodes[k].x0 <= x0 and nodes[k].x1 >= x1 and nodes[k].y0 <= y0 and nodes[k].y1 >= y1]
                if here:
                    terms = {t: p for p, k in enumerate(here) for t in nodes[k].terms or ()} if len(here) > 1 else {}
                    leaves.append(Leaf(x0, y0, x1, y1, [owners[k] for k in here], terms, sum(nodes[k].load for k in here)))
    return leaves
