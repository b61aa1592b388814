"""Partitioners by space only: a grid, a kd-tree and the leaves of an R-tree."""

from __future__ import annotations

from math import ceil, sqrt

from geoherald.operators.assignment import Assignment, Leaf
from geoherald.operators.node import Node
from geoherald.operators.pack import pack_nodes
from geoherald.operators.sample import Sample


def by_grid(sample: Sample, m: int) -> Assignment:
    """Every cell of the grid by itself, packed by load."""
    root = Node.root(sample)
    at: dict[tuple[int, int], list[int]] = {}
    for k in root.objects:
        at.setdefault(sample.objects[k][:2], []).append(k)
    over: dict[tuple[int, int], list[int]] = {}
    for q, s in enumerate(sample.subs):
        for cx in range(s[0], s[1] + 1):
            for cy in range(s[2], s[3] + 1):
                over.setdefault((cx, cy), []).append(q)
    n = sample.grid.n
    cells = [Node(sample, cx, cy, cx + 1, cy + 1, at.get((cx, cy), []), over.get((cx, cy), []), "space") for cy in range(n) for cx in range(n)]
    busy = [c for c in cells if c.objects or c.subs]
    owners = dict(zip(((c.x0, c.y0) for c in busy), pack_nodes(busy, m, sample.costs, "sum"), strict=True))
    leaves = [Leaf(c.x0, c.y0, c.x1, c.y1, [owners.get((c.x0, c.y0), (c.x0 + c.y0) % m)], {}, c.load if (c.x0, c.y0) in owners else 0.0) for c in cells]
    return Assignment(sample.grid, m, leaves, "grid")


def by_kdtree(sample: Sample, m: int) -> Assignment:
    """``m`` leaves; the heaviest is halved at its median, along its longer side."""
    leaves = [Node.root(sample)]
    while len(leaves) < m:
        for leaf in sorted(leaves, key=lambda n: (-n.load, n.x0, n.y0)):
            first = "x" if leaf.x1 - leaf.x0 >= leaf.y1 - leaf.y0 else "y"
            pair = leaf.median_cut(first) or leaf.median_cut("y" if first == "x" else "x")
            if pair:
                leaves.remove(leaf)
                leaves += pair
                break
        else:
            break
    return Assignment(sample.grid, m, [Leaf(n.x0, n.y0, n.x1, n.y1, [k], {}, n.load) for k, n in enumerate(leaves)], "kdtree")


def by_rtree(sample: Sample, m: int, leaf_capacity: int | None = None) -> Assignment:
    """Leaves by sorting into slabs and tiling each; their tiles, on cell borders, are packed by load."""
    n_objects = max(len(sample.objects), 1)
    capacity = leaf_capacity or max(1, n_objects // (8 * m))
    slabs = ceil(sqrt(n_objects / capacity))
    n, tiles = sample.grid.n, []

    def borders(values: list[int], parts: int) -> list[int]:
        values = sorted(values)
        cuts = {values[len(values) * k // parts] for k in range(1, parts)} if values else set()
        return [0, *sorted(c for c in cuts if 0 < c < n), n]

    root = Node.root(sample)
    xs = borders([o[0] for o in sample.objects], slabs)
    for x0, x1 in zip(xs, xs[1:], strict=False):
        slab = root.within(x0, 0, x1, n)
        ys = borders([sample.objects[k][1] for k in slab.objects], max(1, ceil(len(slab.objects) / capacity)))
        tiles += [slab.within(x0, y0, x1, y1) for y0, y1 in zip(ys, ys[1:], strict=False)]
    owners = pack_nodes(tiles, m, sample.costs, "sum")
    return Assignment(sample.grid, m, [Leaf(t.x0, t.y0, t.x1, t.y1, [w], {}, t.load) for t, w in zip(tiles, owners, strict=True)], "rtree")
