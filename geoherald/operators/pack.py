"""Putting pieces of load together for workers."""

from __future__ import annotations

import random

from geoherald.operators.node import Node
from geoherald.operators.sample import Costs


def pack_nodes(nodes: list[Node], m: int, costs: Costs = Costs(), model: str = "definition") -> list[int]:
    """A worker for each node, heaviest node first.

    ``definition``: a worker's load is that of all that it gets, an object or a subscription in two of
    its nodes counting once, so pieces that share them attract each other. ``sum``: loads add up. The
    worker whose load grows least takes a node unless that makes the balance worse; then the least
    loaded worker does.
    """
    objects: list[set[int]] = [set() for _ in range(m)]
    subs: list[set[int]] = [set() for _ in range(m)]
    loads = [0.0] * m
    out = [0] * len(nodes)

    def factor(values: list[float]) -> float:
        return max(values) / min(values) if min(values) > 0 else float("inf")

    for k in sorted(range(len(nodes)), key=lambda k: (-nodes[k].load, k)):
        node = nodes[k]
        reached = set(node.reached()) if model == "definition" else set()
        grown = []
        for w in range(m):
            if model == "definition":
                grown.append(costs.load(len(objects[w] | reached), len(subs[w].union(node.subs))))
            else:
                grown.append(loads[w] + node.load)
        choice = min(range(m), key=lambda w: (grown[w] - loads[w], loads[w], w))
        now = factor(loads)
        after = factor([grown[w] if w == choice else loads[w] for w in range(m)])
        worse = after > now or (now == float("inf") and loads[choice] > 0)
        if worse:
            choice = min(range(m), key=lambda w: (loads[w], grown[w], w))
        out[k] = choice
        objects[choice] |= reached
        subs[choice].update(node.subs)
        loads[choice] = grown[choice]
    return out


def packed_loads(nodes: list[Node], owners: list[int], m: int, costs: Costs) -> list[float]:
    """Loads of the workers by the definition."""
    out = []
    for w in range(m):
        mine = [n for n, o in zip(nodes, owners, strict=True) if o == w]
        out.append(costs.load(len({o for n in mine for o in n.reached()}), len({q for n in mine for q in n.subs})))
    return out


def relabel(owners: list[int], m: int, seed: int) -> list[int]:
    """The same parts with workers in random order."""
    order = list(range(m))
    random.Random(seed).shuffle(order)
    return [order[w] for w in owners]
