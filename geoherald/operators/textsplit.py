"""Partitioners by text only: one leaf over the whole world, its terms shared by all workers."""

from __future__ import annotations

from collections import Counter

from geoherald.operators.assignment import HEAD_TERMS, Assignment, whole_world
from geoherald.operators.node import Node, pack_terms
from geoherald.operators.sample import Sample


def _weights(sample: Sample) -> dict[str, float]:
    df, routed = sample.df, sample.routed
    return {t: df[t] * (1.0 + routed[t]) for t in df.keys() | routed.keys()}


def by_frequency(sample: Sample, m: int) -> Assignment:
    """Terms by weight (objects that have it, times one more than the subscriptions under it), each to the
    worker with the least so far."""
    loads, placed = [0.0] * m, {}
    for t, w in sorted(_weights(sample).items(), key=lambda x: (-x[1], x[0]))[:HEAD_TERMS]:
        p = min(range(m), key=lambda k: (loads[k], k))
        placed[t] = p
        loads[p] += w
    return whole_world(sample.grid, m, list(range(m)), placed, "frequency")


def by_metric(sample: Sample, m: int, slack: float = 0.15) -> Assignment:
    """Each term to where the load, by its definition, grows least."""
    placed = pack_terms(Node.root(sample), m, slack)
    return whole_world(sample.grid, m, list(range(m)), placed, "metric")


def cut_size(edges: dict[frozenset[str], int], placed: dict[str, int]) -> int:
    """Parts that each set of terms touches beyond the first, by how often the set occurs."""
    return sum(n * (len({placed[t] for t in e}) - 1) for e, n in edges.items())


def by_hypergraph(sample: Sample, m: int, eps: float = 0.2, rounds: int = 6, edge_terms: int = 64) -> Assignment:
    """Terms as vertices and objects' term sets as edges: as few parts per edge as the balance allows.

    Starts from the split by frequency; in each round terms move to the part that most reduces the cut,
    in the order of their gain and within a capacity of ``1 + eps`` shares of the weight.
    """
    weights = _weights(sample)
    head = set(sorted(weights, key=lambda t: (-weights[t], t))[:HEAD_TERMS])
    edges: Counter = Counter()
    for _, _, terms in sample.objects:
        e = terms & head
        if len(e) > edge_terms:
            e = frozenset(sorted(e, key=lambda t: (-weights[t], t))[:edge_terms])
        if len(e) > 1:
            edges[frozenset(e)] += 1
    placed = dict(by_frequency(sample, m).leaves[0].terms)
    loads = [0.0] * m
    for t, p in placed.items():
        loads[p] += weights[t]
    capacity = (1 + eps) * sum(loads) / m
    of: dict[str, list[frozenset[str]]] = {}
    for e in edges:
        for t in e:
            of.setdefault(t, []).append(e)
    before = cut_size(edges, placed)
    for _ in range(rounds):
        parts_of = {e: Counter(placed[t] for t in e) for e in edges}
        moves = []
        for t, mine in of.items():
            here, gain = placed[t], Counter()
            for e in mine:
                alone = parts_of[e][here] == 1
                for p in parts_of[e]:
                    if p != here:
                        gain[p] += edges[e]
                if not alone:
                    gain[here] += edges[e]
            if gain:
                # to leave saves a part where the term is alone, to arrive costs one where none is yet
                total = sum(edges[e] for e in mine)
                stay = gain.pop(here, 0)
                for p, shared in gain.items():
                    saved = (total - stay) - (total - shared)
                    if saved > 0:
                        moves.append((-saved, t, p))
        moved: set[str] = set()
        for _, t, p in sorted(moves):
            if t not in moved and loads[p] + weights[t] <= capacity:
                loads[placed[t]] -= weights[t]
                loads[p] += weights[t]
                placed[t] = p
                moved.add(t)
        after = cut_size(edges, placed)
        if before - after <= before // 1000:
            break
        before = after
    return whole_world(sample.grid, m, list(range(m)), placed, "hypergraph")
