"""A node of a partitioner's tree: a rectangle of cells with what lies in it, and its trial splits."""

from __future__ import annotations

from bisect import bisect_left
from collections import Counter
from dataclasses import dataclass, field
from math import sqrt

from geoherald.operators.assignment import HEAD_TERMS
from geoherald.operators.sample import Sample


@dataclass
class Node:
    """Rectangle ``[x0, x1)`` by ``[y0, y1)``; ``part`` restricts it to some terms, ``rest`` holding those
    of the other parts (a term in none belongs to part 0)."""

    sample: Sample
    x0: int
    y0: int
    x1: int
    y1: int
    objects: list[int]
    subs: list[int]
    kind: str = "open"
    terms: frozenset[str] | None = None
    family: int = -1
    frozen: bool = False
    sim: float = 0.0
    _load: float | None = field(default=None, repr=False)

    @classmethod
    def root(cls, sample: Sample) -> "Node":
        n = sample.grid.n
        return cls(sample, 0, 0, n, n, list(range(len(sample.objects))), list(range(len(sample.subs))))

    @property
    def single_cell(self) -> bool:
        return self.x1 - self.x0 == 1 and self.y1 - self.y0 == 1

    @property
    def load(self) -> float:
        if self._load is None:
            self._load = self.sample.costs.load(len(self.reached()), len(self.subs))
        return self._load

    def live(self) -> frozenset[str]:
        """Routing terms of its subscriptions, within its terms."""
        found = {t for s in self.subs for t in self.sample.subs[s][4]}
        return frozenset(found if self.terms is None else found & self.terms)

    def reached(self) -> list[int]:
        """Objects that a dispatcher would send here: those with a live term."""
        live = self.live()
        return [o for o in self.objects if not live.isdisjoint(self.sample.objects[o][2])]

    def within(self, x0: int, y0: int, x1: int, y1: int) -> "Node":
        s = self.sample
        objects = [o for o in self.objects if x0 <= s.objects[o][0] < x1 and y0 <= s.objects[o][1] < y1]
        subs = [q for q in self.subs if s.subs[q][0] < x1 and s.subs[q][1] >= x0 and s.subs[q][2] < y1 and s.subs[q][3] >= y0]
        return Node(s, x0, y0, x1, y1, objects, subs, self.kind, self.terms, self.family)

    def median_cut(self, axis: str) -> tuple["Node", "Node"] | None:
        """Two halves at the median of its objects, on a border of cells; None where there is no border."""
        low, high = (self.x0, self.x1) if axis == "x" else (self.y0, self.y1)
        if high - low < 2:
            return None
        k = 0 if axis == "x" else 1
        at = sorted(self.sample.objects[o][k] for o in self.objects)
        middle = at[len(at) // 2] if at else (low + high) // 2
        # the border nearer to halves
        cut = max(low + 1, min(high - 1, middle))
        if at and cut + 1 < high and abs(2 * bisect_left(at, cut + 1) - len(at)) < abs(2 * bisect_left(at, cut) - len(at)):
            cut += 1
        if axis == "x":
            return self.within(low, self.y0, cut, self.y1), self.within(cut, self.y0, high, self.y1)
        return self.within(self.x0, low, self.x1, cut), self.within(self.x0, cut, self.x1, high)

    def similarity(self) -> float:
        """Cosine between how often terms occur in its objects and in its subscriptions; 0 if one is empty."""
        o = Counter(t for k in self.objects for t in self.sample.objects[k][2])
        q = Counter(t for k in self.subs for t in self.sample.subs[k][5])
        if self.terms is not None:
            o = Counter({t: n for t, n in o.items() if t in self.terms})
            q = Counter({t: n for t, n in q.items() if t in self.terms})
        dot = sum(n * o[t] for t, n in q.items() if t in o)
        return dot / (sqrt(sum(n * n for n in o.values())) * sqrt(sum(n * n for n in q.values()))) if o and q else 0.0

    def text_cut(self, parts: int, pack=None) -> list["Node"] | None:
        """Nodes over the same cells that share its live terms; None if it has fewer terms than parts."""
        live = self.live()
        if len(live) < parts:
            return None
        placed = (pack or pack_terms)(self, parts)
        groups = [frozenset(t for t, p in placed.items() if p == k) for k in range(parts)]
        out = []
        for g in groups:
            subs = [q for q in self.subs if not g.isdisjoint(self.sample.subs[q][4])]
            out.append(Node(self.sample, self.x0, self.y0, self.x1, self.y1, self.objects, subs, "text", g, self.family))
        return out

    def space_cut(self, parts: int) -> list["Node"] | None:
        """Halves of the heaviest piece, again and again; the direction with the smaller sum of loads."""
        pieces = [self]
        while len(pieces) < parts:
            for piece in sorted(pieces, key=lambda p: (-p.load, p.x0, p.y0)):
                cuts = [c for c in (piece.median_cut("x"), piece.median_cut("y")) if c]
                if cuts:
                    best = min(cuts, key=lambda c: c[0].load + c[1].load)
                    pieces.remove(piece)
                    pieces += best
                    break
            else:
                return None
        return pieces


def pack_terms(node: Node, parts: int, slack: float = 0.15) -> dict[str, int]:
    """Live terms of a node to parts, heaviest first, each to where the load grows least.

    The growth counts the objects that the part has not yet, so that terms of the same objects attract
    each other; a part over its share by more than ``slack`` is left out while another is not.
    """
    sample, costs = node.sample, node.sample.costs
    routed = Counter(t for q in node.subs for t in sample.subs[q][4])
    has: dict[str, list[int]] = {}
    for o in node.objects:
        for t in sample.objects[o][2]:
            if t in routed:
                has.setdefault(t, []).append(o)
    live = sorted(node.live(), key=lambda t: (-(len(has.get(t, ())) * routed[t] + len(has.get(t, ())) + routed[t]), t))[:HEAD_TERMS]
    objects: list[set[int]] = [set() for _ in range(parts)]
    subs = [0] * parts
    loads = [0.0] * parts
    placed = {}
    for t in live:
        mine = has.get(t, ())
        limit = (1 + slack) * sum(loads) / parts
        best = None
        for p in range(parts):
            grown = costs.load(len(objects[p]) + sum(o not in objects[p] for o in mine), subs[p] + routed[t])
            key = (loads[p] > limit, grown - loads[p], loads[p], p)
            if best is None or key < best[0]:
                best = (key, p, grown)
        _, p, grown = best
        placed[t] = p
        objects[p].update(mine)
        subs[p] += routed[t]
        loads[p] = grown
    return placed
