"""How many pieces each node gets, so that their loads add up to the least."""

from __future__ import annotations


def allocate(costs: list[list[float]], m: int) -> list[int]:
    """Pieces per node, at least one each and ``m`` in all, of least total cost.

    ``costs[i][k-1]`` is the load of node i in k pieces. The best for the first nodes and any number of
    pieces is extended node by node.
    """
    n = len(costs)
    if not 0 < n <= m:
        raise ValueError(f"{n} nodes cannot get {m} pieces")
    infinite = float("inf")
    best = {0: (0.0, ())}
    for i, row in enumerate(costs):
        following: dict[int, tuple[float, tuple[int, ...]]] = {}
        for used, (cost, chosen) in best.items():
            for k in range(1, min(len(row), m - used - (n - i - 1)) + 1):
                total = cost + row[k - 1]
                if total < following.get(used + k, (infinite,))[0]:
                    following[used + k] = (total, (*chosen, k))
        best = following
    if m not in best:
        raise ValueError("the nodes cannot be cut into so many pieces")
    return list(best[m][1])
