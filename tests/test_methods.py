"""Hand-computed examples and invariants of the methods that run on the driver."""

import itertools
import random

import pytest

from geoherald.functions.expr import to_dnf
from geoherald.functions.geometry import Grid
from geoherald.operators import adjust, hybrid, migrate, spacesplit, textsplit
from geoherald.operators.load import optimal_small
from geoherald.operators.migrate import Cell
from geoherald.operators.node import Node
from geoherald.operators.numparts import allocate
from geoherald.operators.pack import pack_nodes, packed_loads, relabel
from geoherald.operators.sample import Costs, Sample

GRID = Grid(4096, 4)


def cells(*pairs):
    return [Cell(k, float(load), size) for k, (load, size) in enumerate(pairs)]


def test_load_by_definition():
    assert Costs(1, 2, 3, 4).load(100, 20, 10) == 2300


def test_allocation():
    assert allocate([[10, 7, 6], [8, 6, 5.5]], 3) == [2, 1]
    with pytest.raises(ValueError):
        allocate([[1], [1], [1]], 2)


def test_allocation_is_least_and_independent_of_order():
    rng = random.Random(2)
    for _ in range(30):
        table = [sorted((rng.randint(1, 50) for _ in range(4)), reverse=True) for _ in range(3)]
        got = allocate(table, 6)
        least = min(sum(t[k - 1] for t, k in zip(table, ks)) for ks in itertools.product(range(1, 5), repeat=3) if sum(ks) == 6)
        assert sum(got) == 6 and sum(t[k - 1] for t, k in zip(table, got)) == least
        turned = allocate(table[::-1], 6)
        assert sum(t[k - 1] for t, k in zip(table[::-1], turned)) == least


@pytest.mark.parametrize(
    "given, tau, exact, greedy, largest",
    [
        (cells((5, 1), (9, 4), (10, 4)), 10, 4, 5, 8),
        (cells((6, 3), (5, 3), (4, 3), (10, 9)), 10, 6, 6, 9),
        (cells((4, 4), (3, 3), (3, 3)), 5, 6, 7, 7),
        (cells((3, 3), (1, 1), (1, 1), (2, 2), (2, 2), (1, 1)), 5, 5, None, None),
    ],
)
def test_selectors(given, tau, exact, greedy, largest):
    assert migrate.exact_dp(given, tau).size == exact
    if greedy is not None:
        assert migrate.ratio_greedy(given, tau).size == greedy
        assert migrate.largest_first(given, tau).size == largest


def test_selectors_against_all_subsets():
    rng = random.Random(4)
    for _ in range(60):
        given = [Cell(k, float(rng.randint(0, 9)), rng.randint(0, 12)) for k in range(7)]
        tau = rng.randint(1, 20)
        sums = [(sum(c.load for c in s), sum(c.size for c in s)) for n in range(8) for s in itertools.combinations(given, n)]
        best = min((size for load, size in sums if load >= tau), default=None)
        for name, selector in migrate.SELECTORS.items():
            got = selector(given, tau)
            assert got.feasible == (best is not None), name
            if best is not None:
                assert got.load >= tau and got.size >= best
        if best is not None:
            assert migrate.exact_dp(given, tau).size == best


def test_exact_refuses_a_table_beyond_memory(monkeypatch):
    monkeypatch.setattr(migrate, "MAX_TABLE", 10)
    with pytest.raises(MemoryError):
        migrate.exact_dp(cells((5, 100), (6, 200)), 10)


def test_perfect_halves_need_space():
    # objects of one text in regions of sizes with equal halves: two workers can be balanced exactly
    units = []
    at = 0
    for size in (3, 1, 1, 2, 2, 1):
        units.append((frozenset(range(at, at + size)), frozenset()))
        at += size
    assert optimal_small(units, 2, 1.0)[0] == 10


def test_dnf():
    assert to_dnf("a and b") == [["a", "b"]]
    assert to_dnf("(a AND b) OR c") == [["a", "b"], ["c"]]
    assert to_dnf("a AND (b OR c)") == [["a", "b"], ["a", "c"]]
    assert to_dnf("a OR a AND b") == [["a"]]
    for wrong in ("", "a AND", "(a", "a)", "OR a"):
        with pytest.raises(ValueError):
            to_dnf(wrong)
    with pytest.raises(ValueError):
        to_dnf(" AND ".join(f"(x{k} OR y{k})" for k in range(7)))


def world(seed, n=300, q=120, terms=30):
    rng = random.Random(seed)
    objects = [(rng.randrange(16), rng.randrange(16), frozenset(f"t{min(rng.randrange(terms), rng.randrange(terms))}" for _ in range(4))) for _ in range(n)]
    subs = []
    for _ in range(q):
        x, y, w = rng.randrange(16), rng.randrange(16), rng.randrange(4)
        words = tuple(f"t{rng.randrange(terms)}" for _ in range(rng.randint(1, 2)))
        subs.append((x, min(15, x + w), y, min(15, y + w), frozenset(words[:1]), words))
    return Sample(GRID, objects, subs)


BUILDERS = [hybrid.build, spacesplit.by_grid, spacesplit.by_kdtree, spacesplit.by_rtree, textsplit.by_frequency, textsplit.by_hypergraph, textsplit.by_metric]


@pytest.mark.parametrize("build", BUILDERS)
@pytest.mark.parametrize("seed", [1, 2])
def test_partitions_cover_the_world(build, seed):
    assignment = build(world(seed), 4)
    assignment.check()
    assert {w for leaf in assignment.leaves for w in leaf.workers} == set(range(4))


def test_hybrid_reports_balance_and_stays_within_theta():
    params = hybrid.HybridParams(sigma=1.2, theta=4)
    assignment = hybrid.build(world(3), 4, params)
    loads = adjust.modelled_loads(world(3), assignment)
    assert len(loads) == 4 and min(loads) > 0
    assert isinstance(assignment.feasible, bool) and len(assignment.leaves) >= 4


def test_hybrid_leaves_alike_regions_to_space_and_cuts_others_by_text():
    rng = random.Random(1)
    # left: objects and subscriptions talk alike; right: they share one rare word only
    objects = [(rng.randrange(8), rng.randrange(16), frozenset(["a", "b"])) for _ in range(200)]
    objects += [(8 + rng.randrange(8), rng.randrange(16), frozenset(rng.sample([f"o{k}" for k in range(40)], 4) + ["r"] * (rng.random() < 0.05))) for _ in range(200)]
    subs = [(x, x, y, y, frozenset(["a"]), ("a", "b")) for x, y in ((rng.randrange(8), rng.randrange(16)) for _ in range(60))]
    subs += [(8, 15, 0, 15, frozenset([w]), (w,)) for w in ["r"] + [f"s{k}" for k in range(20)] for _ in range(3)]
    kinds = {(n.x0 >= 8): n.kind for n in hybrid.classify(Sample(GRID, objects, subs), hybrid.HybridParams(delta=0.99, max_depth=1))}
    assert kinds == {False: "space", True: "text"}


def test_packing_uses_every_worker():
    nodes = [n for n in Node.root(world(5)).space_cut(9) if n.load]
    owners = pack_nodes(nodes, 4)
    assert set(owners) == set(range(4))
    assert min(packed_loads(nodes, owners, 4, Costs())) > 0
    assert sorted(relabel([0, 1, 2, 3], 4, 1)) == [0, 1, 2, 3]


def test_text_cut_shares_all_live_terms():
    root = Node.root(world(6))
    parts = root.text_cut(3)
    assert frozenset().union(*(p.terms for p in parts)) == root.live()
    assert sum(len(p.terms) for p in parts) == len(root.live())


def test_hypergraph_does_not_cut_more_than_its_start():
    sample = world(7)
    edges = {}
    for _, _, terms in sample.objects:
        if len(terms) > 1:
            edges[terms] = edges.get(terms, 0) + 1
    start = textsplit.by_frequency(sample, 4).leaves[0].terms
    end = textsplit.by_hypergraph(sample, 4).leaves[0].terms
    assert textsplit.cut_size(edges, end) <= textsplit.cut_size(edges, start)


def test_phase_one_never_adds_load():
    for seed in range(3):
        sample = world(seed)
        assignment = spacesplit.by_kdtree(sample, 4)
        loads = adjust.modelled_loads(sample, assignment)
        changed, _ = adjust.phase_one(sample, assignment, loads.index(max(loads)), loads.index(min(loads)), 5)
        changed.check()
        after = adjust.modelled_loads(sample, changed)
        assert sum(after) <= sum(loads) + 1e-9


def test_target_restores_the_balance():
    tau = adjust.target(100, 20, 1.5)
    assert abs((100 - tau) / (20 + tau) - 1.5) < 1e-9
    assert adjust.target(100, 20, 1.5, half=True) == 40
