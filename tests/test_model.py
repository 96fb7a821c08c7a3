"""Costs, bounds, schedules and sample sizes against hand values."""

from __future__ import annotations

import random

import pytest

from evenlane.operators.networks import bitonic_schedule, odd_even_schedule
from evenlane.operators.sampling import claim_size, lane_quotas, random_size, regular_ratio
from evenlane.plans import bounds, model
from evenlane.plans.advisor import choose
from evenlane.plans.model import MACHINES, MachineModel, best_t


@pytest.mark.parametrize(("p", "regular", "rand"), [(16, (1.0348, 0.0773, 0.899), (1.0377, 0.0789, 0.896)), (64, (1.0522, 0.1175, 0.855), (1.0670, 0.1306, 0.835)), (128, (1.0609, 0.2109, 0.786), (1.0979, 0.2527, 0.740))])
def test_efficiencies(p, regular, rand):
    m = next(MachineModel(*x) for x in MACHINES if x[0] == p)
    for name, want in (("regular", regular), ("presorted_random", rand)):
        t = model.theory(name, 2**23, m)
        assert (round(t["pi"], 4), round(t["mu"], 4), round(t["efficiency"], 3)) == want


@pytest.mark.parametrize(("p", "b", "f"), [(16, (910, 15), (3640, 16)), (32, (1749.02, 31), (9904.72, 32)), (64, (7644, 8), (30576, 8)), (128, (16002, 11), (64008, 12))])
def test_tree_costs(p, b, f):
    m = next(MachineModel(*x) for x in MACHINES if x[0] == p)
    assert best_t(model.cost_broadcast, p - 1, p, m.l_ops, m.g_ops) == (pytest.approx(b[0]), b[1])
    assert best_t(model.cost_prefix, p, p, m.l_ops, m.g_ops) == (pytest.approx(f[0]), f[1])


def test_claim_sizes():
    assert [claim_size(2**23, k, 0.2, 1.0) for k in (8, 32, 128)] == [1417, 1544, 1671]


def test_sample_sizes():
    assert regular_ratio(2**23, 64) == 5
    assert random_size(60_000) == 504
    assert sum(lane_quotas(8, 800, 42)) == 800


def test_superstep_charges():
    m = MachineModel(16, 130.0, 0.21)
    assert m.superstep(0, 0) == pytest.approx(910)
    assert m.superstep(1000, 100) == pytest.approx(1000 + 147)
    assert m.h_relation(10) == pytest.approx(910)


@pytest.mark.parametrize("schedule", [bitonic_schedule, odd_even_schedule])
@pytest.mark.parametrize("p", [1, 2, 3, 5, 8, 16])
def test_networks_sort(schedule, p):
    rng = random.Random(p)
    q = 1 << max(0, (p - 1).bit_length())
    for _ in range(20):
        blocks = [sorted(rng.randrange(10) for _ in range(4)) for _ in range(q)]
        want = sorted(sum(blocks, []))
        for _, _, step in schedule(p):
            assert len({x for c in step for x in c}) == 2 * len(step)
            for a, b in step:
                both = sorted(blocks[a] + blocks[b])
                blocks[a], blocks[b] = both[:4], both[4:]
        assert sum(blocks, []) == want


def test_network_depths():
    assert [len(bitonic_schedule(p)) for p in (8, 16, 128)] == [6, 10, 28]
    assert [len(odd_even_schedule(p)) for p in (8, 16, 128)] == [6, 10, 28]


def _run_regular(lanes: list[list[int]], r: int) -> int:
    """Largest bucket of the method on small in-memory lanes, padded segments."""
    p = len(lanes)
    n = sum(map(len, lanes))
    s = r * p
    x = bounds.segment(n, p, s)
    runs = [sorted((k, i, j) for j, k in enumerate(sorted(lane))) for i, lane in enumerate(lanes)]
    top = (10**9, 10**9, 10**9)
    sample = sorted(run[(j + 1) * x - 1] if (j + 1) * x - 1 < len(run) else top for run in runs for j in range(s))
    fences = [sample[i * s - 1] for i in range(1, p)]
    size = [0] * p
    for run in runs:
        for rec in run:
            size[sum(f < rec for f in fences)] += 1
    return max(size)


def test_bound_holds_on_small_inputs():
    rng = random.Random(7)
    for _ in range(400):
        p, r = rng.randint(2, 5), rng.randint(1, 4)
        per = rng.randint(1, 40)
        lanes = [[rng.randrange(rng.choice([1, 3, 1000])) for _ in range(per)] for _ in range(p)]
        assert _run_regular(lanes, r) <= bounds.regular(p * per, p, r)


def test_bound_forms():
    assert bounds.regular(60_000, 8, 4) == 9165
    assert bounds.regular(60_000, 8, 4, "printed") == pytest.approx(9407)
    assert bounds.regular(15_000, 8, 4) == 2301


def test_schedules_reach_everyone():
    got = {c for _, _, c, k in model.broadcast_schedule(15, 16, 3) if k == 0}
    assert got == set(range(1, 16))
    ups = [(a, b) for s, _, a, b in model.prefix_schedule(16, 4) if s == "up"]
    assert len(ups) == 15 and {a for a, _ in ups} == set(range(1, 16))


def test_advisor_and_regimes():
    assert choose(MachineModel(16, 130.0, 0.21), 2**23).method == "regular"
    assert choose(MachineModel(128, 762.0, 0.34), 2**23).method == "presorted_random"
    assert model.regime(2**20, 2**8) == ("square", 1)
    assert model.regime(2**20, 2**14)[1] == 4
    terms = model.ledger("regular", 2**23, MachineModel(16, 130.0, 0.21))
    assert [t[1] for t in terms][:3] == ["local sort", "sample", "sample sort"] and all(t[5] >= 910 for t in terms)
