"""Simulated machines against brute force, with the errata of the published descriptions as regressions."""

import heapq
import random

import pytest

from writelite.functions import bounds
from writelite.functions.model import MachineParams
from writelite.operators import linalg, simulate, spectral
from writelite.plans import planner


def test_merge_does_not_pass_over_records():
    out, rounds = simulate.merge([[1, 9], [2], [3], [4]], MachineParams(2, 1, 2, 2))
    assert out == [1, 2, 3, 4, 9]
    assert [r[0] for r in rounds] == [2, 2, 1]
    assert sum(r[1] for r in rounds) == 9


def test_merge_does_not_emit_twice():
    out, rounds = simulate.merge([[2], [7, 8], [1, 3, 4], [5, 6]], MachineParams(4, 2, 2, 2))
    assert out == list(range(1, 9))
    assert [r[0] for r in rounds] == [5, 3]


@pytest.mark.parametrize("seed", range(40))
def test_merge_bounds(seed):
    rng = random.Random(seed)
    k, B = rng.choice([2, 3, 4]), rng.choice([1, 2, 4])
    mp = MachineParams(B * rng.choice([2, 4, 8]), B, 8, k)
    n = rng.randrange(1, 300)
    keys = rng.sample(range(10 * n), n)
    runs = [r for i in range(mp.fan_out) if (r := sorted(keys[i :: mp.fan_out]))]
    out, rounds = simulate.merge(runs, mp)
    assert out == sorted(keys)
    assert sum(r[1] for r in rounds) <= (k + 1) * sum(-(-len(r) // B) for r in runs)
    assert all(r[0] >= mp.M for r in rounds[:-1])
    assert sum(r[2] for r in rounds) == -(-n // B)


@pytest.mark.parametrize("seed", range(12))
@pytest.mark.parametrize("k", [1, 4])
def test_queue(seed, k):
    rng, q, h = random.Random(seed), simulate.Queue(MachineParams(16, 4, 8, k)), []
    for i in range(3000):
        if not h or rng.random() < (0.7 if i < 2000 else 0.3):
            x = rng.random()
            q.insert(x)
            heapq.heappush(h, x)
        else:
            assert q.delete_min() == heapq.heappop(h)
        if i % 300 == 0:
            assert q.ordered() and q.tree.check()
    assert simulate.Queue(MachineParams()).delete_min() is None


def test_tree_writes_a_constant():
    keys, tree = random.Random(1).sample(range(10**6), 4000), simulate.Tree()
    for x in keys:
        tree.insert(x)
    assert tree.walk() == sorted(keys)
    assert tree.writes < 12 * len(keys)
    for x in keys[::2]:
        assert tree.delete(x)
    assert tree.walk() == sorted(keys[1::2])
    assert not tree.delete(-1)


@pytest.mark.parametrize("seed", range(60))
def test_read_write_lru_stays_within_its_lemma(seed):
    rng = random.Random(seed)
    trace = [(rng.choice("RW"), rng.randrange(5)) for _ in range(14)]
    best = simulate.ideal_cost(trace, 2, 8)
    for policy in ("lru_dirty", "rw_lru"):
        assert simulate.cache(trace, 2, 8, policy)[1] >= 0
    assert simulate.cache(trace, 4, 8, "rw_lru")[1] <= bounds.rw_lru_bound(best, 2, 4, 8, 1)


def test_optimum_misses_least():
    rng = random.Random(3)
    trace = [("R", rng.randrange(12)) for _ in range(400)]
    assert simulate.cache(trace, 4, 8, "opt")[1] <= simulate.cache(trace, 4, 8, "lru")[1]


@pytest.mark.parametrize(
    ("n", "M", "B", "omega", "classic", "k", "best"),
    [(6000, 64, 8, 8, 27000, 4, 19500), (6000, 1024, 32, 4, 1880, 1, 1880), (60000, 64, 8, 8, 337500, 3, 270000), (60000, 256, 16, 4, 56250, 1, 56250), (600000, 256, 16, 8, 1350000, 1, 1350000), (600000, 1024, 32, 40, 2306250, 5, 1725000)],
)
def test_golden_costs(n, M, B, omega, classic, k, best):
    mp = MachineParams(M, B, omega)
    assert bounds.classic_cost(n, mp) == classic
    assert planner.choose_k(n, mp) == k
    assert bounds.mergesort_cost(n, mp.with_k(k)) == best


def test_planner_matches_exhaustive_search():
    rng = random.Random(5)
    for _ in range(300):
        mp, n = MachineParams(rng.choice([64, 256, 1024]), 8, rng.randrange(1, 60)), rng.randrange(1, 10**7)
        assert bounds.mergesort_cost(n, mp.with_k(planner.choose_k(n, mp))) == min(bounds.mergesort_cost(n, mp.with_k(k)) for k in range(1, mp.omega + 1))


def test_machine_rejects_nonsense():
    for bad in ((8, 16, 4, 1), (16, 8, 4, 5), (16, 8, 0, 1)):
        with pytest.raises(ValueError):
            MachineParams(*bad)


def test_both_twiddles_are_needed():
    import numpy as np

    x = np.random.default_rng(0).normal(size=64)
    assert np.abs(spectral.transform(x.astype(complex), 4, 4) - np.fft.fft(x)).max() < 1e-11
    for n in (2, 8, 128, 512):
        y = np.random.default_rng(n).normal(size=n) + 0j
        assert np.abs(spectral.transform(y, 4, 4) - np.fft.fft(y)).max() < 1e-10


def test_expected_product_cost():
    r, w = bounds.matmul_recurrence(2048, 1024, 8)
    std = 2048**3 / 32
    assert round(w / std, 3) == 0.292 and round((8 * w + r) / (10 * std), 2) == 0.70
    assert sum(x[6] for x in linalg.ledger_rows(64, 1024, 16, 8, 1)) == 256


def _few_runs():
    import numpy as np

    return np.random.default_rng(3).integers(0, 9, 240_000).astype(np.uint16)


def test_a_round_that_never_overflows_forgets_what_has_left():
    """The queue takes a block of each of nine runs, so their merge is one round: it holds the queue, not all that left it."""
    import tracemalloc

    runs, mp = _few_runs(), MachineParams(256, 16, 8, 4)
    tracemalloc.start()
    fine, rounds = simulate.merge_ranks(runs, mp)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    lists = [(runs == r).nonzero()[0].tolist() for r in range(9)]
    out, counted = simulate.merge(lists, mp)
    assert fine and out == sorted(out) and rounds == counted and len(rounds) == 1
    assert peak < 30 * len(runs)


@pytest.mark.parametrize("pointers", ["memory", "secondary"])
def test_merge_of_a_node_that_comes_in_parts(pointers):
    """A node's runs need not be put together: nine runs in one round, and in many of a smaller memory."""
    whole = _few_runs()[:5000]
    for mp in (MachineParams(256, 16, 8, 4), MachineParams(64, 8, 8, 4), MachineParams(8, 2, 8, 4)):
        out, rounds = simulate.merge([(whole == r).nonzero()[0].tolist() for r in range(9)], mp, pointers)
        for most in (1, 700, 5000):
            parts = [whole[i : i + most] for i in range(0, len(whole), most)]
            assert simulate.merge_ranks(parts, mp, pointers) == (out == list(range(5000)), rounds)
