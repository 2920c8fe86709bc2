"""The kernel against brute force, the golden graphs, the closed forms and the proven bounds."""

import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from hopbound.functions.search import COMPLETE, INCOMPLETE, UNBOUNDED, Csr, distances_to, search, weighted_paths
from hopbound.operators.audit import run_violations
from hopbound.operators.measure import intervals, periods
from hopbound.sources import generators as G


def brute(csr, s, t, k):
    out = []

    def go(path):
        if len(path) > k:
            return
        for w in csr.succ[path[-1]]:
            if w == t:
                out.append((*path, t))
            elif w not in path:
                go([*path, w])

    go([s])
    return out


def drawn(seed):
    r = random.Random(seed)
    n = r.randint(2, 8)
    pairs = [(a, b) for a in range(n) for b in range(n) if a != b]
    csr = Csr.of(r.sample(pairs, r.randint(1, len(pairs))), range(n))
    return csr, r.randrange(n), r.randrange(n), r.randint(1, n)


@pytest.mark.parametrize("scheme", COMPLETE)
def test_complete_schemes_give_all_paths_in_order(scheme):
    for seed in range(500):
        csr, s, t, k = drawn(seed)
        assert search(csr, s, t, k, scheme).outputs == brute(csr, s, t, k)


@pytest.mark.parametrize("scheme", INCOMPLETE)
def test_incomplete_schemes_give_subsequences(scheme):
    for seed in range(400):
        csr, s, t, k = drawn(seed)
        want = iter(brute(csr, s, t, k))
        assert all(p in want for p in search(csr, s, t, k, scheme).outputs)


@pytest.mark.parametrize("scheme", UNBOUNDED)
def test_unbounded_searches(scheme):
    for seed in range(200):
        csr, s, t, _ = drawn(seed)
        assert sorted(search(csr, s, t, csr.n, scheme).outputs) == sorted(brute(csr, s, t, csr.n))


@pytest.mark.parametrize("scheme", ["tight", "tight_seeded", "loose", "lazy", "trivial"])
def test_barriers_stay_consistent_and_admissible(scheme):
    for seed in range(150):
        csr, s, t, k = drawn(seed)
        assert not any(search(csr, s, t, k, scheme, audit=True).violations.values())


def test_tight_keeps_all_invariants():
    for seed in range(150):
        csr, s, t, k = drawn(seed)
        assert not any(run_violations(csr, s, t, min(k, csr.n)).values()), seed


def lettered(lists, s, t, k, scheme, **how):
    csr = Csr.of(G.lettered(lists))
    run = search(csr, csr.index(s), csr.index(t), k, scheme, **how)
    return csr, run, ["".join(csr.names[i] for i in p) for p in run.outputs]


def test_first_counter_example():
    csr, run, paths = lettered(G.FIG_X, "A", "E", 4, "tight")
    assert paths == ["ABE", "ACBE", "ACDBE"]
    assert intervals(run) == [16, 21, 16, 11]
    assert (run.steps["search"], run.steps["cascade"], run.steps["output"]) == (27, 25, 12)
    csr, run, paths = lettered(G.FIG_X, "A", "E", 4, "guarded", log=True)
    assert paths == ["ABE", "ACBE"]
    assert [(csr.names[w[0]], w[3]) for w in run.writes][:4] == [("D", 2), ("C", 3), ("D", 3), ("C", 2)]
    assert run.total == 31
    bad = search(csr, csr.index("A"), csr.index("E"), 4, "guarded", audit=True).violations
    assert bad["consistency"] > 0


def test_second_counter_example():
    for scheme in (*COMPLETE, "guarded"):
        assert lettered(G.FIG_Y, "E", "C", 6, scheme)[2] == ["EADC", "EBDC", "EDC"]
    csr, run, _ = lettered(G.FIG_Y, "E", "C", 6, "guarded", log=True)
    assert [w[3] for w in run.writes if csr.names[w[0]] == "F"] == [3, 5, 3, 4]


@pytest.mark.parametrize(("c", "k"), [(5, 3), (6, 3), (8, 4), (10, 5)])
@pytest.mark.parametrize("seed", [0, 1])
def test_clique_trap_for_any_scan_order(c, k, seed):
    edges, s, t = G.clique_trap(c)
    order = random.Random(seed)
    csr = Csr.of([(a, b, order.random()) for a, b, _ in edges], (t,))
    n = k * c - k * (k + 1) // 2 + 1
    assert search(csr, csr.index(s), csr.index(t), k).total == c * n
    edges, s, t = G.clique_trap(c, True)
    csr = Csr.of(edges)
    assert intervals(search(csr, csr.index(s), csr.index(t), k)) == [4, c * n + c * c - 1]


@pytest.mark.parametrize("k", [8, 12, 16])
def test_breaker_family(k):
    edges, s, t = G.hub_breaker(k)
    csr = Csr.of(edges)
    assert (csr.n, csr.m) == (5 * k // 2, 9 * k // 2 - 6)
    for scheme in ("tight", "loose", "lazy"):
        run = search(csr, csr.index(s), csr.index(t), k, scheme)
        assert [len(p) - 1 for p in run.outputs] == [k // 2, 1]
        scans = run.events[2][1] - run.events[1][1]
        if scheme == "tight":
            assert max(intervals(run)) <= 3 * (k + 1) * (csr.n + csr.m)
        else:
            assert scans >= (k // 4 - 1) * (k // 2) * (k + 1)


def test_factorial_trap_grows_for_the_trivial_scheme_only():
    steps = {}
    for k in (5, 6, 7):
        edges, s, t = G.factorial_trap(k)
        csr = Csr.of(edges)
        for scheme in ("tight", "trivial"):
            steps[scheme, k] = search(csr, csr.index(s), csr.index(t), k, scheme).total
    assert steps["trivial", 7] > 6 * steps["trivial", 6] > 30 * steps["trivial", 5]
    assert steps["tight", 7] < 2 * steps["tight", 6]


@settings(max_examples=80, deadline=None)
@given(st.integers(0, 10_000), st.integers(1, 8))
def test_delay_bounds(seed, k):
    edges, s, t = G.uniform_digraph(seed)
    csr = Csr.of(edges, (s, t))
    k = min(k, csr.n)
    run = search(csr, csr.index(s), csr.index(t), k, cap=3000)
    unit, gaps = (k + 1) * (csr.n + csr.m), intervals(run)
    assert gaps[0] <= unit and max(gaps) <= 3 * unit
    if not run.capped:
        assert gaps[-1] <= 2 * unit
        assert max(periods(run), default=0) <= 2 * unit
    done = 0
    for p, g in enumerate(gaps, 1):
        done += g
        assert done <= 2 * p * unit


def test_cap_and_degenerate_inputs():
    csr = Csr.of([(0, 1), (1, 2), (2, 0), (1, 0)])
    run = search(csr, 0, 0, 3, cap=1)
    assert run.capped and len(run.outputs) == 1
    assert search(csr, 0, 2, 50).outputs == [(0, 1, 2)]
    edges, s, t = G.factorial_trap(8)
    big = Csr.of(edges)
    short = search(big, big.index(s), big.index(t), 8, "trivial", max_steps=500)
    assert short.capped and short.total < 600
    assert search(Csr.of([(0, 0)], (0, 1)), 0, 1, 2).outputs == []
    assert search(csr, 0, 0, 1).outputs == []
    assert Csr.of([]).index(3) is None
    assert Csr.of([(1, 2), (1, 2), (None, 1), (1, 1)]).m == 1


def test_seeding_never_enters_dead_regions():
    edges, s, t = G.clique_trap(8)
    csr = Csr.of(edges, (t,))
    run = search(csr, csr.index(s), csr.index(t), 4, "tight_seeded")
    assert run.calls == 1 and run.steps["seed"] > 0
    assert distances_to(csr, csr.index(t), 4)[0].count(0) == 1


def test_weighted_paths():
    edges = [("a", "b"), ("b", "c"), ("a", "c"), ("c", "b")]
    csr = Csr.of(edges)
    weight = {("a", "b"): 1, ("b", "c"): 1, ("a", "c"): 5, ("c", "b"): 0}
    w = lambda x, y: weight[csr.names[x], csr.names[y]]
    assert weighted_paths(csr, w, csr.index("a"), csr.index("c"), 4) == [(0, 1, 2)]
    assert len(weighted_paths(csr, w, csr.index("a"), csr.index("c"), 5)) == 2
