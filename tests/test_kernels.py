"""Sequential kernels and flows against enumeration and recomputation."""

import itertools
import random

import pytest

from hgpart.functions import kernels, pairflow
from hgpart.functions.kernels import Local, State
from hgpart.functions.maxflow import PushRelabel, augmenting_paths, graph_network, lawler, piercing_bipartition, sync_push_relabel


def instance(rng, n=None, m=None):
    n = n or rng.randint(2, 10)
    pins = [rng.sample(range(n), rng.randint(1, min(4, n))) for _ in range(m or rng.randint(1, 16))]
    return Local(pins, [rng.randint(1, 5) for _ in pins], [rng.randint(1, 3) for _ in range(n)])


def test_state_follows_moves():
    rng = random.Random(1)
    for _ in range(300):
        g, k = instance(rng), rng.randint(2, 4)
        at = State(g, [rng.randrange(k) for _ in range(g.n)], k)
        for _ in range(12):
            u, t = rng.randrange(g.n), rng.randrange(k)
            if t == at.part[u]:
                continue
            before, gain = g.km1(at.part), at.gain(u, t)
            at.move(u, t)
            assert before - g.km1(at.part) == gain
        fresh = State(g, at.part, k)
        assert fresh.alone == at.alone and fresh.phi == at.phi and fresh.weight == at.weight
        assert [{b: w for b, w in x.items() if w} for x in at.present] == fresh.present


def test_searches_never_worsen_and_keep_limits():
    rng = random.Random(2)
    for variant in ("localized", "all_moves", "boundary"):
        for _ in range(60):
            g, k = instance(rng, 12, 20), 3
            limit = [sum(g.node_weight) // k + 3] * k
            part = kernels.rebalance(g, [v % k for v in range(g.n)], k, limit)
            moves, after = kernels.localized_fm(g, part, k, limit, list(range(g.n)), variant=variant)
            assert g.km1(after) <= g.km1(part) and len({v for v, _, _ in moves}) == len(moves)
            if max(g.weights(part, k)) <= limit[0]:
                assert max(g.weights(after, k)) <= limit[0]
            again = list(part)
            for v, s, t in moves:
                assert again[v] == s
                again[v] = t
            assert again == after
            for f in (lambda: kernels.label_propagation(g, part, k, limit), lambda: kernels.fm(g, part, k, limit, seeds_per_search=2), lambda: pairflow.refine(g, part, k, limit)):
                assert g.km1(f()) <= g.km1(part)


def test_recalculation_equals_recomputation():
    rng = random.Random(3)
    for _ in range(200):
        g = instance(rng)
        part = [rng.randrange(3) for _ in range(g.n)]
        moves = [(u, rng.randrange(3)) for u in rng.sample(range(g.n), rng.randint(1, g.n))]
        gains, now = kernels.recalc_sequential(g, part, moves), list(part)
        for (u, t), x in zip(moves, gains):
            before = g.km1(now)
            now[u] = t
            assert before - g.km1(now) == x


def test_two_good_moves_that_hurt_together():
    # two nodes of different blocks, a heavy net between them, a lighter one at home each
    g = Local([[0, 1], [0, 2], [1, 3]], [5, 2, 2], [1] * 4)
    part = [0, 1, 0, 1]
    assert [State(g, part, 2).gain(0, 1), State(g, part, 2).gain(1, 0)] == [3, 3]
    assert kernels.recalc_sequential(g, part, [(0, 1), (1, 0)]) == [3, -7]


def test_constructive_methods_and_recursion():
    rng = random.Random(4)
    for name, f in kernels.TECHNIQUES.items():
        g = instance(rng, 30, 60)
        limit = [int(0.55 * sum(g.node_weight)) + 3] * 2
        part = f(g, limit, 5)
        assert set(part) <= {0, 1} and len(part) == 30, name
        assert f(g, limit, 5) == part
    for k in (1, 2, 3, 5, 8):
        g = Local(instance(rng, 60, 100).pins, [1] * 100, [1] * 60)
        part = kernels.recursive(g, k, 0.1)
        assert set(part) == set(range(k))


def test_small_instances_reach_the_optimum():
    rng = random.Random(5)
    hits = 0
    for _ in range(25):
        g = Local(instance(rng, 9, 12).pins, [1] * 12, [1] * 9)
        best = kernels.exact(g, 3, 3)[0]
        got = g.km1(kernels.rebalance(g, min((kernels.fm(g, kernels.recursive(g, 3, 0.0, s), 3, [3] * 3) for s in range(6)), key=g.km1), 3, [3] * 3))
        assert got >= best
        hits += got == best
    assert hits >= 15


def test_flows_agree_with_enumeration():
    rng = random.Random(6)
    for _ in range(250):
        n = rng.randint(2, 8)
        pins = [rng.sample(range(n), rng.randint(2, min(4, n))) for _ in range(rng.randint(1, 12))]
        w = [rng.randint(1, 5) for _ in pins]
        value = lambda x: sum(w[e] for e, vs in enumerate(pins) if len({x[v] for v in vs}) > 1)  # noqa: B023, E731
        best = min(value(x) for x in itertools.product((0, 1), repeat=n) if x[0] == 0 and x[-1] == 1)
        for cap in (True, False):
            f = PushRelabel(lawler(pins, w, n, cap))
            f.add_source(0)
            f.add_sink(n - 1)
            assert f.run() == best
            side = f.source_side()
            assert side[0] and not side[n - 1] and value([int(not s) for s in side[:n]]) == best
        assert augmenting_paths(lawler(pins, w, n), 0, n - 1) == best == sync_push_relabel(lawler(pins, w, n), 0, n - 1)
        weight = [rng.randint(1, 2) for _ in range(n)]
        most = sum(weight) // 2 + 1
        for bulk in (True, False):
            got = piercing_bipartition(pins, w, weight, 0, n - 1, most, most, bulk=bulk, warmup=1)
            if got:
                assert value(got[0]) == got[1] >= best and got[0][0] == 0 and got[0][-1] == 1
                assert max(sum(x for x, s in zip(weight, got[0]) if s == b) for b in (0, 1)) <= most


def test_path_is_pierced_to_a_balanced_cut():
    edges = [(0, 1, 1), (1, 2, 3), (2, 3, 2), (3, 4, 3), (4, 5, 3)]
    side, value, _ = piercing_bipartition([[a, b] for a, b, _ in edges], [w for *_, w in edges], [1] * 6, 0, 5, 3, 3)
    assert value == 2 and side == [0, 0, 0, 1, 1, 1]
    assert augmenting_paths(graph_network(edges, 6), 0, 5) == 1


def test_pair_flow_is_exact_about_its_gain():
    rng = random.Random(8)
    for _ in range(120):
        g = instance(rng, 14, 24)
        part = [rng.randrange(2) for _ in range(g.n)]
        limit = [max(g.weights(part, 2)) + 1] * 2
        moves, expected = pairflow.refine_pair(g, part, 0, 1, limit)
        after = list(part)
        for v, s, t in moves:
            assert after[v] == s
            after[v] = t
        assert g.km1(part) - g.km1(after) == expected >= 0
        assert max(g.weights(after, 2)) <= limit[0]


def test_swap_walks():
    assert kernels.swap_prefix_walk([2, 3, 1], [4, 1], 1, 1) == (3, 2)
    rng = random.Random(9)
    for _ in range(2000):
        a, b = [1] * rng.randint(0, 6), [1] * rng.randint(0, 6)
        p, q = rng.randint(0, 3), rng.randint(0, 3)
        i, j = kernels.swap_prefix_walk(a, b, p, q)
        assert -q <= i - j <= p and kernels.swap_prefix_recursive(a, b, p, q) == (i, j)
        assert i + j == max(x + y for x in range(len(a) + 1) for y in range(len(b) + 1) if -q <= x - y <= p)


def test_stop_rule_and_eps():
    assert not kernels.fm_should_stop(1, -5, 25) and not kernels.fm_should_stop(50, 3, 90)
    assert kernels.fm_should_stop(50, -100, 220, 1.0, 5.0)
    assert kernels.adaptive_eps(100, 4, 100, 4, 0.03) == pytest.approx(1.03**0.5 - 1)
    assert kernels.worth_rerun([10, 12, 11], 9) and not kernels.worth_rerun([10, 10, 10], 5)


def test_portfolio_repeats_every_technique(monkeypatch):
    calls = []
    real = kernels.candidate
    monkeypatch.setattr(kernels, "candidate", lambda g, name, *rest: calls.append(name) or real(g, name, *rest))
    g = kernels.Local([[i, (i + 1) % 12] for i in range(12)], [1] * 12, [1] * 12)
    kernels.recursive(g, 2, 0.1)
    runs = [calls.count(name) for name in kernels.TECHNIQUES]
    assert min(runs) >= 5 and max(runs) <= 20
