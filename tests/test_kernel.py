"""Closed forms, the hand graph, and the kernels' invariants."""

import itertools
import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from cutstream.params import PartitionParams, alpha, lmax
from cutstream.plans import kernel as K
from cutstream.plans.engine import fold_ghosts

HAND = [(0, 1), (0, 2), (1, 2), (3, 4), (3, 5), (4, 5), (6, 7), (6, 8), (7, 8), (2, 3), (4, 6), (5, 6), (1, 6), (0, 8)]


def level(n, pairs, weights=None):
    a = np.array(pairs, np.int64).reshape(-1, 2)
    return K.Level.of(np.ones(n) if weights is None else np.array(weights, float), a[:, 0], a[:, 1], np.ones(len(a)))


def random_level(seed, n=60, m=180):
    r = random.Random(seed)
    return level(n, [(r.randrange(n), r.randrange(n)) for _ in range(m)], [r.randint(1, 3) for _ in range(n)])


@pytest.mark.parametrize(("total", "k", "eps", "most"), [(9, 2, 0.03, 5), (100, 4, 0, 25), (101, 4, 0, 26), (1000, 8, 0.03, 129), (10.5, 2, 0.1, 6), (16530, 8, 0.03, 2129)])
def test_capacity(total, k, eps, most):
    assert lmax(total, k, eps) == most


def test_hand_numbers():
    assert alpha(9, 14, 2, 1.5) == pytest.approx(14 * 2**0.5 / 27)
    state = K.Blocks(PartitionParams(k=2), alpha(9, 14, 2, 1.5), 5, np.array([1.0, 2.0]))
    assert state.penalty == pytest.approx([1.0999, 1.5556], abs=1e-4)


def test_ghost_folding_on_hand_graph():
    # Buffer 3, 4, 5; vertex 6 comes later and touches 4 and 5.
    a, ghost = np.array([1, 2]), np.array([6, 6])
    weight, ga, gb, gw = fold_ghosts(a, ghost, np.ones(2), np.ones(2), 3, np.ones(3), 42)
    assert sorted(weight.tolist()) == [1, 1, 2] and weight[0] == 1
    g = K.Level.of(weight, np.concatenate([[0, 0, 1], ga]), np.concatenate([[1, 2, 2], gb]), np.concatenate([np.ones(3), gw]))
    assert dict(zip(zip(*[x.tolist() for x in g.edges()[:2]], strict=True), g.edges()[2].tolist(), strict=True)) == {(0, 1): 1, (0, 2): 1, (1, 2): 1.5}


@settings(max_examples=30, deadline=None)
@given(st.integers(0, 10**6), st.integers(1, 6))
def test_contraction_keeps_cut_and_loads(seed, parts):
    g = random_level(seed)
    r = np.random.default_rng(seed)
    labels = r.integers(0, 20, g.n)
    block_of_label = r.integers(0, parts, 20)
    coarse, to = K.contract(g, labels)
    block = block_of_label[labels]
    up = np.zeros(coarse.n, np.int64)
    up[to] = block

    def cut(x, b):
        u, v, w = x.edges()
        return w[b[u] != b[v]].sum()

    assert cut(g, block) == pytest.approx(cut(coarse, up))
    assert np.bincount(block, g.weight, parts) == pytest.approx(np.bincount(up, coarse.weight, parts))


@settings(max_examples=20, deadline=None)
@given(st.integers(0, 10**6))
def test_clusters_stay_small_and_inside(seed):
    g = random_level(seed)
    within = np.random.default_rng(seed).integers(0, 3, g.n)
    for own in (None, within):
        labels = K.label_propagation(g, 5, 9.0, seed, within=own)
        assert np.bincount(labels, g.weight).max() <= 9
        if own is not None:
            assert all(len(set(own[labels == x])) == 1 for x in set(labels.tolist()))


@settings(max_examples=20, deadline=None)
@given(st.integers(0, 10**6))
def test_moves_never_score_worse_and_fit(seed):
    g = random_level(seed)
    p = PartitionParams(k=4)
    most = lmax(float(g.weight.sum()), 4, 0.2)
    state = K.Blocks(p, alpha(g.n, len(g.adj) / 2, 4, 1.5), most)
    block = K.first_blocks(g, [{}] * g.n, state)
    trace = []
    after = K.refine(g, block, [{}] * g.n, state, 5, trace)
    assert all(new >= stay for *_, stay, new in trace)
    assert (np.bincount(after[after >= 0], g.weight[after >= 0], 4) <= most).all()


def test_gain_is_additive():
    g = random_level(3)
    state = K.Blocks(PartitionParams(k=3), 0.7, 1e9, np.array([4.0, 9.0, 2.5]))
    conn, weight = [1.5, 0.0, 3.0], [2.0, 1.0, 4.0]
    for i in range(3):
        assert state.score(sum(conn), sum(weight), i) == pytest.approx(sum(state.score(x, c, i) for x, c in zip(conn, weight, strict=True)))
    assert g.n == 60


def brute(n, pairs, k, most):
    best = None
    for b in itertools.product(range(k), repeat=n):
        if max(np.bincount(b, minlength=k)) <= most:
            cut = sum(b[u] != b[v] for u, v in pairs)
            best = cut if best is None else min(best, cut)
    return best


def test_two_cliques_with_a_bridge_are_cut_at_the_bridge():
    pairs = [*itertools.combinations(range(5), 2), *itertools.combinations(range(5, 10), 2), (4, 5)]
    g, p = level(10, pairs), PartitionParams(k=2)
    most = lmax(10, 2, 0.03)
    levels, maps = K.coarsen(g, p, most)
    block, fits = K.multilevel(levels, maps, [{} for _ in range(10)], K.Blocks(p, alpha(10, len(pairs), 2, 1.5), most), p)
    assert fits and sum(block[u] != block[v] for u, v in pairs) == 1 == brute(10, pairs, 2, most)


def test_never_below_the_optimum():
    p, most = PartitionParams(k=2, eps=0.2), lmax(9, 2, 0.2)
    g = level(9, HAND)
    block, _ = K.multilevel([g], [], [{} for _ in range(9)], K.Blocks(p, alpha(9, 14, 2, 1.5), most), p)
    assert sum(block[u] != block[v] for u, v in HAND) >= brute(9, HAND, 2, most)


def test_heavy_vertex_is_placed_and_reported():
    p = PartitionParams(k=2)
    g = level(3, [(0, 1)], [10, 1, 1])
    block, fits = K.multilevel([g], [], [{}, {}, {}], K.Blocks(p, 0.1, 7.0), p)
    assert not fits and (block >= 0).all()


def test_bad_parameters():
    for bad in ({"k": 0}, {"k": 2, "eps": -1}, {"k": 2, "model": "none"}, {"k": 2, "delta": 0}):
        with pytest.raises(ValueError):
            PartitionParams(**bad)


@given(st.integers(1, 9), st.lists(st.dictionaries(st.integers(0, 8), st.integers(1, 4)), min_size=1, max_size=40), st.sampled_from(["penalty_gain", "capacity_discount"]))
@settings(max_examples=60, deadline=None)
def test_scoring_all_blocks_chooses_the_same(k, stream, objective):
    p = PartitionParams(k=k, objective=objective)
    most = float(lmax(len(stream), k, p.eps))
    one, other = K.Blocks(p, 0.7, most), K.AllBlocks(p, 0.7, most)
    for near in stream:
        conn = {i: float(w) for i, w in near.items() if i < k}
        i = one.best_of_all(conn, 1.0)
        assert i == other.best_of_all(conn, 1.0)
        if i >= 0:
            one.add(i, 1.0)
            other.add(i, 1.0)
