import heapq

import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st

from tangentia.functions import numeric as X
from tangentia.functions.similarity import score_arrays
from tangentia.operators.graph import grow_clusters
from tangentia.operators.metrics import matched_accuracy


def random_graph(seed, n=25, k=3):
    r = np.random.default_rng(seed)
    src = np.repeat(np.arange(n), k)
    return src, r.integers(0, n, n * k), r.random(n * k)


@given(st.integers(0, 10_000))
@settings(max_examples=40, deadline=None)
def test_paths_equal_dijkstra(seed):
    src, dst, w = random_graph(seed)
    got = X.shortest_paths(25, src, dst, w, np.arange(25))
    for s in range(25):
        d, heap = {s: 0.0}, [(0.0, s)]
        while heap:
            x, u = heapq.heappop(heap)
            if x > d[u]:
                continue
            for v, l in zip(dst[src == u], w[src == u]):
                if x + l < d.get(v, np.inf):
                    d[v] = x + l
                    heapq.heappush(heap, (d[v], v))
        assert np.allclose([d.get(i, np.inf) for i in range(25)], got[s])


def test_scaling_recovers_a_plane():
    x = np.random.default_rng(0).random((60, 2))
    g = np.sqrt(((x[:, None] - x) ** 2).sum(2))
    assert X.procrustes(x, X.classical_scaling(g, 2)) < 1e-12


def test_dimension_of_a_long_and_narrow_surface():
    from tangentia.operators.spectral import dim_from_spectrum

    assert dim_from_spectrum(np.array([6255.0, 1642.0, 45.0, 40.0])) == 2
    assert dim_from_spectrum(np.array([9.0, 0.0, 0.0])) == 1
    assert dim_from_spectrum(np.array([5.0, 4.0, 3.0, 0.0, 0.0])) == 3
    assert dim_from_spectrum(np.array([])) == 0


def test_procrustes_is_blind_to_shift_turn_and_scale():
    x = np.random.default_rng(1).standard_normal((50, 3))
    assert X.procrustes(x, 3 * x @ X.rotation(2, 3, 3).T + 5) < 1e-12
    assert X.procrustes(x, np.random.default_rng(3).standard_normal((50, 3))) > 0.5


def test_similarity_invariants():
    a = np.stack([X.rotation(i, 2, 5) for i in range(40)])
    b = np.stack([X.rotation(100 + i, 2, 5) for i in range(40)])
    turn = np.array([[np.cos(0.7), -np.sin(0.7)], [np.sin(0.7), np.cos(0.7)]])
    for mode in ("l1", "l2", "det", "vol", "projection"):
        s = score_arrays(a, b, mode)
        assert (s >= 0).all() and (s <= 1).all()
        assert np.allclose(score_arrays(a, a, mode), 1)
        assert np.allclose(s, score_arrays(a, -b, mode))
        assert np.allclose(s, score_arrays(b, a, mode))
    for mode in ("det", "vol", "projection"):
        assert np.allclose(score_arrays(a, b, mode), score_arrays(a, turn @ b, mode))
    assert not np.allclose(score_arrays(a, b, "l1"), score_arrays(a, turn @ b, "l1"))
    assert (score_arrays(a, b, "l1") <= score_arrays(a, b, "l2") + 1e-12).all()
    full = np.stack([X.rotation(i, 3, 3) for i in range(5)])
    assert np.allclose(score_arrays(full, full[::-1], "det"), 1)


def test_one_cluster_scores_a_half():
    assert matched_accuracy(np.array([[300.0, 100.0]])) == 0.5
    assert matched_accuracy(np.array([[0.0, 100.0], [300.0, 0.0]])) == 1.0


@given(st.integers(0, 10_000))
@settings(max_examples=40, deadline=None)
def test_growth_is_the_least_ancestor(seed):
    src, dst, _ = random_graph(seed, 20, 1)
    order = np.random.default_rng(seed).permutation(20).tolist()
    arcs = {i: [int(j) for j in dst[src == i]] for i in range(20)}
    grown = grow_clusters(arcs, order)
    rank = {v: k for k, v in enumerate(order, 1)}
    label = dict(rank)
    for _ in range(20):
        for i, j in zip(src.tolist(), dst.tolist()):
            label[j] = min(label[j], label[i])
    assert grown == label
