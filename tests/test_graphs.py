"""Layered graphs: structure, search, and what holds for any of them."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from vecroute.functions import kernels
from vecroute.graphs import hnsw, knn_graph

RNG = np.random.default_rng(0)
X = RNG.standard_normal((400, 16))
IDS = np.arange(400) * 3 + 1


def truth(q, x, ids, k, metric):
    return kernels.top_k(kernels.score_matrix(kernels.prepared(q, metric), kernels.prepared(x, metric), metric), ids, k)[0]


@pytest.mark.parametrize("metric", ["l2", "cosine", "ip"])
@pytest.mark.parametrize("make", [hnsw.build, hnsw.build_bulk])
def test_structure_and_search(metric, make):
    g = make(IDS, X, metric, degree=8, degree0=16)
    assert g.layers[0].nodes.size == 400 and hnsw.reachable(g).all()
    for upper, lower in zip(g.layers[1:], g.layers, strict=False):
        assert set(upper.nodes) <= set(lower.nodes)
    for t, y in enumerate(g.layers):
        assert (y.links >= 0).sum(axis=1).max() <= max(16 if t == 0 else 8, y.links.shape[1])
        assert not (y.links == y.nodes[:, None]).any()
    want = truth(X[:50], X, IDS, 10, metric)
    got, scores, stats = hnsw.search(g, X[:50], 10, 60)
    assert np.mean([len(set(a) & set(b)) / 10 for a, b in zip(want, got, strict=True)]) > 0.9
    assert (np.diff(scores, axis=1) <= 1e-12).all() and all(len(set(r)) == 10 for r in got.tolist())
    assert (hnsw.search(g, X[:50], 10, 400)[0] == want).all()
    assert stats.evals.min() > 10
    capped = hnsw.search(g, X[:50], 5, 60, max_evals=40)[2]
    assert capped.evals.max() <= 40


def test_same_seed_same_graph():
    a, b = hnsw.build(IDS, X), hnsw.build(IDS[::-1], X[::-1])
    assert hnsw.to_row(a) == hnsw.to_row(b)
    c = hnsw.from_row(hnsw.to_row(a))
    assert (hnsw.search(a, X[:9], 5)[0] == hnsw.search(c, X[:9], 5)[0]).all()


def test_one_way_links_reach_nothing():
    """Without links back, a walk from the first item finds only that item."""
    g = hnsw.build(np.arange(50), X[:50], degree=10**6, reverse_edges=False)
    assert len(g.layers) == 1 and g.entry == 0
    assert hnsw.reachable(g).sum() == 1


def test_repair_reaches_all():
    g = hnsw.build(IDS, X, degree=4, degree0=4, mend=False)
    g.layers[0].links[100:200] = -1
    for row in g.layers[0].links:
        row[np.isin(row, np.arange(100, 200))] = -1
    assert not hnsw.reachable(g).all()
    assert hnsw.reachable(hnsw.repair(g)).all()


def test_levels_thin_out():
    level = hnsw.draw_level(np.arange(200_000), 42, 16)
    counts = [(level >= t).sum() for t in range(4)]
    for a, b in zip(counts, counts[1:], strict=False):
        assert 12 < a / b < 21


def test_small_and_empty():
    g = hnsw.build(np.array([7]), np.array([[1.0, 2.0]]))
    ids, scores, _ = hnsw.search(g, np.array([[0.0, 0.0]]), 3)
    assert ids.tolist() == [[7, -1, -1]] and scores[0, 0] == pytest.approx(-(5**0.5))
    assert hnsw.search(hnsw.build(np.zeros(0, int), np.zeros((0, 2))), np.zeros((1, 2)), 2)[0].tolist() == [[-1, -1]]
    assert hnsw.search(hnsw.build_bulk(np.zeros(0, int), np.zeros((0, 2))), np.zeros((1, 2)), 2)[0].tolist() == [[-1, -1]]


def test_ties_go_to_the_smaller_id():
    grid = np.array([[i, j] for i in range(3) for j in range(3)], float)
    g = hnsw.build(np.arange(9), grid)
    assert hnsw.search(g, np.array([[1.0, 1.0]]), 5, 9)[0].tolist() == [[4, 1, 3, 5, 7]]


def test_diverse_in_bulk_equals_one_by_one():
    for metric in ("l2", "ip"):
        g = kernels.rank_matrix(X[:20], X, metric)
        np.fill_diagonal(g, -np.inf)
        near = np.argsort(-g, axis=1)[:, :32]
        worth = np.take_along_axis(g, near, 1) - ((X[:20] ** 2).sum(axis=1)[:, None] if metric == "l2" else 0)
        many = hnsw._diverse_rows(X, metric, worth, near, 12)
        for i in range(20):
            assert many[i].tolist() == hnsw._diverse(X, metric, worth[i], near[i], 12).tolist()


@settings(max_examples=25, deadline=None)
@given(st.integers(2, 60), st.integers(1, 6), st.sampled_from(["l2", "cosine", "ip"]), st.integers(0, 10**6))
def test_exhaustive_search_is_exact(n, d, metric, seed):
    x = np.random.default_rng(seed).integers(-3, 4, (n, d)).astype(float)
    g = hnsw.build_bulk(np.arange(n), x, metric, degree=4, degree0=8)
    ids, scores, _ = hnsw.search(g, x[:5], min(5, n), n)
    want = kernels.score_matrix(kernels.prepared(x[:5], metric), kernels.prepared(x, metric), metric)
    assert np.allclose(scores, -np.sort(-want, axis=1)[:, : min(5, n)])


def test_flat_graph_walk():
    g = knn_graph.build(IDS, X, 12)
    got, _, _ = knn_graph.search(g, X[:40], 10, 80, start=399)
    want = truth(X[:40], X, IDS, 10, "l2")
    assert np.mean([len(set(a) & set(b)) / 10 for a, b in zip(want, got, strict=True)]) > 0.85
