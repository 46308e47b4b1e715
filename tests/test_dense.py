"""Numeric kernels: golden values, sandwiches and identities."""

import numpy as np
import pytest

from cutfield.operators import dense as D

RING_H = np.array([0.1, -0.2, 0.3, 0.0])
RING_W = np.zeros((4, 4))
for _i, _j, _t in ((0, 1, 1.0), (2, 3, 1.0), (1, 2, 0.25), (0, 3, -0.25)):
    RING_W[_i, _j] = RING_W[_j, _i] = _t

#: Golden values of the ring: domain, partition, W, means, bound.
GOLDEN = [
    ("spin", [0, 1, 2, 3], 2.5, (-0.503924, -0.485992, 0.692501, 0.674243), 2.970817),
    ("spin", [0, 0, 1, 1], 0.5, (-0.053431, -0.095357, 0.278757, 0.217894), 3.689371),
    ("spin", [0, 1, 1, 0], 2.0, (-0.438995, -0.428949, 0.656551, 0.625804), 2.997838),
    ("spin", [0, 0, 0, 0], 0.0, (-0.048341, -0.094361, 0.271657, 0.206644), 3.714862),
    ("bit", [0, 1, 2, 3], 2.5, (0.643824, 0.652876, 0.751516, 0.643494), 3.591162),
    ("bit", [0, 0, 1, 1], 0.5, (0.635866, 0.643651, 0.739560, 0.636609), 3.640252),
    ("bit", [0, 1, 1, 0], 2.0, (0.643246, 0.652316, 0.750710, 0.642857), 3.594134),
    ("bit", [0, 0, 0, 0], 0.0, (0.635376, 0.643176, 0.738867, 0.636050), 3.643157),
]


@pytest.mark.parametrize("domain,labels,w,means,bound", GOLDEN)
def test_golden_ring(domain, labels, w, means, bound):
    f = D.ClusterField(RING_H, RING_W, np.array(labels), domain)
    f.run()
    assert np.allclose(f.mean, means, atol=2e-6)
    assert f.bound() == pytest.approx(bound, abs=2e-6)
    assert f.broken() == pytest.approx(w)
    log_z, _ = D.exact(RING_H, RING_W, domain)
    assert -1e-9 <= log_z - f.bound() <= f.kl_upper() + 1e-9


def test_clusters_without_inner_edges_are_naive():
    a, b = D.ClusterField(RING_H, RING_W, np.array([0, 1, 0, 1])), D.ClusterField(RING_H, RING_W, np.arange(4))
    a.run(), b.run()
    assert np.allclose(a.mean, b.mean, atol=1e-8) and a.bound() == pytest.approx(b.bound(), abs=1e-8)


def _model(seed, n=10, p=0.5, scale=1.0):
    rng = np.random.default_rng(seed)
    w = np.triu(rng.normal(size=(n, n)) * scale * (rng.random((n, n)) < p), 1)
    return rng.normal(size=n), w + w.T


@pytest.mark.parametrize("domain", ["spin", "bit"])
@pytest.mark.parametrize("seed", range(4))
def test_invariants(domain, seed):
    h, w = _model(seed)
    log_z, prob = D.exact(h, w, domain)
    s = D.states_of(10, domain)
    e = s @ h + ((s @ np.triu(w, 1)) * s).sum(1)
    assert log_z == pytest.approx(np.log(np.exp(e).sum()))
    labels = D.partition(np.abs(w), 5)["labels"]
    f = D.ClusterField(h, w, labels, domain)
    bounds = [b for _, _, b in f.run()]
    assert all(y >= x - 1e-9 for x, y in zip(bounds, bounds[1:])), "sequential sweeps never lower the bound"
    assert -1e-9 <= log_z - f.bound() <= f.kl_upper() + 1e-9
    one = D.ClusterField(h, w, np.zeros(10, int), domain)
    one.run()
    assert np.allclose(one.prob(), prob)


@pytest.mark.parametrize("k", [2, 4])
@pytest.mark.parametrize("sense", ["min", "max"])
def test_sandwich(k, sense):
    rng = np.random.default_rng(k)
    for _ in range(5):
        a = np.triu(rng.random((8, 8)) * (rng.random((8, 8)) < 0.7), 1)
        a = a + a.T
        best, _ = D.brute_cut(a, k, sense)
        bounds = [D.relax(a, k, sense, level)[2] for level in ("eigen", "psd", "psd_nonneg")]
        cut = D.partition(a, k, sense)["cut"]
        if sense == "min":
            assert bounds[0] <= bounds[1] + 1e-3 and bounds[1] <= bounds[2] + 1e-3 and bounds[2] <= best + 1e-6 <= cut + 2e-6
        else:
            assert bounds[0] >= bounds[1] - 1e-3 and bounds[1] >= bounds[2] - 1e-3 and bounds[2] >= best - 1e-6 >= cut - 2e-6


def test_rounding_sizes():
    rng = np.random.default_rng(1)
    a = np.triu(rng.random((12, 12)), 1)
    a = a + a.T
    for method in ("kmeans", "projection", "linearised", "spectral"):
        labels = D.partition(a, 3, "min", method)["labels"]
        assert np.bincount(labels).tolist() == [4, 4, 4]
    assert sorted(np.bincount(D.partition(a, 3, "min", sizes=[6, 4, 2])["labels"]).tolist()) == [2, 4, 6]
    assert sorted(np.bincount(D.partition(a, 5, "min")["labels"]).tolist()) == [2, 2, 2, 3, 3]
    assert np.bincount(D.partition(a, 2, "max", "hyperplane")["labels"]).tolist() == [6, 6]
    polished = D.polish(a, np.arange(12) % 3, "min")
    assert D.cut_value(a, polished) <= D.cut_value(a, np.arange(12) % 3)


def test_tree_is_exact_where_the_border_is_the_tree():
    h, w = np.array([0.3, -0.2, 0.5, 0.1, -0.4, 0.2]), np.zeros((6, 6))
    for i, j, t in ((0, 1, 0.9), (1, 2, -0.7), (2, 3, 1.1), (3, 4, 0.6), (4, 5, -0.8)):
        w[i, j] = w[j, i] = t
    for domain in ("spin", "bit"):
        f = D.TreeField(h, w, np.array([0, 0, 1, 1, 2, 2]), domain)
        f.run()
        log_z, prob = D.exact(h, w, domain)
        assert f.bound() == pytest.approx(log_z, abs=1e-8) and np.allclose(f.prob(), prob, atol=1e-8)


def test_tree_bound_never_passes_the_truth():
    for seed in range(3):
        h, w = _model(seed, 8, 0.5, 0.5)
        f = D.TreeField(h, w, np.repeat(np.arange(4), 2))
        f.run(sweeps=20)
        assert f.bound() <= D.exact(h, w, "spin")[0] + 1e-9


def test_treewidth():
    ring = np.zeros((6, 6))
    for i in range(6):
        ring[i, (i + 1) % 6] = ring[(i + 1) % 6, i] = 1
    assert D.treewidth_minfill(ring) == 2 and D.treewidth_minfill(np.ones((5, 5)) - np.eye(5)) == 4
