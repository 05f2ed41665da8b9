import numpy as np
import pytest

from stablecf.operators import downstream as D
from stablecf.operators.mixture import Mixture

M = np.array([[0.0], [0.2], [0.4], [9.0], [9.1], [50.0]])
W, Q = np.array([3.0, 1, 1, 2, 2, 1]), np.zeros((6, 1))


def test_medoids_reach_the_exact_optimum():
    from itertools import combinations

    cost = lambda ids: (W * np.abs(M - M[list(ids)].T).min(axis=1)).sum()
    ids, got = D.kmedoids_search(W, M, Q, 3, neighbours=200, restarts=3)
    assert got == pytest.approx(min(cost(c) for c in combinations(range(6), 3)))
    assert cost(ids) == pytest.approx(got)
    assert D.kmedoids_search(W, M, Q, 9)[1] == 0


def test_density():
    assert D.density_clusters(W, M, Q, 1.0, 3).tolist() == [0, 0, 0, 1, 1, -1]
    assert D.density_clusters(W[:0], M[:0], Q[:0], 1.0, 3).tolist() == []


def test_border_entry_joins_but_does_not_connect():
    # entry 2 lies within reach of core 0, its own neighbourhood weighs 1.2; entry 3 reaches only it
    m, w = np.array([[0.0], [-0.5], [1.0], [2.0]]), np.array([1.0, 5.0, 0.1, 0.1])
    assert D.density_clusters(w, m, np.zeros((4, 1)), 1.0, 5.0).tolist() == [0, 0, 0, -1]


def test_feature_likelihood_and_size():
    one = Mixture(np.array([1.0]), np.array([[0.0]]), np.array([[1.0]]))
    assert D.loglik_features(np.array([2.0]), np.array([[0.0]]), np.array([[2.0]]), one) == pytest.approx(-0.5 * np.log(4 * np.pi))
    assert [D.feature_values("classic", 3, "scalar"), D.feature_values("stable", 3), D.feature_values("covariance", 3)] == [5, 7, 10]
