import numpy as np
import pytest

from meshprofile.operators import topology as T
from meshprofile.sources import graphs as G


@pytest.mark.parametrize("kind", ["main", "ring", "complete", "petersen", "circulant", "unsafe"])
def test_weights_are_symmetric_and_sum_to_one(kind):
    w = T.mixing_matrix(G.named(kind))
    b = T.boosted_matrix(w)
    for m in (w, b):
        assert np.allclose(m, m.T) and np.allclose(m.sum(0), 1) and np.allclose(m.sum(1), 1)
    assert (w >= 0).all() and T.radius(b) < 1


def test_boost_minimises_the_radius():
    w = T.mixing_matrix(G.main_graph())
    best = min((T.radius(T.boosted_matrix(w, a)), a) for a in np.arange(-0.5, 1, 0.0005))
    s = T.spectrum(w)
    assert abs(best[1] - s["a"]) < 1e-3
    assert abs(s["rho_boosted"] - (s["lambda2"] - s["lambda_min"]) / (2 - s["lambda2"] - s["lambda_min"])) < 1e-9


def test_exposure():
    assert T.exposed_pairs(G.ring(3)) and T.exposed_pairs(G.complete(5)) and T.exposed_pairs([(0, 1), (1, 2), (2, 3), (3, 0), (0, 4)])
    for safe in (G.ring(4), G.ring(10), G.petersen(), G.circulant(25, (1, 5)), G.main_graph()):
        assert not T.exposed_pairs(safe)
    assert T.exposed_pairs(G.named("unsafe")) == [(0, 1), (2, 1)]
    with pytest.raises(ValueError):
        T.prune_exposed(G.ring(3), 3)


def test_connectivity_and_diameter():
    assert not T.is_connected(G.named("split"), 10) and T.is_connected(G.main_graph(), 10)
    assert T.diameter(G.ring(10), 10) == 5
    with pytest.raises(ValueError):
        T.diameter(G.named("split"), 10)


def test_rounds_follow_the_radius_over_nine_graphs():
    rho, rounds = [], []
    for i, e in enumerate(G.SWEEP_EDGES):
        w = T.boosted_matrix(T.mixing_matrix(G.random_connected(10, e, i)))
        rho.append(T.radius(w))
        rounds.append(T.rounds_needed(rho[-1]))
    rank = lambda v: np.argsort(np.argsort(v))
    assert np.corrcoef(rank(rho), rank(rounds))[0, 1] > 0.8 and rounds[0] > rounds[-1]


def test_dataframe_weights_equal_the_matrix(spark):
    got = T.matrix(T.mixing(G.edges_df(spark, G.main_graph())))
    assert np.allclose(got, T.mixing_matrix(G.main_graph()))


def test_components_of_long_rings(spark):
    pairs = G.ring(150) + [(a + 200, b + 200) for a, b in G.ring(5)]
    got = {r.src: r.component for r in T.connected_components(G.edges_df(spark, pairs)).collect()}
    assert got == {i: 0 for i in range(150)} | {i: 200 for i in range(200, 205)}
    assert T.connected_components(G.edges_df(spark, pairs).limit(0)).count() == 0


def test_spectrum_by_iteration(spark):
    """Power iteration by joins against the closed form of the Petersen graph's eigenvalues."""
    got = T.spectrum_by_iteration(T.mixing(G.edges_df(spark, G.petersen())), rounds=7)
    assert abs(got["lambda2"] - 1 / 2) < 0.03 and abs(got["lambda_min"] + 1 / 4) < 0.03
