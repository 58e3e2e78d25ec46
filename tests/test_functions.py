"""Proximal maps, losses, centres and draws against brute force."""

import numpy as np
import pytest

from parley.functions import centres as C
from parley.functions import draws as D
from parley.functions import losses as L
from parley.functions import prox as P

rng = np.random.default_rng(7)


@pytest.mark.parametrize("kind", ["sq", "l2", "l1"])
def test_prox_minimises_its_definition(kind):
    x, delta, sigma = rng.normal(size=3), 0.3, 2.0
    best = P.prox_np(kind, x, delta)
    cost = lambda v: P.value_np(kind, v, delta, sigma) + sigma / 2 * ((x - v) ** 2).sum(-1)
    tries = best + 0.2 * rng.normal(size=(20_000, 3))
    assert cost(best) <= cost(tries).min() + 1e-12
    assert P.envelope_np(kind, x, delta, sigma) == pytest.approx(cost(best))


def test_soft_threshold_keeps_signs():
    assert P.prox_np("l1", np.array([-1, -0.05, 0.05, 1]), 0.1).tolist() == pytest.approx([-0.9, 0, 0, 0.9])


@pytest.mark.parametrize("kind", ["sq", "l2", "l1"])
def test_prox_is_nonexpansive_and_gives_the_envelopes_gradient(kind):
    x, y, sigma = rng.normal(size=(50, 4)), rng.normal(size=(50, 4)), 1.5
    assert (np.linalg.norm(P.prox_np(kind, x, 0.2) - P.prox_np(kind, y, 0.2), axis=1) <= np.linalg.norm(x - y, axis=1) + 1e-12).all()
    h, d = 1e-6, np.eye(4)[0]
    slope = (P.envelope_np(kind, x + h * d, 0.2, sigma) - P.envelope_np(kind, x - h * d, 0.2, sigma)) / (2 * h)
    assert np.allclose(slope, sigma * (x - P.prox_np(kind, x, 0.2))[:, 0], atol=1e-5)


def test_prox_at_edges():
    assert P.prox_np("l2", np.zeros(3), 0.1).tolist() == [0, 0, 0]
    assert np.allclose(P.prox_np("l2", np.array([0.1, 0, 0]), 0.1), 0)
    assert np.isinf(P.value_np("consensus", np.array([0.0, 1.0]), 0.1, 1.0))
    x = rng.normal(size=4)
    assert np.allclose(P.prox_np("free", x, 0.1), x)
    assert P.unscaled("l1", 4.0).delta == 0.25
    assert P.unscaled("sq", 4.0).delta == 0.5


@pytest.mark.parametrize("k", [1, 2, 3, 4, 8, 9])
def test_coordinate_centre_is_the_plain_iterations_limit(k):
    w = rng.normal(size=(k, 5)) * 2
    assert np.allclose(C.coordinate(w, 0.1), C.plain(w, "l1", 0.1)[0], atol=1e-8)


def test_flat_optimum_takes_the_point_nearest_to_the_mean():
    assert C.coordinate(np.array([[0.0], [1], [5], [20]]), 0.1)[0] == pytest.approx(4.9)


def test_geometric_centre_is_the_plain_iterations_limit():
    w = rng.normal(size=(9, 5))
    assert np.allclose(C.geometric(w, 0.1)[0], C.plain(w, "l2", 0.1)[0], atol=1e-7)
    w[0] = 1000
    fast, slow = C.geometric(w, 0.1)[1], C.plain(w, "l2", 0.1)[1]
    assert fast < slow / 10
    assert np.abs(C.geometric(w, 0.1)[0]).max() < 2  # one far model moves it little
    assert np.allclose(C.geometric(w, 1e6)[0], w.mean(0), atol=1e-6)


def test_centres_move_with_their_models():
    w, s = rng.normal(size=(7, 3)), np.array([1.0, -2, 3])
    for reg in (P.Regulariser("sq"), P.Regulariser("l2"), P.Regulariser("l1")):
        assert np.allclose(C.centre(w + s, reg), C.centre(w, reg) + s, atol=1e-7)
        assert np.allclose(C.centre(w[::-1], reg), C.centre(w, reg), atol=1e-7)


def test_squared_and_consensus_regularisers_give_the_mean():
    w = rng.normal(size=(6, 4))
    for kind in ("sq", "consensus"):
        assert np.allclose(C.generic(w, P.Regulariser(kind), 1.0)[0], w.mean(0), atol=1e-8)


LOSSES = [
    (L.Linear(4), lambda: (rng.normal(size=(2, 5, 4)), rng.normal(size=(2, 5)))),
    (L.Softmax(4, 3), lambda: (rng.normal(size=(2, 5, 4)), rng.integers(0, 3, (2, 5)))),
    (L.Logistic(4), lambda: (rng.normal(size=(2, 5, 4)), rng.integers(0, 2, (2, 5)))),
    (L.Mlp(4, 3, 3), lambda: (rng.normal(size=(2, 5, 4)), rng.integers(0, 3, (2, 5)))),
    (L.Portfolio(4, 3, 3), lambda: (rng.normal(size=(2, 5, 4)), rng.uniform(0.9, 1.1, (2, 5, 3)))),
    (L.Lstm(7, 3, 2), lambda: (rng.integers(0, 7, (2, 4, 5)), rng.integers(0, 2, (2, 4)))),
]


@pytest.mark.parametrize(("loss", "data"), LOSSES, ids=[type(x[0]).__name__ for x in LOSSES])
def test_gradients_match_differences(loss, data):
    x, y = data()
    w = rng.normal(size=(2, loss.size)) * 0.5
    g, h = loss.grad(w, x, y), 1e-6
    for j in range(loss.size):
        d = np.zeros(loss.size)
        d[j] = h
        assert np.allclose((loss.value(w + d, x, y) - loss.value(w - d, x, y)) / (2 * h), g[:, j], atol=1e-6)


def test_draws_agree_between_engines(spark, duck):
    ids = np.arange(500)
    got = [r[0] for r in spark.range(500).select(D.mixed(3, __import__("pyspark.sql.functions", fromlist=["col"]).col("id"), 8)).collect()]
    assert got == D.mixed_np(3, ids, 8).tolist()
    assert got == [r[0] for r in duck.execute(f"SELECT {D.mixed_sql(3, 'id', 8)} FROM range(500) t(id) ORDER BY id").fetchall()]
    u = D.uniform_np(1, np.arange(100_000))
    assert abs(u.mean() - 0.5) < 0.01
    assert abs(D.normal_np(1, np.arange(100_000)).std() - 1) < 0.02
