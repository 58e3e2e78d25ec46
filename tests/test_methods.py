"""The round loop: identities between methods, theory, distributed against simulated, and orders that trials support."""

import numpy as np
import pytest
from conftest import SF

from parley import workloads as W
from parley.functions.losses import Softmax
from parley.functions.prox import Regulariser
from parley.operators import aggregate as A
from parley.operators import methods as M
from parley.operators import rounds as R
from parley.operators import simulation as S
from parley.operators import theory as T
from parley.plans.choose import aggregator, sufficient_statistics


@pytest.fixture(scope="module")
def small():
    return W.softmax_generator(6, 1, 1.0, 1.0, 10)


def test_a_fused_step_is_a_gradient_step_on_the_penalised_loss(small):
    loss, fed = small
    w, z, eta, sigma = np.full((1, loss.size), 0.1), np.full((1, loss.size), 0.3), 0.05, 2.0
    g = loss.grad(w, fed.x[0][None], fed.y[0][None])
    k = 1 / (1 + eta * sigma)
    assert np.allclose(k * (w - eta * g) + (1 - k) * z, w - eta * k * (g + sigma * (w - z)), atol=1e-13)


def test_methods_reduce_to_each_other(small):
    loss, fed = small
    cfg = M.Rounds(0.05, 0.0, 4, 4, 5, 8)
    base = S.simulate(loss, fed, M.fed_mean(), cfg)["g"]
    assert np.allclose(S.simulate(loss, fed, M.fed_prox_mean(), cfg)["g"], base)  # no penalty
    assert np.allclose(S.simulate(loss, fed, M.adaptive_mix_personal(0.0, False), cfg)["g"], base)  # nothing of its own
    own = S.simulate(loss, fed, M.local_only(), cfg)["state"]["w"]
    assert np.allclose(S.simulate(loss, fed, M.personal_mean(), cfg)["state"]["w"], own)  # an untied party is alone
    layout = [(0, 50, Regulariser("sq")), (50, loss.size, Regulariser("sq"))]
    cfg = M.Rounds(0.05, 1.0, 4, 4, 5, 8)
    assert np.allclose(S.simulate(loss, fed, M.personal_hybrid(layout), cfg)["g"], S.simulate(loss, fed, M.personal_mean(), cfg)["g"])


def test_equal_parties_make_control_variates_idle():
    x, y = np.random.default_rng(1).normal(size=(20, 4)), np.arange(20) % 3
    fed, loss = S.Federation([x] * 4, [y] * 4, [x] * 4, [y] * 4), Softmax(4, 3)
    cfg = M.Rounds(0.1, 0.0, 5, 4, 3, None)
    assert np.allclose(S.simulate(loss, fed, M.control_variate_mean(), cfg)["g"], S.simulate(loss, fed, M.fed_mean(), cfg)["g"])


def test_stragglers_and_idle_parties(small):
    loss, fed = small
    cfg = M.Rounds(0.05, 1.0, 1, 2, 5, 8, stragglers=1.0)
    r = S.simulate(loss, fed, M.personal_mean(), cfg)
    k = M.draw_active(fed.parties, 2, 0, cfg.seed)
    moved = np.abs(r["state"]["w"]).sum(1) > 0
    assert set(np.nonzero(moved)[0]) == set(k)
    assert (M.steps_of(fed.parties, 0, cfg) <= 5).all()


@pytest.mark.parametrize("reg", [Regulariser("sq"), Regulariser("l2"), Regulariser("l1")])
def test_objective_never_rises_and_gradients_vanish(small, reg):
    loss, fed = small
    cfg = M.Rounds(1 / loss.lipschitz(fed.x), 0.1, 20, 6, 2, None, scope="all")
    got = T.descent(loss, fed, M.Method("x", reg), cfg)
    o = [r["objective"] for r in got]
    assert all(b <= a + 1e-12 for a, b in zip(o, o[1:], strict=False))
    assert all(r["decrease_held"] for r in got)
    assert got[-1]["squared_gradients"] < 0.2 * got[0]["squared_gradients"]


HYBRID = [(0, 325, Regulariser("sq", 0.1)), (325, 650, Regulariser("l1", 0.1))]


@pytest.mark.parametrize("late", [0.0, 0.7])
@pytest.mark.parametrize("make", [M.personal_geomed, M.fed_geomed, M.control_variate_mean, M.envelope_personal, M.meta_init_personal, M.adaptive_mix_personal, lambda: M.personal_hybrid(HYBRID)])
def test_distributed_rounds_equal_the_simulation(spark, make, late):
    ex = W.image_examples(spark, SF).persist()
    loss, cfg, method = Softmax(64, 10), M.Rounds(0.05, 1.0, 2, 4, 3, 8, seed=3, stragglers=late), make()
    rows = ex.orderBy("party_id", "pos").collect()
    part = lambda name, f: [np.array([r[f] for r in rows if r.party_id == k and r.split == name]) for k in range(10)]
    fed = S.Federation(part("train", "x"), part("train", "y"), part("test", "x"), part("test", "y"))
    a, b = R.run_rounds(ex.where("split = 'train'"), loss, method, cfg), S.simulate(loss, fed, method, cfg)
    state = a.state.orderBy("party_id").collect()
    assert np.allclose([r.w for r in state], b["state"]["w"], atol=1e-12)
    if method.kind == "envelope":
        assert np.allclose([r.theta for r in state], b["state"]["theta"], atol=1e-12)
    assert np.allclose(a.g, b["g"], atol=1e-12)
    got = {r.party_id: r.score for r in R.scores(ex.where("split = 'test'"), a, loss, method, cfg).collect()}
    assert np.allclose([got[k] for k in range(10)], b["party"])


@pytest.mark.parametrize("make", [M.personal_mean, M.control_variate_mean])
def test_resuming_gives_the_same_state(spark, tmp_path, make):
    from parley.sources.stores import RunStore

    ex = W.image_examples(spark, SF).where("split = 'train'").persist()
    loss, method = Softmax(64, 10), make()
    whole = R.run_rounds(ex, loss, method, M.Rounds(0.05, 1.0, 2, 4, 3, 8))
    half = R.run_rounds(ex, loss, method, M.Rounds(0.05, 1.0, 1, 4, 3, 8))
    store = RunStore(spark, f"file://{tmp_path}")
    store.save(half)
    assert store.rounds() == [1]
    rest = R.run_rounds(ex, loss, method, M.Rounds(0.05, 1.0, 1, 4, 3, 8), resume=store.load(1))
    assert np.allclose(rest.g, whole.g)
    assert np.allclose([r.w for r in rest.state.orderBy("party_id").collect()], [r.w for r in whole.state.orderBy("party_id").collect()])


def test_rounds_write_active_parties_only_and_leave_one_table(spark, monkeypatch):
    """Models beside the table of all parties, folded in now and then: the result is the same, and nothing is left over."""
    from parley.sources import tables

    written, removed = [], []
    keep, drop = tables.Tables.keep, tables.Tables.drop
    monkeypatch.setattr(tables.Tables, "keep", lambda self, df, label: written.append((label, (out := keep(self, df, label)))) or out)
    monkeypatch.setattr(tables.Tables, "drop", lambda self, *t: removed.extend(x for x in t if id(x) in self.paths) or drop(self, *t))
    ex = W.image_examples(spark, SF).where("split = 'train'").persist()
    loss, method, cfg = Softmax(64, 10), M.personal_mean(), M.Rounds(0.05, 1.0, 5, 3, 2, 8)
    monkeypatch.setattr(R, "FOLD", 2)
    often = R.run_rounds(ex, loss, method, cfg)
    sizes = [t.count() for label, t in written if label == "solved" and not any(t is r for r in removed)]
    assert sizes == [] and sum(label == "solved" for label, _ in written) == 5
    assert [label for label, t in written if not any(t is r for r in removed)] == ["state"]
    monkeypatch.setattr(R, "FOLD", 100)
    once = R.run_rounds(ex, loss, method, cfg)
    assert np.allclose(often.g, once.g)
    assert np.allclose([r.w for r in often.state.orderBy("party_id").collect()], [r.w for r in once.state.orderBy("party_id").collect()])


def test_a_round_moves_no_example_of_a_bucketed_table(spark):
    from parley.sources.stores import bucketed

    spark.sql("DROP TABLE IF EXISTS parley_round_examples")
    ex = bucketed(W.image_examples(spark, SF).where("split = 'train'"), "parley_round_examples", 4, "party_id", "pos")
    try:
        loss, method, cfg = Softmax(64, 10), M.personal_geomed(), M.Rounds(0.05, 1.0, 1, 4, 3, 8)
        run = R.run_rounds(ex, loss, method, cfg)
        active = spark.createDataFrame([(k,) for k in range(4)], "party_id long")
        one = R.local_round(ex, run.state, active, loss, method, cfg, run.g, 0, np.zeros(loss.size))
        plan = one._jdf.queryExecution().executedPlan().toString()
        sides = plan.split("parley_round_examples")[0]  # what stands above the scan of the examples
        assert "SelectedBucketsCount: 4 out of 4" in plan or "Bucketed: true" in plan
        assert sides.count("Exchange hashpartitioning") <= 1 and "PushedFilters" in plan  # the states' side alone
        from_examples = sides[sides.rindex("FlatMapCoGroups") :].split("Scan")[0]
        assert "Exchange hashpartitioning" not in from_examples
        assert one.count() == 4
    finally:
        spark.sql("DROP TABLE parley_round_examples")


def test_hot_parties_are_scored_in_shards(spark, monkeypatch):
    ex = W.image_examples(spark, SF).persist()
    loss, method, cfg = Softmax(64, 10), M.personal_mean(), M.Rounds(0.05, 1.0, 1, 4, 3, 8)
    run, test = R.run_rounds(ex.where("split = 'train'"), loss, method, cfg), ex.where("split = 'test'")
    whole = {r.party_id: (r.score, r.n) for r in R.scores(test, run, loss, method, cfg).collect()}
    monkeypatch.setattr(R, "SHARD_ROWS", 3)
    parts = {r.party_id: (r.score, r.n) for r in R.scores(test, run, loss, method, cfg).collect()}
    assert whole.keys() == parts.keys() and all(whole[k] == pytest.approx(parts[k]) for k in whole)


def test_sweeps_beyond_a_tasks_size_run_distributed(spark, monkeypatch):
    """A federation too large for a task gives the same scores by the distributed loop."""
    from dataclasses import replace

    cfg = replace(M.bench_standard("five_labels", rounds=2), steps=2)
    settings = [("five_labels", 20, M.personal_geomed(), cfg, 1)]
    inside = sorted(W.experiment(spark, SF, settings).collect())
    monkeypatch.setattr(W, "fits", lambda examples, held: False)
    beyond = sorted(W.experiment(spark, SF, settings).collect())
    assert [(r.round, r.method) for r in inside] == [(r.round, r.method) for r in beyond]
    assert [tuple(r)[5:7] for r in inside] == [pytest.approx(tuple(r)[5:7]) for r in beyond]  # parties without test rows have no score in either


def test_exact_minimisers_of_losses_without_closed_form(small):
    loss, fed = small
    x, y = fed.x[0][None], fed.y[0][None]
    z = np.full((1, loss.size), 0.2)
    from parley.functions.losses import Linear, Loss, minimiser

    assert isinstance(loss, Loss) and isinstance(Linear(3), Loss)
    w = minimiser(loss, np.zeros((1, loss.size)), x, y, z, 0.5)
    assert np.abs(loss.grad(w, x, y) + 0.5 * (w - z)).max() < 1e-9
    rng = np.random.default_rng(1)
    x, y, z = rng.normal(size=(2, 9, 3)), rng.normal(size=(2, 9)), rng.normal(size=(2, 3))
    w = minimiser(Linear(3), z, x, y, z, 0.7)
    assert np.abs(Linear(3).grad(w, x, y) + 0.7 * (w - z)).max() < 1e-12


def test_a_users_loss_trains(spark):
    """Any object with the members of the protocol will do."""
    from parley.functions.losses import Loss

    class Absolute:
        task, size = "regression", 2

        def value(self, w, x, y):
            return np.abs(np.einsum("pbf,pf->pb", x, w) - y).mean(1)

        def grad(self, w, x, y):
            return np.einsum("pbf,pb->pf", x, np.sign(np.einsum("pbf,pf->pb", x, w) - y)) / x.shape[1]

        def predict(self, w, x):
            return np.einsum("pbf,pf->pb", x, w)

    loss = Absolute()
    assert isinstance(loss, Loss)
    ex = W.order_examples(spark, SF).persist()
    run = R.run_rounds(ex.where("split = 'train'"), loss, M.personal_mean(), M.Rounds(0.3, 0.1, 3, 25, 5, 20))
    first = R.scored(ex.where("split = 'test'"), run.state.select("party_id", "w"), loss)
    zero = R.scored(ex.where("split = 'test'"), run.state.selectExpr("party_id", "transform(w, a -> 0D) AS w"), loss)
    assert first.agg({"loss": "avg"}).first()[0] < zero.agg({"loss": "avg"}).first()[0]


def test_iterated_centres_scan_their_models_once(spark):
    """Models made by an aggregation: the steps read what is held, not the rows below."""
    from pyspark.sql import functions as F

    seen = spark.sparkContext.accumulator(0)

    def count(frames):
        for f in frames:
            seen.add(len(f))
            yield f

    rows = spark.range(400).select((F.col("id") % 40).alias("party_id"), F.array(F.rand(3), F.rand(4)).alias("w")).mapInPandas(count, "party_id long, w array<double>")
    models = rows.groupBy("party_id").agg(F.first("w").alias("w"))
    _, steps = A.geometric_median(models, 0.1)
    assert steps > 2 and seen.value == 400


def test_far_parties_hurt_the_common_model_most():
    """Averages over seeds of short regression runs: a common model is worst, as in every trial."""
    cfg = dict(eta=1e-3, sigma=100.0, rounds=40, active=10, steps=20, batch=10)
    mean = {}
    for make in (M.fed_mean, M.local_only, M.personal_mean, M.personal_geomed, M.personal_comed):
        mean[make.__name__] = np.mean([np.nanmean(S.simulate(*W.planted_regression(10, s, 50), make(), M.Rounds(seed=s, **cfg))["party"]) for s in range(1, 4)])
    assert mean["fed_mean"] == max(mean.values())


def test_the_planner_trains_on_statistics_where_it_can(spark):
    from parley.functions.losses import Linear
    from parley.operators import quadratic

    ex = W.order_examples(spark, SF).where("split = 'train'").persist()
    cfg = M.Rounds(0.3, 1.0, 2, 8, 3, None)
    a, b = quadratic.train(ex, Linear(2), M.personal_geomed(), cfg), R.run_rounds(ex, Linear(2), M.personal_geomed(), cfg)
    assert np.allclose(a.g, b.g, atol=1e-12)
    assert np.allclose([r.w for r in a.state.orderBy("party_id").collect()], [r.w for r in b.state.orderBy("party_id").collect()], atol=1e-12)


def test_planner():
    assert aggregator(Regulariser("sq"), 10**6, 10**6).form == "mean"
    assert aggregator(Regulariser("l1"), 100, 1000).form == "gathered"
    assert aggregator(Regulariser("l1"), 10**6, 10**4).form == "by_coordinate"
    assert aggregator(Regulariser("l2"), 10**6, 10**4).form == "by_norm"
    assert sufficient_statistics("Linear", 8, True)
    assert not sufficient_statistics("Softmax", 8, True)
    assert not M.Rounds(0.02, 15.0).advised
    assert M.Rounds(0.01, 5.0).advised


def test_distributed_centres_match_the_local_ones(spark):
    from parley.functions import centres as C

    w = np.random.default_rng(2).normal(size=(13, 4))
    w[0] = 50
    df = spark.createDataFrame([(k, [float(a) for a in r]) for k, r in enumerate(w)], "party_id long, w array<double>")
    vec = lambda g: np.array([r.g for r in g.orderBy("coord").collect()])
    assert np.allclose(vec(A.mean(df)), w.mean(0))
    assert np.allclose(vec(A.median_between_bounds(df, 5)), np.median(w, axis=0))
    assert np.allclose(vec(A.median_between_bounds(df.where("party_id < 4"), 100)), np.median(w[:4], axis=0))
    assert np.allclose(vec(A.plain_centre(df, "l1", 0.5)[0]), C.plain(w, "l1", 0.5)[0], atol=1e-6)
    assert np.allclose(vec(A.coordinate_median(df)), np.median(w, axis=0))
    assert np.allclose(vec(A.smoothed_coordinate_median(df, 0.1)), C.coordinate(w, 0.1), atol=1e-9)
    assert np.allclose(vec(A.geometric_median(df, 0.1)[0]), C.geometric(w, 0.1)[0], atol=1e-7)
    even = df.where("party_id > 8")
    assert np.allclose(vec(A.smoothed_coordinate_median(even, 0.1)), C.coordinate(w[9:], 0.1), atol=1e-9)


def test_bucketed_examples_need_no_exchange(spark):
    from parley.sources.stores import bucketed

    spark.sql("DROP TABLE IF EXISTS parley_bucketed")
    t = bucketed(spark.range(1000).selectExpr("id % 20 AS party_id", "id AS pos"), "parley_bucketed", 4)
    plan = t.groupBy("party_id").applyInPandas(lambda f: f.head(1), t.schema)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan
    spark.sql("DROP TABLE parley_bucketed")


@pytest.mark.parametrize("size", [3, 650])
def test_change_at_aggregation_of_models_of_any_size(spark, size):
    rng = np.random.default_rng(8)
    w, g = rng.normal(5, 2, (7, size)), rng.normal(size=size)
    solved = spark.createDataFrame([(k, row.tolist()) for k, row in enumerate(w)], "party_id long, w array<double>").repartition(4)
    change = 0.5 * (g - w)
    assert R.change_at_aggregation(solved, g, 0.5) == pytest.approx((change.mean(), change.std()))
    assert R.change_at_aggregation(solved, g, 0.0) == (0.0, 0.0)
