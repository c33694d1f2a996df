"""Recovery of planted states, nodes and links; the distributed path equals the local one."""

import numpy as np
import pytest

from nodeweave.functions.states import Options, fit_local
from nodeweave.operators import estimators as est
from nodeweave.operators import experiments as exp
from nodeweave.operators import measures, moments
from nodeweave.operators.model import NetworkModel
from nodeweave.plans import planner
from nodeweave.functions.precision import sparse_precision
from nodeweave.sources.planted import draw, plant_signals, plant_truth


@pytest.mark.parametrize("update", ["multiplicative", "disjoint"])
def test_recovery(update):
    truth = plant_truth(2, 5, 70, 1)
    x, s = draw(truth, np.arange(2000), 0.0, 3)
    fit = fit_local(x, Options(n_restarts=3, max_iter=40, membership_update=update))
    got = exp.score_model(NetworkModel(fit.params, fit.mass, fit.loss), np.argmax(exp.responsibilities(x, fit.params), axis=1), truth, s)
    assert got["state_purity"] >= 0.9 and got["node_purity"] >= 0.9


def test_proposal_wins_on_planted_data():
    rows = exp.run_cell(exp.SCENARIOS["samples"][2] | {"scenario": "samples"}, 0, np.arange(2000))
    assert len(rows) == len(exp.METHODS) * 6
    by = {(r[3], r[5]): r[6] for r in rows}
    for metric in ("edge_f1", "node_purity"):
        assert by["mixture", metric] >= max(by[m, metric] for m in exp.METHODS)


def test_truths_agree_under_the_invariant_construction():
    t = plant_truth(2, 4, 24, 0)
    for j in range(2):
        h = np.eye(4)[t.node[j]]
        h /= np.linalg.norm(h, axis=0)
        direct, inverse = h.T @ t.theta[j] @ h, np.linalg.inv(h.T @ np.linalg.inv(t.theta[j]) @ h)
        assert np.allclose(direct, inverse) and np.allclose(direct, t.node_precision[j])
    r = plant_truth(2, 4, 40, 0, construction="random")
    assert all(np.linalg.eigvalsh(x).min() > 0 for x in r.theta)


def test_draws_do_not_depend_on_order():
    t = plant_truth(2, 3, 12, 0)
    a, sa = draw(t, [5, 9, 2], 1.0, 1)
    b, sb = draw(t, [2, 5], 1.0, 1)
    assert np.allclose(a[[2, 0]], b) and (sa[[2, 0]] == sb).all()


def test_distributed_equals_local(spark):
    truth = plant_truth(2, 3, 20, 0)
    ids = spark.range(600).withColumnRenamed("id", "sample_id")
    rows = plant_signals(ids.repartition(5), truth, 0.0, 2).persist()
    x, _ = draw(truth, np.arange(600), 0.0, 2)
    opt = dict(m=2, k=3, l1=0.05, max_iter=6, n_restarts=2, membership_update="disjoint")
    far, near = est.StateNetworkMixture(**opt).fit(rows), fit_local(x, Options(**opt))
    assert np.isclose(far.loss, near.loss, rtol=1e-9)
    a, n = moments.gram(rows)
    assert n == 600 and np.allclose(a, x.T @ x / 600)
    assert np.isclose(est.negative_log_likelihood(rows, far), exp.fit_local(x, Options(**opt)).loss - 0.5 * 0.05 * sum(m * np.abs(o).sum() for m, o in zip(near.mass, near.params.omega, strict=True)), rtol=1e-6)


def test_strategies_agree(spark):
    from nodeweave.functions.states import Params
    from nodeweave.operators.moments import state_passes

    truth = plant_truth(2, 3, 15, 0)
    rows = plant_signals(spark.range(300).withColumnRenamed("id", "sample_id"), truth, 0.0, 2).persist()
    w = np.random.default_rng(0).random((15, 3))
    p = Params(np.array([0.5, 0.5]), [w, w + 0.1], [np.eye(3)] * 2, np.ones(2))
    opt = Options(m=2, k=3)
    g, q = state_passes(rows, [p], [opt], True)[0], state_passes(rows, [p], [opt], False)[0]
    for j in range(2):
        assert np.allclose(g.gram[j] @ p.w[j], q.product[j], rtol=1e-9)
        assert np.isclose(np.trace(g.gram[j]), g.square[j])
    sql = {(r["i"], r["j"]): r["value"] for r in moments.sql_gram(moments.long_form(rows)).collect()}
    a, _ = moments.gram(rows)
    assert all(np.isclose(a[i, j], v) for (i, j), v in sql.items())


def test_model_roundtrip(spark, tmp_path):
    truth = plant_truth(2, 3, 12, 0)
    rows = plant_signals(spark.range(200).withColumnRenamed("id", "sample_id"), truth).persist()
    model = est.StateNetworkMixture(2, 3, max_iter=3).fit(rows)
    model.save(spark, str(tmp_path / "m"))
    back = NetworkModel.load(spark, str(tmp_path / "m"))
    a = {r["sample_id"]: r["loglik"] for r in model.transform(rows).collect()}
    b = {r["sample_id"]: r["loglik"] for r in back.transform(rows).collect()}
    assert a.keys() == b.keys() and all(np.isclose(a[k], b[k]) for k in a)
    edges, nodes = est.report(spark, model)
    assert nodes.agg({"size": "sum"}).first()[0] == 24 and edges.columns == ["state", "a", "b", "weight", "partial_corr"]


def test_bad_signals_are_errors(spark):
    good = [(1, [1.0, 2.0]), (2, [1.0, 3.0])]
    for bad in ([1.0], [1.0, float("nan")], [1.0, None], None):
        df = spark.createDataFrame([*good, (3, bad)], "sample_id long, x array<double>")
        with pytest.raises(ValueError):
            moments.assert_uniform_length(df)


def test_planner():
    assert planner.choose_strategy(None, 100, 5, 2) == "gram"
    assert planner.choose_strategy(10**10, 3281, 6, 2, "signed") == "product"
    assert planner.choose_strategy(None, 10_000, 5, 2) == "product" and planner.moment_mode_for("product", "sign_split") == "signed"
    assert "product" in planner.explain_strategy(10**9, 3281, 6, 2, "signed")


def test_pass_plan_has_one_exchange_per_merge(spark):
    rows = plant_signals(spark.range(50).withColumnRenamed("id", "sample_id"), plant_truth(2, 3, 12, 0))
    plan = rows._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "MapInArrow" in plan


def test_language_states_beat_the_majority(spark, sf):
    _, scored = exp.language_workload(spark, sf, max_iter=8, n_restarts=2)
    majority = max(r["count"] for r in scored.groupBy("lang").count().collect()) / scored.count()
    assert measures.purity(scored, "state_hat", "lang").first()[0] >= majority


def test_kmeans_start(spark):
    rows = plant_signals(spark.range(200).withColumnRenamed("id", "sample_id"), plant_truth(2, 3, 12, 0)).persist()
    model = est.StateNetworkMixture(2, 3, init="kmeans", max_iter=3).fit(rows)
    assert np.isfinite(model.loss) and np.isclose(model.params.shares.sum(), 1)


def test_many_variables_without_a_square_matrix(spark, monkeypatch):
    """6,000 variables with the default moments: the product strategy starts from a sketch and separates the planted groups."""
    from nodeweave.functions import states

    p, n = 6000, 60
    rng = np.random.default_rng(0)
    node = np.arange(p) % 3
    x = rng.normal(size=(n, 3))[:, node] + 0.5 * rng.normal(size=(n, p))
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "sample_id long, x array<double>").repartition(4)
    largest = []
    seen = moments._summed
    monkeypatch.setattr(moments, "_summed", lambda r: (lambda got: largest.append(max(len(v) for v in got.values())) or got)(seen(r)))
    monkeypatch.setattr(states, "init_membership", lambda *a: (_ for _ in ()).throw(AssertionError("a p x p start")))
    model = est.StateNetworkMixture(1, 3, 0.1, l1_relative=True, max_iter=3).fit(rows)
    assert model.settings["strategy"] == "product" and model.settings["moment_mode"] == "signed"
    assert max(largest) < 70 * p  # numbers that reach the driver at once
    label = model.params.w[0].argmax(axis=1)
    assert measures.local_purity(label, node) > 0.99 and np.isclose(model.mass.sum(), n)


def test_variables_apart_in_tiles(spark):
    """The tiled graphical lasso equals the one on the whole moment."""
    rng = np.random.default_rng(1)
    x = rng.normal(size=(80, 9)) @ np.kron(np.eye(3), np.array([[1, 0.7, 0], [0, 1, 0.5], [0, 0, 1]]))
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "sample_id long, x array<double>").repartition(3)
    want = sparse_precision(x.T @ x / 80, 0.25)
    got = np.zeros((9, 9))
    for r in est.SparsePrecision(0.25).fit(rows, block=4).collect():
        got[r["a"], r["b"]] = r["value"]
    assert np.allclose(got, want, atol=1e-6)
