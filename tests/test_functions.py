"""Closed forms, stationarity, invariants and guards of the local matrix functions."""

import itertools

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from nodeweave.functions import membership as mem
from nodeweave.functions import numeric, partition, precision, states


def moment(k, n=60, seed=0):
    x = np.random.default_rng(seed).normal(size=(n, k))
    x[:, 0] += 0.7 * x[:, -1]
    return x.T @ x / n


@pytest.mark.parametrize("l1", [0.01, 0.1, 0.6])
def test_two_nodes_closed_form(l1):
    s = moment(2)
    assert np.allclose(precision.sparse_precision(s, l1), precision.two_node_precision(s, l1), atol=1e-7)


@pytest.mark.parametrize("k", [2, 5, 11])
@pytest.mark.parametrize("diagonal", [True, False])
def test_stationarity(k, diagonal):
    s = moment(k, seed=k)
    p = precision.sparse_precision(s, 0.08, diagonal)
    assert precision.optimality_residual(p, s, 0.08, diagonal) < 1e-5
    assert np.linalg.eigvalsh(p).min() > 0 and np.allclose(p, p.T)


def test_penalty_limits():
    s = moment(4)
    assert np.allclose(precision.sparse_precision(s, 0), np.linalg.inv(s))
    top = np.abs(s - np.diag(np.diag(s))).max()
    assert np.allclose(precision.sparse_precision(s, top), np.diag(1 / (np.diag(s) + top)))


def test_block_screening_is_exact():
    s = np.zeros((6, 6))
    s[:3, :3], s[3:, 3:] = moment(3), moment(3, seed=2)
    assert sorted(map(tuple, precision.blocks(s, 0.0001)))[0][0] == 0
    whole = precision._solve_block(s, 0.05, True, 1e-10, 5000)
    assert np.allclose(precision.sparse_precision(s, 0.05), whole, atol=1e-6)


def test_joint_without_coupling_is_separate():
    s = [moment(4, seed=i) for i in range(3)]
    for kind in ("group", "fused"):
        z = precision.joint_precision(s, 0.1, 0.0, kind)
        assert all(np.allclose(z[j], precision.sparse_precision(s[j], 0.1), atol=1e-5) for j in range(3))
    strong = precision.joint_precision(s, 0.05, 5.0, "fused")
    assert np.allclose(strong[0][0, 1], strong[2][0, 1], atol=1e-4)


@settings(max_examples=40, deadline=None)
@given(st.integers(1, 5), st.integers(1, 6), st.integers(0, 10_000))
def test_assignment_is_optimal(rows, more, seed):
    cols = max(rows, more)
    g = np.random.default_rng(seed).random((rows, cols))
    got = numeric.assignment(g)
    best = max(sum(g[i, p[i]] for i in range(rows)) for p in itertools.permutations(range(cols), rows))
    assert len(set(got)) == rows and np.isclose(g[np.arange(rows), got].sum(), best)


@settings(max_examples=30, deadline=None)
@given(st.integers(2, 8), st.integers(1, 3), st.sampled_from(["sign_split", "absolute", "signed"]), st.integers(0, 1000))
def test_membership_update_invariants(p, k, mode, seed):
    rng = np.random.default_rng(seed)
    x = rng.normal(size=(30, p))
    a, w = x.T @ x / 30, numeric.unit_columns(rng.random((p, k)) + 0.05)
    w[0, 0] = 0.0
    omega = precision.sparse_precision(numeric.symmetric(w.T @ a @ w) + 0.01 * np.eye(k), 0.05)
    new = mem.update_membership(w, a, omega, mode)
    assert (new >= 0).all() and new[0, 0] == 0 and np.allclose(np.linalg.norm(new, axis=0)[1:], 1)


def test_product_rule_equals_signed_rule():
    a, w = moment(6), numeric.unit_columns(np.random.default_rng(1).random((6, 2)))
    omega = np.array([[1.0, -0.3], [-0.3, 2.0]])
    for x, y in zip(mem.ratio_terms(w, a, omega, "signed"), mem.ratio_from_product(w, a @ w, omega), strict=True):
        assert np.allclose(x, y)


def test_scale_is_free_in_the_trace():
    a, w, o = moment(5), np.random.default_rng(2).random((5, 2)), np.array([[1.0, 0.2], [0.2, 1.5]])
    assert np.isclose(np.trace(w.T @ a @ w @ o), np.trace((3 * w).T @ a @ (3 * w) @ (o / 9)))


def test_coherent_pairs_show_the_degeneracy_of_the_projected_objective():
    """Two pairs with correlation 0.6: the crossed grouping has the lower projected objective."""
    a = np.kron(np.eye(2), np.array([[1.0, 0.6], [0.6, 1.0]]))
    true = np.array([[1, 0], [1, 0], [0, 1], [0, 1]]) / np.sqrt(2)
    # projected log det of a node that carries its pair's sum, and of one that carries differences
    assert np.isclose(numeric.safe_logdet(true.T @ a @ true), 2 * np.log(1.6))
    apart = np.array([[1, 0], [-1, 0], [0, 1], [0, -1]]) / np.sqrt(2)
    crossed = np.column_stack([true[:, 0], apart[:, 0]])
    assert np.isclose(numeric.safe_logdet(crossed.T @ a @ crossed), np.log(1 - 0.36))
    assert np.log(0.64) < 2 * np.log(1.6)


def test_factorisation_errors_fall():
    a = np.abs(moment(12, seed=3))
    for errors in (partition.nmf(a, 3)[2], partition.symmetric_nmf(a, 3)[1]):
        assert all(y <= x * (1 + 1e-7) for x, y in zip(errors, errors[1:], strict=False))
    w, s, _ = partition.tri_factor(a, 3)
    d = mem.disjoint(w)
    assert np.allclose(d.T @ d, np.eye(3))


def test_start_membership_has_no_zero():
    assert (partition.init_membership(moment(8), 3) > 0).all()


def test_soft_start():
    r = states.soft_start(np.arange(1000), 3, 1)
    assert np.allclose(r.sum(axis=1), 1) and np.allclose(r.max(axis=1), 0.9) and states.soft_start([1, 2], 1, 0).min() == 1.0


@pytest.mark.parametrize("k", [1, 3])
@pytest.mark.parametrize("m", [1, 2])
def test_small_and_degenerate_fits(m, k):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(40, 3))
    x[:, 2] = 0.0 if k == 1 else x[:, 2]
    fit = states.fit_local(np.vstack([x, x]), states.Options(m=m, k=k, max_iter=5))
    assert np.isfinite(fit.loss) and np.isclose(fit.params.shares.sum(), 1)


def test_fewer_samples_than_variables():
    x = np.random.default_rng(0).normal(size=(10, 30))
    assert np.isfinite(states.fit_local(x, states.Options(m=2, k=3, max_iter=4)).loss)


def test_loss_never_rises_with_frozen_nodes_and_fixed_penalty():
    x = np.random.default_rng(5).normal(size=(300, 6)) * np.repeat([[1, 1, 1, 3, 3, 3]], 300, axis=0)
    opt = states.Options(m=2, k=3, l1=0.05, membership_update="frozen", density="projected", penalty_scale="global", max_iter=15, tol=0, inner_max_iter=1)
    w = numeric.unit_columns(partition.indicators(np.array([0, 0, 1, 1, 2, 2]), 3))
    values = [t[2] for t in states.fit_local(x, opt, w0=w).trace]
    assert all(b <= a + 1e-5 * abs(a) for a, b in zip(values, values[1:], strict=False))


def test_zero_mean_mixture_reduces_to_one_gaussian():
    x = np.random.default_rng(6).normal(size=(500, 3))
    opt = states.Options(m=1, k=3, l1=0.0, membership_update="frozen", density="projected", max_iter=2)
    fit = states.fit_local(x, opt, w0=np.eye(3))
    assert np.allclose(np.linalg.inv(fit.params.omega[0]), x.T @ x / 500, atol=1e-5)


def test_label_permutation_leaves_loss():
    x = np.random.default_rng(7).normal(size=(50, 4))
    w = [np.eye(4)[:, :2], np.eye(4)[:, 2:]]
    p = states.Params(np.array([0.3, 0.7]), w, [np.eye(2), 2 * np.eye(2)], np.array([1.0, 2.0]))
    q = states.Params(p.shares[::-1], w[::-1], p.omega[::-1], p.tau[::-1])
    assert np.isclose(states.em_pass(x, p, True).nll, states.em_pass(x, q, True).nll)
    assert np.allclose(states.responsibilities(x, p).sum(axis=1), 1)


def test_states_in_threads_give_the_same_fit():
    x = np.random.default_rng(8).normal(size=(200, 6))
    a, b = (states.fit_local(x, states.Options(m=3, k=2, max_iter=4, parallel_states=p)) for p in (False, True))
    assert a.loss == b.loss


def test_unguarded_step_follows_the_formulas():
    """A state of tiny mass gets its own moment's inverse, one without mass none; a guarded step keeps what it had."""
    from nodeweave.functions.states import Options, Params, Stats, m_step

    grams = np.stack([4e-9 * np.diag([2.0, 5.0]), 10 * np.eye(2)])
    start = Params(np.array([0.5, 0.5]), [np.eye(2)] * 2, [3 * np.eye(2)] * 2, np.ones(2), "projected")
    plain = Options(m=2, k=2, l1=0.0, density="projected", membership_update="frozen", refresh=(), guard=False)
    got = m_step(Stats(np.array([4e-9, 10.0]), np.ones(2), 0.0, 10, grams), start, plain)
    assert np.allclose(got.omega[0], np.diag([0.5, 0.2])) and np.isclose(got.shares[0], 4e-10)
    none = m_step(Stats(np.array([0.0, 10.0]), np.ones(2), 0.0, 10, np.stack([np.zeros((2, 2)), 10 * np.eye(2)])), start, plain)
    assert np.isnan(none.omega[0]).all() and none.shares[0] == 0 and np.allclose(none.omega[1], np.eye(2))
    flat = m_step(Stats(np.array([1.0, 10.0]), np.ones(2), 0.0, 11, np.stack([np.diag([1.0, 0.0]), 10 * np.eye(2)])), start, plain)
    assert np.isnan(flat.omega[0]).all()
