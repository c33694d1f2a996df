"""Sparse Gaussian precision: -log det P + tr(S P) + l1 * sum |P|, one or several groups."""

from __future__ import annotations

import numpy as np

from .numeric import soft_threshold, symmetric


def blocks(s, l1):
    """Index arrays of the components of |S_ab| > l1; the problem separates over them exactly."""
    n = len(s)
    label = np.arange(n)
    link = np.abs(s) > l1
    for a in range(n):
        for b in np.flatnonzero(link[a, :a]):
            old, new = label[a], label[b]
            if old != new:
                label[label == old] = new
    return [np.flatnonzero(label == c) for c in np.unique(label)]


def _prox_logdet(m, rho):
    """argmin -log det P + rho/2 ||P - M||^2, by the eigenvalues of M."""
    values, vectors = np.linalg.eigh(symmetric(m))
    return (vectors * ((values + np.sqrt(values**2 + 4 / rho)) / 2)) @ vectors.T


def _solve_block(s, l1, penalize_diagonal, tol, max_iter):
    k = len(s)
    weight = np.full((k, k), float(l1))
    if not penalize_diagonal:
        np.fill_diagonal(weight, 0.0)
    if k == 1:
        return np.array([[1 / max(s[0, 0] + weight[0, 0], 1e-12)]])
    scale = np.sqrt(np.maximum(np.diag(s), 1e-12))
    z = np.diag(1 / (scale**2 + l1 + 1e-12))
    u = np.zeros_like(z)
    rho = float(np.mean(scale**2) + l1) ** 2 + 1e-12
    for _ in range(max_iter):
        p = _prox_logdet(z - u - s / rho, rho)
        before = z
        z = symmetric(soft_threshold(p + u, weight / rho))
        u = u + p - z
        primal, dual = np.abs(p - z).max(), rho * np.abs(z - before).max()
        size = max(1.0, np.abs(z).max())
        if primal <= tol * size and dual <= tol * max(1.0, np.abs(s).max()):
            break
        if primal * rho > 10 * dual:
            rho, u = rho * 2, u / 2
        elif dual > 10 * primal * rho:
            rho, u = rho / 2, u * 2
    return z if np.linalg.eigvalsh(z).min() > 0 else p


def sparse_precision(s, l1, penalize_diagonal=True, tol=1e-9, max_iter=2000, jitter=0.0):
    """The sparse precision of a moment matrix, block by block; l1 = 0 gives the inverse."""
    s = symmetric(np.asarray(s, dtype=float)) + jitter * np.eye(len(s))
    if l1 == 0:
        return symmetric(np.linalg.inv(s))
    out = np.zeros_like(s)
    for own in blocks(s, l1):
        out[np.ix_(own, own)] = _solve_block(s[np.ix_(own, own)], l1, penalize_diagonal, tol, max_iter)
    return out


def two_node_precision(s, l1):
    """Closed form for two nodes: threshold the off-diagonal, add l1 to the diagonal, invert."""
    off = soft_threshold(s[0, 1], l1)
    return np.linalg.inv(np.array([[s[0, 0] + l1, off], [off, s[1, 1] + l1]]))


def optimality_residual(p, s, l1, penalize_diagonal=True):
    """Largest violation of the stationarity conditions; zero at the optimum."""
    grad = np.linalg.inv(p) - s
    weight = np.full(p.shape, float(l1))
    if not penalize_diagonal:
        np.fill_diagonal(weight, 0.0)
    on = p != 0
    return float(max(np.abs(grad - weight * np.sign(p))[on].max(initial=0.0), np.maximum(np.abs(grad) - weight, 0)[~on].max(initial=0.0)))


def joint_precision(moments, l1, l2, penalty="group", weights=None, tol=1e-7, max_iter=1000):
    """Precisions of several groups with a coupling penalty: ``group`` (shared zeros) or ``fused`` (equal values).

    Minimises the sum of weighted likelihood terms plus l1 * sum |P_j| and, with
    ``group``, l2 * the norm over groups of each off-diagonal entry, or with ``fused`` l2 * sum of
    absolute differences between groups.
    """
    s = np.stack([symmetric(np.asarray(x, dtype=float)) for x in moments])
    m, k, _ = s.shape
    w = np.ones(m) if weights is None else np.asarray(weights, dtype=float) / np.mean(weights)
    rho = 1.0
    z = np.stack([np.diag(1 / (np.diag(x) + l1 + 1e-12)) for x in s])
    u = np.zeros_like(z)
    off = ~np.eye(k, dtype=bool)
    for _ in range(max_iter):
        p = np.stack([_prox_logdet(z[j] - u[j] - w[j] * s[j] / rho, rho / w[j]) for j in range(m)])
        before, a = z, p + u
        if penalty == "group":
            z = soft_threshold(a, l1 / rho)
            norm = np.sqrt((z**2).sum(axis=0))
            shrink = np.maximum(1 - (l2 / rho) / np.maximum(norm, 1e-300), 0.0)
            z = np.where(off, z * shrink, z)
        elif penalty == "fused":
            z = soft_threshold(np.where(off, _fuse(a, l2 / rho), a), l1 / rho)
        else:
            raise ValueError(f"unknown penalty {penalty!r}")
        z = (z + z.transpose(0, 2, 1)) / 2
        u = u + p - z
        if max(np.abs(p - z).max(), rho * np.abs(z - before).max()) < tol:
            break
    return z


def _fuse(a, t):
    """Prox of t * sum over pairs |a_i - a_j| along axis 0: sort, shift by rank, average what crosses."""
    m = a.shape[0]
    if m == 1 or t == 0:
        return a
    order = np.argsort(a, axis=0, kind="stable")
    shift = t * (m - 1 - 2 * np.arange(m)).reshape(-1, *[1] * (a.ndim - 1))
    y = np.take_along_axis(a, order, axis=0) + shift
    # isotonic regression over m values (pool adjacent violators), for all entries
    flat = y.reshape(m, -1).T.copy()
    for row in flat:
        level, weight = [], []
        for x in row:
            level.append(x)
            weight.append(1)
            while len(level) > 1 and level[-2] > level[-1]:
                b, wb = level.pop(), weight.pop()
                level[-1] = (level[-1] * weight[-1] + b * wb) / (weight[-1] + wb)
                weight[-1] += wb
        row[:] = np.repeat(level, weight)
    out = np.empty_like(a)
    np.put_along_axis(out, order, flat.T.reshape(a.shape), axis=0)
    return out
