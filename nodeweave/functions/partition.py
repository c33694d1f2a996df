"""Groupings of variables from a moment matrix: k-means, spectral, factorisations, start values, atlases."""

from __future__ import annotations

import numpy as np

from .numeric import psd_clip, unit_columns


def correlation(a):
    d = np.sqrt(np.maximum(np.diag(a), 1e-300))
    return a / np.outer(d, d)


def kmeans(rows, k, seed=0, max_iter=100, starts=8):
    """Labels and centres of the best of several Lloyd runs from spread-out seeds."""
    rng = np.random.default_rng(seed)
    rows = np.asarray(rows, dtype=float)
    n = len(rows)
    k = min(k, n)
    square = (rows**2).sum(axis=1)
    best = (np.inf, None, None)
    for _ in range(starts):
        centres = rows[[rng.integers(n)]]
        while len(centres) < k:
            d = np.maximum(square[:, None] - 2 * rows @ centres.T + (centres**2).sum(axis=1), 0).min(axis=1)
            total = d.sum()
            centres = np.vstack([centres, rows[rng.choice(n, p=d / total) if total > 0 else rng.integers(n)]])
        label = None
        for _ in range(max_iter):
            d = square[:, None] - 2 * rows @ centres.T + (centres**2).sum(axis=1)
            new = d.argmin(axis=1)
            if label is not None and (new == label).all():
                break
            label = new
            for c in range(k):
                own = label == c
                centres[c] = rows[own].mean(axis=0) if own.any() else rows[d.min(axis=1).argmax()]
        cost = float(np.maximum(d[np.arange(n), label], 0).sum())
        if cost < best[0]:
            best = (cost, label, centres)
    return best[1], best[2]


def kmeans_variables(a, k, seed=0):
    """Node of each variable: k-means over rows of the absolute correlation."""
    return kmeans(np.abs(correlation(a)), k, seed)[0]


def spectral_nodes(a, k, seed=0):
    """Node of each variable: k-means on the leading eigenvectors of the normalised absolute correlation."""
    c = np.abs(correlation(a))
    d = 1 / np.sqrt(np.maximum(c.sum(axis=1), 1e-12))
    _, vectors = np.linalg.eigh(c * np.outer(d, d))
    top = vectors[:, -k:]
    return kmeans(top / np.maximum(np.linalg.norm(top, axis=1, keepdims=True), 1e-12), k, seed)[0]


def indicators(label, k):
    out = np.zeros((len(label), k))
    out[np.arange(len(label)), label] = 1.0
    return out


def init_membership(a, k, offset=0.2, seed=0):
    """Indicators of k-means nodes plus an offset, so that no weight starts at the absorbing zero."""
    return offset_membership(kmeans_variables(a, k, seed), k, offset)


def offset_membership(label, k, offset=0.2):
    """Unit columns of a grouping's indicators plus an offset."""
    return unit_columns(indicators(label, k) + offset)


def nmf(a, k, seed=0, max_iter=500, tol=1e-9, start=None):
    """Non-negative F, G with A close to F G', and the errors; multiplicative steps never raise the error."""
    rng = np.random.default_rng(seed)
    a = np.maximum(a, 0.0)
    f, g = (x.copy() for x in start) if start is not None else (rng.random((a.shape[0], k)) + 0.1, rng.random((a.shape[1], k)) + 0.1)
    errors = []
    for _ in range(max_iter):
        f *= (a @ g) / np.maximum(f @ (g.T @ g), 1e-12)
        g *= (a.T @ f) / np.maximum(g @ (f.T @ f), 1e-12)
        errors.append(float(((a - f @ g.T) ** 2).sum()))
        if len(errors) > 1 and errors[-2] - errors[-1] < tol * max(errors[0], 1e-300):
            break
    return f, g, errors


def symmetric_nmf(a, k, seed=0, max_iter=500, tol=1e-9, start=None):
    """Non-negative F with A close to F F', by damped steps (half of the ratio)."""
    rng = np.random.default_rng(seed)
    a = np.maximum(a, 0.0)
    f = start.copy() if start is not None else rng.random((len(a), k)) * np.sqrt(a.mean() / k) * 2 + 1e-3
    errors = []
    for _ in range(max_iter):
        f *= 0.5 + 0.5 * (a @ f) / np.maximum(f @ (f.T @ f), 1e-12)
        errors.append(float(((a - f @ f.T) ** 2).sum()))
        if len(errors) > 1 and abs(errors[-2] - errors[-1]) < tol * max(errors[0], 1e-300):
            break
    return f, errors


def tri_factor(a, k, seed=0, max_iter=300, tol=1e-8, w=None):
    """W (non-negative, unit columns, nearly orthogonal) and S with |A| close to W S W', and the errors; ``w``: start."""
    a = np.abs(np.asarray(a, dtype=float))
    w = init_membership(a, k, seed=seed) if w is None else w
    s = w.T @ a @ w
    errors = []
    for _ in range(max_iter):
        aws = a @ w @ s
        w = unit_columns(w * np.sqrt(aws / np.maximum(w @ (w.T @ aws), 1e-12)))
        # the least-squares middle factor for this W; W'AW where W'W = I
        gram = w.T @ w + 1e-10 * np.eye(k)
        left = np.linalg.solve(gram, w.T @ a @ w)
        s = np.maximum(np.linalg.solve(gram, left.T).T, 0.0)
        errors.append(float(((a - w @ s @ w.T) ** 2).sum()))
        if len(errors) > 1 and abs(errors[-2] - errors[-1]) < tol * max(errors[0], 1e-300):
            break
    return w, s, errors


def tri_factor_edges(s, threshold=0.1):
    """Node links of the middle factor: scaled to unit diagonal, off-diagonals above the threshold."""
    d = np.sqrt(np.maximum(np.diag(s), 1e-300))
    c = s / np.outer(d, d)
    k = len(s)
    return [(i, j, float(c[i, j])) for i in range(k) for j in range(i + 1, k) if c[i, j] > threshold]


def absolute_moment(a):
    """|A| made positive semidefinite, as an elementwise absolute matrix need not be."""
    return psd_clip(np.abs(a))
